"""BPE encoding by forced-boundary splitting, and decoding.

A merge can only join two symbols if their concatenation is a vocabulary token, so two neighbouring
bytes that no token holds inside it always stay apart. Those byte pairs cut a pre-token into
fragments that are encoded independently; their ids are concatenated. Fragments, pre-tokens and
space-separated chunks repeat a lot, so each level has a bounded cache in the worker process. Decoding
starts from the ids.

Covers vocabulary files of the ``tokenizers`` format with an NFC, white-space and lower-case normaliser, a
removing split and byte-level symbols with an end-of-word suffix.

Defined cases: null text is encoded as empty (no ids, empty decoded text); repeated rows are encoded alike, an empty table
gives an empty result; columns of the names of the result are replaced; special tokens in a text
become their ids, as the library does; texts with characters whose class may differ between Unicode
versions are split by the library's own pre-tokeniser; other columns pass through.
"""

from __future__ import annotations

import hashlib
import heapq
import json
import os
import re
import unicodedata
from array import array
from collections.abc import Callable, Iterator, Sequence
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import SparkFiles
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from mediarel.llm import common

#: Entries of the caches of a worker at most: fragments and words, chunks, chunks of the library. An entry has at most ``CACHED_CHARS``
#: characters and takes about 170 bytes, so the caches stay below 100 MB here and 200 MB with the library.
CACHE_ENTRIES = 40_000
CHUNK_ENTRIES = 450_000
LIBRARY_ENTRIES = 1_200_000
CACHED_CHARS = 32
#: Symbols up to which a fragment is merged by looking at every pair again; a longer one uses a heap.
SHORT = 24
#: Texts that are Python strings at a time.
ROWS = 64

#: Fixed values of the vocabulary file's format: bytes that stand for themselves as symbols.
_PLAIN_BYTES = (*range(33, 127), *range(161, 173), *range(174, 256))


def byte_symbols() -> list[str]:
    """Symbol of each byte: plain bytes are themselves, the others take code points from 256 on."""
    others = iter(range(256, 512))
    return [chr(b) if b in _PLAIN_BYTES else chr(next(others)) for b in range(256)]


def vocabulary_path() -> str:
    """Default vocabulary: the public word-end BPE file of this machine."""
    import public_tokenizers

    return public_tokenizers.path("word_bpe_49k.json")


class BoundedCache(dict):
    """Keeps what comes first, up to a bound; starts anew once it has turned away four times that many entries.

    Words repeat by a steep law, so the first ones are the frequent ones; a text of another kind turns so many away that the cache adapts.
    """

    def __init__(self, entries: int):
        super().__init__()
        self.entries, self.refused = entries, 0

    def put(self, key, value) -> None:
        if len(self) >= self.entries:
            self.refused += 1
            if self.refused <= 4 * self.entries:
                return
            self.clear()
            self.refused = 0
        self[key] = value

    def put_all(self, found: dict) -> None:
        if len(self) >= self.entries:
            self.refused += len(found)
            if self.refused <= 4 * self.entries:
                return
            self.clear()
            self.refused = 0
        self.update((k, v) for k, v in found.items() if len(k) <= CACHED_CHARS)


class ForcedBoundaryBpe:
    """Encoder and decoder over one vocabulary file."""

    def __init__(self, content: str):
        spec = json.loads(content)
        model = spec["model"]
        self.content = content
        self.vocab: dict[str, int] = model["vocab"]
        self.suffix: str = model["end_of_word_suffix"] or ""
        pairs = [tuple(m) if not isinstance(m, str) else tuple(m.split(" ")) for m in model["merges"]]
        self.ranks = {pair: k for k, pair in enumerate(pairs)}
        self.tokens = {i: t for t, i in self.vocab.items()} | {t["id"]: t["content"] for t in spec["added_tokens"]}
        self.word_ends = np.zeros(max(self.tokens) + 1, dtype=bool)
        self.word_ends[[i for i, t in self.tokens.items() if self.suffix and t.endswith(self.suffix)]] = True
        self.special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        self.special_pattern = re.compile("|".join(map(re.escape, sorted(self.special, key=len, reverse=True)))) if self.special else None
        self.symbols = byte_symbols()
        inner = set()
        for token in self.vocab:
            body = token.removesuffix(self.suffix) if self.suffix else token
            inner.update(body[i : i + 2] for i in range(len(body) - 1))
        #: Pairs of symbols that some token holds; any other pair is a forced boundary.
        self.inner = inner
        self.forget()
        # Latin letters, digits and marks whose class no Unicode version moves; others go to the library.
        self.plain = re.compile(r"[\x00-\x1b\x20-ɏ‐-‧€]*\Z")
        self.split = re.compile(r"'s|'t|'re|'ve|'m|'ll|'d|[^\W\d_²³¹¼½¾]+|[\d²³¹¼½¾]|(?:[^\w\s]|_)+")
        self.marked = re.compile(r"([^\W\d_²³¹¼½¾]+)((?:[^\w\s']|_)+)\Z")
        self._library = None

    def forget(self) -> None:
        """Empty the caches."""
        self.fragments, self.words = BoundedCache(CACHE_ENTRIES), BoundedCache(CACHE_ENTRIES)
        self.chunks, self.library_chunks = BoundedCache(CHUNK_ENTRIES), BoundedCache(LIBRARY_ENTRIES)

    def library(self):
        if self._library is None:
            os.environ["TOKENIZERS_PARALLELISM"] = "false"
            from tokenizers import Tokenizer

            self._library = Tokenizer.from_str(self.content)
        return self._library

    def cut(self, word: str) -> list[str]:
        """Fragments of a word between its forced boundaries."""
        inner = self.inner
        at = [i for i in range(1, len(word)) if word[i - 1 : i + 1] not in inner]
        if not at:
            return [word]
        at = [0, *at, len(word)]
        return [word[a:b] for a, b in zip(at, at[1:], strict=False)]

    def merge(self, fragment: str, last: bool) -> bytes:
        """Ids of one fragment: lowest rank first, leftmost first among equals; n log n in its length if that is large."""
        parts: list[str | None] = list(fragment)
        if last:
            parts[-1] += self.suffix
        if len(parts) <= SHORT:
            rank, none = self.ranks.get, len(self.ranks)
            found = [rank(p, none) for p in zip(parts, parts[1:])]  # noqa: B905
            while found and (least := min(found)) < none:
                i = found.index(least)
                parts[i] += parts.pop(i + 1)
                del found[i]
                # Only the pairs on either side are new.
                if i:
                    found[i - 1] = rank((parts[i - 1], parts[i]), none)
                if i < len(found):
                    found[i] = rank((parts[i], parts[i + 1]), none)
            return array("I", map(self.vocab.__getitem__, parts)).tobytes()
        n = len(parts)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        heap = [(self.ranks[p], i, p) for i in range(n - 1) if (p := (parts[i], parts[i + 1])) in self.ranks]
        heapq.heapify(heap)
        while heap:
            _, i, pair = heapq.heappop(heap)
            j = after[i] if parts[i] is not None else n
            if j >= n or (parts[i], parts[j]) != pair:
                continue
            parts[i] = pair[0] + pair[1]
            parts[j] = None
            after[i] = after[j]
            if after[i] < n:
                before[after[i]] = i
                if (p := (parts[i], parts[after[i]])) in self.ranks:
                    heapq.heappush(heap, (self.ranks[p], i, p))
            if before[i] >= 0 and (p := (parts[before[i]], parts[i])) in self.ranks:
                heapq.heappush(heap, (self.ranks[p], before[i], p))
        return array("I", [self.vocab[p] for p in parts if p is not None]).tobytes()

    def word_ids(self, word: str) -> bytes:
        """Ids of a pre-token, given as text."""
        if (found := self.words.get(word)) is not None:
            return found
        symbols = "".join(map(self.symbols.__getitem__, word.encode("utf-8", "surrogatepass")))
        ids: list[bytes] = []
        pieces = self.cut(symbols)
        for k, piece in enumerate(pieces):
            key = (piece, k == len(pieces) - 1)
            if (part := self.fragments.get(key)) is None:
                part = self.merge(*key)
                if len(piece) <= CACHED_CHARS:
                    self.fragments.put(key, part)
            ids.append(part)
        made = ids[0] if len(ids) == 1 else b"".join(ids)
        if len(word) <= CACHED_CHARS:
            self.words.put(word, made)
        return made

    def pretokens(self, text: str, plain: bool) -> list[str]:
        """Pre-tokens of a normalised text."""
        if plain:
            return self.split.findall(text)
        found = self.library().pre_tokenizer.pre_tokenize_str(text)
        return [text[a:b] for _, (a, b) in found]

    def _chunk(self, chunk: str, plain: bool) -> bytes:
        # A chunk of plain letters is one pre-token.
        made = self.word_ids(chunk) if plain and chunk.isalpha() else b"".join(map(self.word_ids, self.pretokens(chunk, plain)))
        if plain and len(chunk) <= CACHED_CHARS:
            self.chunks.put(chunk, made)
        return made

    def _segment(self, text: str) -> bytes:
        """Ids of a text without special tokens."""
        if self.plain.match(text):
            if not text.isascii():
                text = unicodedata.normalize("NFC", text)
            text = text.lower() if "İ" not in text else self.library().normalizer.normalize_str(text)
            plain = text.isascii() or self.plain.match(text) is not None
        else:
            plain, text = False, self.library().normalizer.normalize_str(text)
        if not plain:
            return self._chunk(text, False)
        chunks = text.split()
        found = list(map(self.chunks.get, chunks))
        if None in found:
            found = [self._chunk(c, True) if ids is None else ids for c, ids in zip(chunks, found, strict=True)]
        return b"".join(found)

    def encode(self, text: str | None) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        if not text:
            return b""
        if self.special_pattern is None or "<|" not in text and not self.special_pattern.search(text):
            return self._segment(text)
        ids, at = [], 0
        for m in self.special_pattern.finditer(text):
            ids += [self._segment(text[at : m.start()]), array("I", [self.special[m[0]]]).tobytes()]
            at = m.end()
        return b"".join([*ids, self._segment(text[at:])])

    def library_ids(self, text: str | None) -> bytes:
        """Ids of one text by the library."""
        return self.library_batch([text])[0]

    def library_batch(self, texts: Sequence[str | None]) -> list[bytes]:
        """Ids of texts by the library: it encodes the chunks between white space that the cache lacks, all of them in one call."""
        known, out, split = self.library_chunks, [b""] * len(texts), {}
        for k, text in enumerate(texts):
            if not text:
                continue
            if not self.plain.match(text) or "İ" in text or "<|" in text and self.special_pattern is not None and self.special_pattern.search(text):
                out[k] = array("I", self.library().encode(text, add_special_tokens=False).ids).tobytes()
                continue
            chunks = (text if text.isascii() else unicodedata.normalize("NFC", text)).lower().split()
            split[k] = chunks, list(map(known.get, chunks))
        missing = {c for chunks, found in split.values() if None in found for c, ids in zip(chunks, found, strict=True) if ids is None}
        # Letters and the marks after them are two pre-tokens, each of which may be known.
        parted = {c: m.groups() for c in missing if (m := self.marked.match(c))}
        known.put_all(self._by_library([t for t in {t for _, t in parted.values()} if t not in known]))
        made = {c: head + tail for c, (h, t) in parted.items() if (head := known.get(h)) is not None and (tail := known.get(t)) is not None}
        made |= self._by_library([c for c in missing if c not in made])
        for k, (chunks, found) in split.items():
            out[k] = b"".join([made[c] if ids is None else ids for c, ids in zip(chunks, found, strict=True)] if None in found else found)
        known.put_all(made)
        return out

    def _by_library(self, chunks: list[str]) -> dict[str, bytes]:
        """Ids of distinct chunks from one text of them all: the last token of every pre-token has the word-end mark."""
        if not chunks:
            return {}
        ids = np.array(self.library().encode_batch_fast([" ".join(chunks)], add_special_tokens=False)[0].ids, dtype="<u4")
        ends = np.flatnonzero(self.word_ends[ids]) + 1
        upto = np.cumsum([1 if c.isalpha() else len(self.split.findall(c)) for c in chunks])
        if upto[-1] != len(ends):
            each = self.library().encode_batch_fast(chunks, add_special_tokens=False)
            return {c: array("I", e.ids).tobytes() for c, e in zip(chunks, each, strict=True)}
        raw, at = ids.tobytes(), (4 * np.concatenate(([0], ends))[np.concatenate(([0], upto))]).tolist()
        return {c: raw[a:b] for c, a, b in zip(chunks, at, at[1:], strict=False)}

    def decode(self, ids: bytes) -> str:
        """Text of ids, special tokens included: their tokens joined by spaces."""
        return " ".join(map(self.tokens.__getitem__, array("I", ids)))


@lru_cache(maxsize=2)
def _loaded(name: str) -> ForcedBoundaryBpe:
    """Encoder of a vocabulary file that the session has distributed; worker processes keep it between tasks."""
    with open(SparkFiles.get(name), encoding="utf-8") as f:
        return ForcedBoundaryBpe(f.read())


def distribute(spark: SparkSession, path: str) -> str:
    """Hand the vocabulary file to all executors; returns its name for ``encoder``."""
    spark.sparkContext.addFile(path)
    return os.path.basename(path)


def encoder(name: str) -> ForcedBoundaryBpe:
    """The worker's encoder."""
    common.claim("bpe", _loaded.cache_clear)
    return _loaded(name)


def _coded(batches: Iterator[pa.RecordBatch], name: str, of: Callable[[ForcedBoundaryBpe, str | None], tuple], kinds: dict[str, pa.DataType]) -> Iterator[pa.RecordBatch]:
    """Batches with the fields of ``of`` in the place of their last column, the text; small blocks are handed on."""
    coder = encoder(name)
    for part in common.slices(batches, ROWS):
        rows = [of(coder, text) for text in part.column(part.num_columns - 1).to_pylist()]
        made = [pa.array([r[k] for r in rows], kind) for k, kind in enumerate(kinds.values())]
        yield pa.RecordBatch.from_arrays([*part.columns[:-1], *made], names=[*part.schema.names[:-1], *kinds])


def _ids_and_text(coder: ForcedBoundaryBpe, text: str | None) -> tuple[int, bytes, str]:
    ids = coder.encode(text)
    return len(ids) // 4, ids, coder.decode(ids)


def _digests(coder: ForcedBoundaryBpe, text: str | None) -> tuple[int, str, str]:
    n, ids, decoded = _ids_and_text(coder, text)
    return n, hashlib.sha256(ids).hexdigest(), hashlib.sha256(decoded.encode("utf-8", "surrogatepass")).hexdigest()


def encoded(docs: DataFrame, path: str | None = None, text: str = "text") -> DataFrame:
    """All columns but ``text``, with ``n_tokens``, ``token_ids`` (binary, little-endian unsigned 32-bit) and ``decoded``, replacing columns of these names."""
    name = distribute(docs.sparkSession, path or vocabulary_path())
    kept = docs.select(*[F.col(f"`{c}`") for c in docs.columns if c not in (text, "n_tokens", "token_ids", "decoded")])
    schema = T.StructType([*kept.schema.fields, T.StructField("n_tokens", T.LongType()), T.StructField("token_ids", T.BinaryType()), T.StructField("decoded", T.StringType())])
    kinds = {"n_tokens": pa.int64(), "token_ids": pa.binary(), "decoded": pa.string()}
    return docs.select(*[F.col(f"`{c}`") for c in kept.columns], text).mapInArrow(lambda batches: _coded(batches, name, _ids_and_text, kinds), schema)


def digests(docs: DataFrame, path: str | None = None) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256: digests are taken where the ids are made, so no ids travel."""
    name = distribute(docs.sparkSession, path or vocabulary_path())
    kept = docs.select("doc_id", "text")
    schema = T.StructType([kept.schema["doc_id"], T.StructField("n_tokens", T.LongType()), T.StructField("ids_sha256", T.StringType()), T.StructField("decoded_sha256", T.StringType())])
    kinds = {"n_tokens": pa.int64(), "ids_sha256": pa.string(), "decoded_sha256": pa.string()}
    return kept.mapInArrow(lambda batches: _coded(batches, name, _digests, kinds), schema)


def op4_bpe_codec(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digests(common.table(spark, sf_dir, "documents"))
