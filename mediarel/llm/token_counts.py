"""Token counts of a unigram segmentation, by dynamic programming that shares prefixes in a trie.

The best segmentation of a prefix does not depend on what follows it, so the forward scores of pre-tokens with
a common prefix agree on it. The distinct pre-tokens of a block go into a trie, every node gets its forward
score and token count once, and ends of pre-tokens store the count. A document adds up the stored counts of its pre-tokens.

Scores of pieces follow their rank in the public vocabulary, ``-ln(rank + shift)``: nothing is trained.
Pre-tokens are words with the vocabulary's word mark in front. Characters that no piece covers
cost one byte token for each of their bytes. Among equal scores the segmentation with fewer tokens counts.

Defined cases: null, empty and blank texts have no tokens; an empty table gives an empty result; repeated rows count alike; a very long word
shares the nodes of its first ``SHARED`` characters and costs time in proportion to its length; other columns pass through, and columns
named ``n_words`` or ``n_tokens`` are replaced.
"""

from __future__ import annotations

import math
import os
from collections.abc import Iterable, Iterator
from functools import lru_cache

import pyarrow as pa
from pyspark import SparkFiles
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from mediarel.llm import common

MARK = "▁"
#: Rank shift of the score: flattens the head as word frequencies do.
SHIFT = 2.7
#: Distinct pre-tokens whose stored counts a worker keeps, and how many share one trie.
KEPT_COUNTS = 500_000
TRIE_WORDS = 40_000
#: Depth of the trie, and bytes of a word whose count is kept.
SHARED = 64


def vocabulary_path() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


class UnigramCounter:
    """Token counts under piece scores; ``unknown`` is the score of a byte token."""

    def __init__(self, scores: dict[str, float], unknown: float):
        self.unknown = unknown
        #: Pieces by their characters from the last to the first; "" holds the score where one begins.
        self.back: dict = {}
        for piece, score in scores.items():
            node = self.back
            for c in reversed(piece):
                node = node.setdefault(c, {})
            node[""] = score
        self.counts: dict[bytes, int] = {}

    @classmethod
    def from_ranks(cls, pieces: Iterable[str]) -> UnigramCounter:
        ranked = list(pieces)
        return cls({p: -math.log(k + SHIFT) for k, p in enumerate(ranked)}, -math.log(len(ranked) + SHIFT))

    def _step(self, word: str, d: int, scores: list[float], counts: list[int]) -> tuple[float, int]:
        """Forward score and tokens of the first ``d`` characters from those of shorter prefixes."""
        size = len(word[d - 1].encode("utf-8", "surrogatepass"))
        best, least = scores[d - 1] + size * self.unknown, counts[d - 1] + size
        node, start = self.back, d
        while start:
            start -= 1
            if (node := node.get(word[start])) is None:
                break
            if (piece := node.get("")) is not None:
                score = scores[start] + piece
                if score > best or score == best and counts[start] + 1 < least:
                    best, least = score, counts[start] + 1
        return best, least

    def count_trie(self, words: Iterable[str]) -> dict[str, int]:
        """Tokens of each distinct word. A node of the trie is [children, forward score, tokens].

        Prefixes up to ``SHARED`` characters are nodes; what a longer word has beyond them goes on from its node's scores.
        """
        root: list = [{}, 0.0, 0]
        ends: dict[str, int] = {}
        for word in words:
            marked = MARK + word
            node, scores, counts = root, [0.0], [0]
            for d, c in enumerate(marked[:SHARED], 1):
                following = node[0].get(c)
                if following is None:
                    following = [{}, *self._step(marked, d, scores, counts)]
                    node[0][c] = following
                node = following
                scores.append(node[1])
                counts.append(node[2])
            for d in range(SHARED + 1, len(marked) + 1):
                score, tokens = self._step(marked, d, scores, counts)
                scores.append(score)
                counts.append(tokens)
            ends[word] = counts[-1]
        return ends

    def count(self, texts: list[str | None]) -> list[tuple[int, int]]:
        """(words, tokens) of each text; the words that no earlier text had share a trie."""
        # bytes.split knows the separators 9 to 13 and 32 only.
        split = [(t or "").encode("utf-8", "surrogatepass").split() for t in texts]
        known = self.counts
        found = [list(map(known.get, words)) for words in split]
        missing = {w for words, counts in zip(split, found, strict=True) if None in counts for w, n in zip(words, counts, strict=True) if n is None}
        if not missing:
            return [(len(counts), sum(counts)) for counts in found]
        text_of = {w: w.decode("utf-8", "surrogatepass") for w in missing}
        fresh: dict[bytes, int] = {}
        todo = sorted(missing)
        for at in range(0, len(todo), TRIE_WORDS):
            part = todo[at : at + TRIE_WORDS]
            made = self.count_trie(map(text_of.__getitem__, part))
            fresh.update((w, made[text_of[w]]) for w in part)
        out = [(len(words), sum([fresh[w] if n is None else n for w, n in zip(words, counts, strict=True)])) for words, counts in zip(split, found, strict=True)]
        if len(known) < KEPT_COUNTS:
            known.update((w, n) for w, n in fresh.items() if len(w) <= SHARED)
        return out


@lru_cache(maxsize=2)
def _loaded(name: str) -> UnigramCounter:
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=SparkFiles.get(name))
    plain = [i for i in range(model.get_piece_size()) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i))]
    return UnigramCounter.from_ranks(model.id_to_piece(plain))


def with_token_counts(docs: DataFrame, path: str | None = None, text: Column | None = None) -> DataFrame:
    """``docs`` with ``n_words`` and ``n_tokens``."""
    path = path or vocabulary_path()
    docs.sparkSession.sparkContext.addFile(path)
    name = os.path.basename(path)

    def run(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        common.claim("counts", _loaded.cache_clear)
        counter = _loaded(name)
        for batch in batches:
            # Small blocks: split words of few documents are held at a time.
            rows = [r for at in range(0, len(batch), 64) for r in counter.count(batch.slice(at, 64).to_pylist())]
            yield pa.StructArray.from_arrays([pa.array([r[k] for r in rows], pa.int64()) for k in (0, 1)], names=["n_words", "n_tokens"])

    run = F.arrow_udf(run, "n_words long, n_tokens long")

    kept = docs.drop("n_words", "n_tokens")
    return kept.withColumn("_n", run(F.col("text") if text is None else text)).select(*kept.columns, "_n.n_words", "_n.n_tokens")


def op6_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = common.table(spark, sf_dir, "documents").select("doc_id", "text")
    return with_token_counts(docs).select("doc_id", "n_words", "n_tokens")
