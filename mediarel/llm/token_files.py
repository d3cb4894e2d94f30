"""Token ids in bit-plane or byte-plane shuffled files with a chunk index.

Ids are written in document order. A chunk holds whole documents; its id stream is cut into blocks
of a fixed number of ids, each block is transposed into planes (all lowest bytes, all next bytes,
... or single bits), and every plane is compressed with zstandard on its own. Rows of a Parquet
table are the chunks, so Spark's committer makes writing safe against lost tasks and any store that
Spark reaches will do; the index table beside it has a row for each chunk: its place, documents and ids.

Defined cases: null text is encoded as empty, so the document has the end id alone; repeated doc_ids
keep their rows, in order of their texts; null doc_ids come first; a very long text stays in one chunk; an empty table makes an empty file that reads back empty; other columns are left out.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from mediarel.llm import bpe, common

#: Ids of a block: planes are compressed one block at a time.
BLOCK_IDS = 1 << 16
#: A chunk ends with the document that brings it to this many ids.
CHUNK_IDS = 1 << 19
LEVEL = 3
END_ID = 1

CHUNK_SCHEMA = (
    "part int, chunk int, first_doc long, n_docs int, start_in_part long, n_ids long, crc long, "
    "doc_ids binary, doc_nulls binary, lengths binary, blocks array<struct<n: int, planes: array<binary>>>"
)


_CHUNK_ARROW = pa.schema(
    {
        **{"part": pa.int32(), "chunk": pa.int32(), "first_doc": pa.int64(), "n_docs": pa.int32(), "start_in_part": pa.int64(), "n_ids": pa.int64(), "crc": pa.int64()},
        **dict.fromkeys(("doc_ids", "doc_nulls", "lengths"), pa.binary()),
        "blocks": pa.list_(pa.struct({"n": pa.int32(), "planes": pa.list_(pa.binary())})),
    }
)


def to_planes(ids: np.ndarray, bits: bool = False) -> list[bytes]:
    """Planes of a block of 32-bit ids: 4 byte planes, or 32 bit planes from the lowest bit."""
    if not bits:
        return [p.tobytes() for p in np.ascontiguousarray(ids.astype("<u4").view(np.uint8).reshape(-1, 4).T)]
    table = np.unpackbits(ids.astype("<u4").view(np.uint8).reshape(-1, 4), axis=1, bitorder="little")
    return [np.packbits(p, bitorder="little").tobytes() for p in table.T]


def from_planes(planes: list[bytes], n: int) -> np.ndarray:
    """Ids of a block; 4 planes are bytes, 32 are bits."""
    if len(planes) == 4:
        return np.ascontiguousarray(np.stack([np.frombuffer(p, np.uint8, n) for p in planes], axis=1)).view("<u4").ravel()
    table = np.stack([np.unpackbits(np.frombuffer(p, np.uint8), count=n, bitorder="little") for p in planes], axis=1)
    return np.packbits(table, axis=1, bitorder="little").view("<u4").ravel()


class _Writer:
    """Collects documents of one part into chunks."""

    def __init__(self, part: int, bits: bool, chunk_ids: int, block_ids: int):
        self.part, self.bits, self.chunk_ids, self.block_ids = part, bits, chunk_ids, block_ids
        self.pack = zstandard.ZstdCompressor(level=LEVEL)
        self.chunk, self.start = 0, 0
        self.clear()

    def clear(self) -> None:
        self.ids: list[bytes] = []
        self.docs: list[int | None] = []
        self.lengths: list[int] = []
        self.held = 0

    def add(self, doc: int | None, ids: bytes) -> bool:
        self.docs.append(doc)
        self.lengths.append(len(ids) // 4)
        self.ids.append(ids)
        self.held += len(ids) // 4
        return self.held >= self.chunk_ids

    def take(self) -> dict:
        raw = b"".join(self.ids)
        ids = np.frombuffer(raw, "<u4")
        blocks = []
        for at in range(0, len(ids), self.block_ids):
            block = ids[at : at + self.block_ids]
            blocks.append({"n": len(block), "planes": [self.pack.compress(p) for p in to_planes(block, self.bits)]})
        known = [d for d in self.docs if d is not None]
        made = {
            "part": self.part,
            "chunk": self.chunk,
            "first_doc": known[0] if known else None,
            "n_docs": len(self.docs),
            "start_in_part": self.start,
            "n_ids": len(ids),
            "crc": zlib.crc32(raw),
            "doc_ids": self.pack.compress(np.array([d or 0 for d in self.docs], "<i8").tobytes()),
            "doc_nulls": self.pack.compress(np.packbits([d is None for d in self.docs]).tobytes()),
            "lengths": self.pack.compress(np.array(self.lengths, "<i8").tobytes()),
            "blocks": blocks,
        }
        self.chunk += 1
        self.start += len(ids)
        self.clear()
        return made

    def batch(self) -> pa.RecordBatch:
        return pa.RecordBatch.from_pylist([self.take()], schema=_CHUNK_ARROW)


def write(docs: DataFrame, path: str, vocabulary: str | None = None, end_id: int | None = END_ID, bits: bool = False, parts: int | None = None, chunk_ids: int = CHUNK_IDS, block_ids: int = BLOCK_IDS) -> None:
    """Encode ``docs`` (doc_id, text) in ascending doc_id order into ``path/chunks`` and ``path/index``.

    Texts, not ids, are dealt out into ranges of doc_id: they are smaller.
    """
    spark = docs.sparkSession
    name = bpe.distribute(spark, vocabulary or bpe.vocabulary_path())
    n = parts or max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    ordered = docs.select("doc_id", "text").repartitionByRange(n, F.col("doc_id").asc_nulls_first()).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), "text")
    tail = np.array([] if end_id is None else [end_id], "<u4").tobytes()

    def encode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = bpe.encoder(name)
        writer = None
        for rows in common.slices(batches, bpe.ROWS):
            parts, docs_, texts = (c.to_pylist() for c in rows.columns)
            for part, doc, ids in zip(parts, docs_, coder.library_batch(texts), strict=True):
                writer = writer or _Writer(part, bits, chunk_ids, block_ids)
                if writer.add(doc, ids + tail):
                    yield writer.batch()
        if writer and writer.docs:
            yield writer.batch()

    keyed = ordered.select(F.spark_partition_id().alias("part"), F.col("doc_id").cast("long").alias("doc_id"), "text")
    with common.small_batches(spark):
        keyed.mapInArrow(encode, CHUNK_SCHEMA).write.parquet(f"{path}/chunks")
    spark.read.schema(CHUNK_SCHEMA).parquet(f"{path}/chunks").select("part", "chunk", "first_doc", "n_docs", "start_in_part", "n_ids", "crc").coalesce(1).write.parquet(f"{path}/index")


def read_chunk(row: dict) -> tuple[list[int | None], np.ndarray, np.ndarray]:
    """Documents, their lengths and all ids of a chunk; a wrong checksum raises."""
    unpack = zstandard.ZstdDecompressor().decompress
    docs = np.frombuffer(unpack(row["doc_ids"]), "<i8")
    nulls = np.unpackbits(np.frombuffer(unpack(row["doc_nulls"]), np.uint8), count=len(docs)).astype(bool)
    lengths = np.frombuffer(unpack(row["lengths"]), "<i8")
    ids = np.concatenate([np.empty(0, "<u4"), *[from_planes([unpack(p) for p in b["planes"]], b["n"]) for b in row["blocks"]]]).astype("<u4")
    if zlib.crc32(ids.tobytes()) != row["crc"]:
        raise ValueError(f"chunk {row['part']}/{row['chunk']} is damaged")
    return [None if gone else int(d) for d, gone in zip(docs, nulls, strict=True)], lengths, ids


def read(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start (ids of all documents before it), ids (binary) from the files."""
    return _read(spark, path, "doc_id long, start long, ids binary", lambda raw: raw)


def _read(spark: SparkSession, path: str, schema: str, of) -> DataFrame:
    # One row for each part, however large the table: range partitions follow each other in doc_id order.
    index = spark.read.schema("part int, chunk int, n_ids long").parquet(f"{path}/index")
    offsets = index.groupBy("part").agg(F.sum("n_ids").alias("held"))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = offsets.select("part", F.coalesce(F.sum("held").over(before), F.lit(0)).cast("long").alias("offset"))
    chunks = spark.read.schema(CHUNK_SCHEMA).parquet(f"{path}/chunks")

    def decode(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            for row in batch.to_dict("records"):
                docs, lengths, ids = read_chunk(row)
                ends = np.cumsum(lengths)
                base = row["offset"] + row["start_in_part"]
                raw = memoryview(ids.tobytes())
                found = [(d, int(base + e - n), of(bytes(raw[4 * (e - n) : 4 * e]))) for d, n, e in zip(docs, lengths, ends, strict=True)]
                yield pd.DataFrame({"doc_id": pd.array([f[0] for f in found], dtype="Int64"), "start": [f[1] for f in found], **_columns([f[2] for f in found])})

    return chunks.join(F.broadcast(offsets), "part").mapInPandas(decode, schema)


def _columns(values: list) -> dict:
    return {"ids": values} if not values or isinstance(values[0], bytes) else {"n_tokens": [v[0] for v in values], "ids_crc32": [v[1] for v in values]}


def op5_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = common.new_path(spark, "token-files")
    write(common.table(spark, sf_dir, "documents"), path)
    return _read(spark, path, "doc_id long, start long, n_tokens long, ids_crc32 long", lambda raw: (len(raw) // 4, zlib.crc32(raw)))
