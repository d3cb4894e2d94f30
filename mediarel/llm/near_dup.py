"""Near-duplicate documents: bottom-k sketches from one hash function, union sketches, exact Jaccard.

One hash orders all shingles. A document keeps its first ``n - ceil(t n) + 1`` values: two sets with
Jaccard similarity of t or more always share one of those, so inverted lists over them lose no link.
Values that many documents hold go to the end of the order (any common order keeps the guarantee),
so lists stay short except inside large families of near copies.

Lists never become all pairs. Each list compares its members with one leader (the member nearest to
the family's common part); what ends in one component needs no more comparison. Members left over
are compared with a few hubs of the family; those still outside its main component meet the whole family in blocks, where exact
intersections are matrix products and only one link a document and component leaves a block.

Candidates pass an estimate from the union sketch of their smallest hashes. It drops a pair only where so few
values of the sketch are shared that a true link has a chance below ``DROP_CHANCE`` of showing no more.
Surviving pairs are confirmed on full sets.

Defined cases: without words or text a document has no shingles and links with nothing; equal sets
are one class, represented by the smallest id; rows that repeat a doc_id keep their rows and share a component;
a null doc_id links with nothing and is kept; other columns are left out.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import lru_cache
from math import comb

import numpy as np
import pandas as pd
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from mediarel.llm import common

#: Values of the fixed-size sketch behind the union estimate, and the chance that it drops a pair just at the threshold.
SKETCH = 48
DROP_CHANCE = 1e-15
#: A value in more documents than this, and than this share of them, goes to the end of the order. Other lists are shorter, so their
#: pairs stay in proportion to their members.
HOT_LEAST = 8
HOT_SHARE = 1 / 200_000
#: Values moved to the end at most (the most frequent): bounds what is broadcast, not what is found.
HOT_MOST = 1_000_000
#: Values that are counted at once while looking for frequent ones.
COUNT_BLOCK = 2_000_000
#: Ids that may be broadcast to pick texts for exact comparison; beyond it they are joined by shuffle.
BROADCAST_IDS = 500_000
HUBS = 8
#: Nodes whose labels are broadcast at most while components are found; keys of large groups elsewhere.
LARGE_NODES = 20_000
#: Sides of the grid in which members outside their family's main component meet the family, and columns of one matrix product.
OUTSIDE_BLOCK = 128
FAMILY_BLOCK = 512
TILE = 256
#: Bytes of text that one numpy pass over words covers, unless a single word is longer.
WORD_BLOCK = 1 << 18
#: Documents whose values are held at a time between Arrow and numpy.
ROWS = 256

_A, _B, _C = (np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9))
#: An odd base of the word polynomial, so that it has an inverse modulo 2**64.
_BASE = 0x9E3779B97F4A7C15
_SEPARATOR = np.isin(np.arange(256), np.frombuffer(common.WORD_SEPARATORS.encode(), np.uint8))


def _byte_values() -> np.ndarray:
    """A 64-bit value for each byte: 0 for separators, and A to Z have those of a to z."""
    low = np.arange(256, dtype=np.uint64)
    low[65:91] += np.uint64(32)
    with np.errstate(over="ignore"):
        value = (low + np.uint64(1)) * _B
        value = (value ^ (value >> np.uint64(31))) * _C
    value[_SEPARATOR] = 0
    return value


_VALUE = _byte_values()


@lru_cache(maxsize=2)
def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the base and of its inverse, from 0 to ``n``."""
    with np.errstate(over="ignore"):
        up, down = (np.concatenate(([np.uint64(1)], np.cumprod(np.full(n, base, np.uint64)))) for base in (_BASE, pow(_BASE, -1, 1 << 64)))
    return up, down


def _block_hashes(data: bytes) -> np.ndarray:
    at = np.frombuffer(data, np.uint8)
    gap = _SEPARATOR[at]
    edge = np.flatnonzero(gap[1:] != gap[:-1]) + 1
    if len(at) and not gap[0]:
        edge = np.concatenate(([0], edge))
    if len(edge) % 2:
        edge = np.append(edge, len(at))
    start, end = edge[::2], edge[1::2]
    if not len(start):
        return np.empty(0, dtype=np.uint64)
    up, down = _powers(max(WORD_BLOCK, 1 << len(at).bit_length()))
    with np.errstate(over="ignore"):
        sums = np.cumsum(_VALUE[at] * up[: len(at)])
        # The byte before a later word is a separator of value 0, so the sum there is the sum before the word.
        total = (sums[end - 1] - np.where(start > 0, sums[start - 1], np.uint64(0))) * down[start]
        return (total ^ (total >> np.uint64(32))) * _A + (end - start).astype(np.uint64)


def word_hashes(data: bytes) -> np.ndarray:
    """Hash of every word of a UTF-8 text, in order, A to Z as a to z: differences of one running polynomial sum."""
    found, at = [], 0
    while at < len(data):
        cut = len(data)
        if cut - at > WORD_BLOCK:
            # A block ends at a separator.
            near = _LAST_GAP.match(data, at, at + WORD_BLOCK) or _NEXT_GAP.search(data, at + WORD_BLOCK)
            cut = near.end() if near else cut
        found.append(_block_hashes(data[at:cut]))
        at = cut
    return found[0] if len(found) == 1 else np.concatenate(found) if found else np.empty(0, dtype=np.uint64)


_LAST_GAP = re.compile(rb".*[ \t\n\x0b\x0c\r]", re.S)
_NEXT_GAP = re.compile(rb"[ \t\n\x0b\x0c\r]")


def rolled(hashes: np.ndarray, width: int) -> np.ndarray:
    """Hash of every run of ``width`` words, in order."""
    n = len(hashes) - width + 1
    with np.errstate(over="ignore"):
        total = np.full(max(n, 0), width, dtype=np.uint64)
        for k in range(width if n > 0 else 0):
            total = (total ^ hashes[k : n + k]) * _A
            total = (total ^ (total >> np.uint64(32))) * _B
        total ^= total >> np.uint64(29)
        return (total * _C).view(np.int64)


def shingle_set(text: str | None, width: int) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the word shingles of a text; fewer words than ``width`` make one."""
    hashes = word_hashes(text.encode("utf-8", "surrogatepass")) if text else ()
    if not len(hashes):
        return np.empty(0, dtype=np.int64)
    values = np.sort(rolled(hashes, min(width, len(hashes))))
    return values[np.concatenate(([True], values[1:] != values[:-1]))]


def _lists(rows: list[np.ndarray]) -> pa.Array:
    """Arrow lists of 64-bit values."""
    ends = np.cumsum([0, *map(len, rows)])
    return pa.ListArray.from_arrays(pa.array(ends, pa.int32()), pa.array(np.concatenate([np.empty(0, np.int64), *rows])))


def prefix_length(n: int, per_cent: int) -> int:
    return n + (-per_cent * n) // 100 + 1


def crowd(n_docs: int) -> int:
    """Documents from which on a value counts as frequent. The share bounds how many values can."""
    return max(HOT_LEAST, int(n_docs * HOT_SHARE))


def frequent_values(docs: DataFrame, width: int, n_docs: int) -> np.ndarray:
    """Values in many documents, the most frequent ones up to ``HOT_MOST``; only the order of values depends on it."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.claim("words")
        held: list[np.ndarray] = []
        seen: set[int] = set()
        size = 0

        def flush() -> pa.RecordBatch:
            values = np.sort(np.concatenate(held))
            first = np.flatnonzero(np.concatenate(([True], values[1:] != values[:-1])))
            times = np.diff(np.append(first, len(values)))
            return pa.RecordBatch.from_arrays([pa.array(values[first][times > 1]), pa.array(times[times > 1], pa.int64())], names=["v", "times"])

        for text in common.each_text(batches, ROWS):
            values = shingle_set(text, width)
            mark = xxhash.xxh3_64_intdigest(values)
            if not len(values) or mark in seen:
                continue
            seen.add(mark)
            held.append(values)
            size += len(values)
            if size >= COUNT_BLOCK:
                yield flush()
                held, seen, size = [], set(), 0
        if held:
            yield flush()

    least = crowd(n_docs)
    found = docs.select("text").mapInArrow(count, "v long, times long").groupBy("v").agg(F.sum("times").alias("times"))
    return _most_frequent(found.where(F.col("times") > least))


def _most_frequent(counts: DataFrame) -> np.ndarray:
    """Sorted values of (v, times): the most frequent ones up to ``HOT_MOST``, cut between two steps of frequency, of which a few hundred are counted."""
    counts = common.materialise(counts.withColumn("step", F.floor(8 * F.log2("times")).cast("int")), "dup-frequent")
    room, least = HOT_MOST, 0
    for r in counts.groupBy("step").count().orderBy(F.desc("step")).collect():
        room -= r["count"]
        if room < 0:
            least = r["step"] + 1
            break
    values = counts.where(F.col("step") >= least).select("v").toPandas()["v"].to_numpy(dtype=np.int64)
    common.discard(counts)
    return np.sort(values)


def sketches(docs: DataFrame, width: int, per_cent: int, hot: np.ndarray) -> DataFrame:
    """doc_id, n, sig (of the whole set), cool (values of the prefix that are not frequent), prefix, sketch."""
    sent = docs.sparkSession.sparkContext.broadcast(hot)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.claim("words")
        frequent = sent.value
        for part in common.slices(batches, ROWS):
            sets = [shingle_set(text, width) for text in part.column(1).to_pylist()]
            cool, prefixes = [], []
            for values in sets:
                n = len(values)
                at = np.searchsorted(frequent, values)
                is_hot = frequent[np.minimum(at, len(frequent) - 1)] == values if len(frequent) else np.zeros(n, dtype=bool)
                keep = prefix_length(n, per_cent) if n else 0
                first = values[~is_hot][:keep]
                prefixes.append(np.concatenate((first, values[is_hot][: keep - len(first)])) if len(first) < keep else first)
                cool.append(n - int(is_hot.sum()))
            yield pa.RecordBatch.from_arrays(
                [
                    part.column(0),
                    pa.array(list(map(len, sets)), pa.int32()),
                    pa.array([xxhash.xxh3_128_digest(v) if len(v) else b"" for v in sets], pa.binary()),
                    pa.array(cool, pa.int32()),
                    _lists(prefixes),
                    _lists([v[:SKETCH] for v in sets]),
                ],
                names=["doc_id", "n", "sig", "cool", "prefix", "sketch"],
            )

    known = docs.where(F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("long"), "text")
    return known.mapInArrow(run, "doc_id long, n int, sig binary, cool int, prefix array<long>, sketch array<long>")


def set_sizes(docs: DataFrame, width: int) -> DataFrame:
    """doc_id, n_shingles of each row of ``docs`` (doc_id, text)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in common.slices(batches, ROWS):
            sizes = [len(shingle_set(text, width)) for text in part.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(sizes, pa.int64())], names=["doc_id", "n_shingles"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, n_shingles long")


def _sizes_fit(na: Column, nb: Column, per_cent: int) -> Column:
    return 100 * F.least(na, nb).cast("long") >= per_cent * F.greatest(na, nb).cast("long")


def least_shared(per_cent: int) -> int:
    """Largest number of shared sketch values that a pair at the threshold stays below with a chance of at most ``DROP_CHANCE``."""
    t, below, least = per_cent / 100, 0.0, 0
    while least < SKETCH:
        below += comb(SKETCH, least) * t**least * (1 - t) ** (SKETCH - least)
        if below > DROP_CHANCE:
            break
        least += 1
    return least


def _estimated(pairs: DataFrame, sketched: DataFrame, per_cent: int) -> DataFrame:
    """Pairs (a, b) whose union sketch leaves a link possible."""
    side = lambda s: sketched.select(F.col("doc_id").alias(s), F.col("n").alias(f"n_{s}"), F.col("sketch").alias(f"s_{s}"))
    both = pairs.join(side("a"), "a").join(side("b"), "b")
    union = F.array_sort(F.array_union("s_a", "s_b"))
    union = F.when((F.col("n_a") > SKETCH) | (F.col("n_b") > SKETCH), F.slice(union, 1, SKETCH)).otherwise(union)
    both = both.withColumn("u", union)
    share = F.size(F.array_intersect(F.array_intersect("u", "s_a"), F.col("s_b"))) / F.size("u")
    return both.where(share >= least_shared(per_cent) / SKETCH).select("a", "b", "n_a", "n_b")


def _verified(pairs: DataFrame, docs: DataFrame, width: int, per_cent: int) -> DataFrame:
    """a, b, distance, linked: exact, on full sets made from the texts of the documents in question."""
    ids = common.materialise(pairs.select(F.col("a").alias("doc_id")).unionByName(pairs.select(F.col("b").alias("doc_id"))).distinct(), "dup-ids")
    known = _sets_of(ids, docs, width)
    side = lambda s: known.select(F.col("doc_id").alias(s), F.col("values").alias(f"v_{s}"))
    common_values = F.size(F.array_intersect("v_a", "v_b")).cast("long")
    joined = pairs.select("a", "b").join(side("a"), "a").join(side("b"), "b")
    measured = joined.select("a", "b", common_values.alias("same"), (F.size("v_a") + F.size("v_b") - common_values).cast("long").alias("whole"))
    found = measured.select("a", "b", (1 - F.col("same") / F.col("whole")).alias("distance"), (100 * F.col("same") >= per_cent * F.col("whole")).alias("linked"))
    found = common.materialise(found, "dup-links")
    common.discard(ids, known)
    return found


def _sets_of(ids: DataFrame, docs: DataFrame, width: int) -> DataFrame:
    """(doc_id, values): full shingle sets of the documents in question, from their texts."""
    picked = F.broadcast(ids) if ids.count() <= BROADCAST_IDS else ids

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        common.claim("words")
        for part in common.slices(batches, ROWS):
            yield pa.RecordBatch.from_arrays([part.column(0), _lists([shingle_set(t, width) for t in part.column(1).to_pylist()])], names=["doc_id", "values"])

    known = docs.select(F.col("doc_id").cast("long"), "text").join(picked, "doc_id", "left_semi").mapInArrow(sets, "doc_id long, values array<long>")
    return common.materialise(known, "dup-sets")


def _links_of_block(left: pd.DataFrame, right: pd.DataFrame, per_cent: int) -> list[tuple[int, int]]:
    """For each left document one linked right document of every component but its own, by exact intersections."""
    sizes = left["values"].map(len).to_numpy()
    flat, owner = np.concatenate(left["values"].to_list()), np.repeat(np.arange(len(left)), sizes)
    found: dict[tuple[int, int], tuple[int, int]] = {}
    for start in range(0, len(right), TILE):
        part = right.iloc[start : start + TILE]
        part_sizes = part["values"].map(len).to_numpy()
        part_flat, part_owner = np.concatenate(part["values"].to_list()), np.repeat(np.arange(len(part)), part_sizes)
        shared = np.intersect1d(flat, part_flat)
        a, b = (np.zeros((len(x), len(shared)), dtype=np.float32) for x in (left, part))
        for table, values, rows in ((a, flat, owner), (b, part_flat, part_owner)):
            inside = np.isin(values, shared)
            table[rows[inside], np.searchsorted(shared, values[inside])] = 1
        same = (a @ b.T).astype(np.int64)
        linked = 100 * same >= per_cent * (sizes[:, None] + part_sizes[None, :] - same)
        for i, j in zip(*np.nonzero(linked), strict=True):
            x, y = left.iloc[i], part.iloc[j]
            if x["c"] != y["c"]:
                found.setdefault((int(x["id"]), int(y["c"])), (int(x["id"]), int(y["id"])))
    return list(found.values())


def _met_in_blocks(outside: DataFrame, anyone: DataFrame, docs: DataFrame, width: int, per_cent: int) -> DataFrame:
    """Links (a, b) between members outside their family's main component and all members of the family.

    Blocks of the two sides meet in a grid, exact sets in hand; a cell returns one link a document and component, never its pairs.
    """
    ids = common.materialise(anyone.select(F.col("y").alias("doc_id")).distinct(), "dup-ids")
    known = _sets_of(ids, docs, width)
    grid = outside.groupBy("a").agg(F.ceil(F.count("*") / OUTSIDE_BLOCK).cast("int").alias("rows")).join(anyone.groupBy("a").agg(F.ceil(F.count("*") / FAMILY_BLOCK).cast("int").alias("columns")), "a")
    grid = common.materialise(grid, "dup-grid")
    large = (F.col("rows") > 1) | (F.col("columns") > 1)
    place = lambda c, n: F.pmod(F.xxhash64(c), F.col(n)).cast("int")
    every = lambda n: F.explode(F.sequence(F.lit(0), F.col(n) - 1))
    left = _met_by_key(outside, grid, "a", large).select("a", place("x", "rows").alias("row"), every("columns").alias("column"), F.col("x").alias("id"), F.col("c_x").alias("c"))
    right = _met_by_key(anyone, grid, "a", large).select("a", place("y", "columns").alias("column"), every("rows").alias("row"), F.col("y").alias("id"), F.col("c_y").alias("c"))
    # Fresh names on either side: both come from the same tables, which a cogroup could not tell apart.
    fields = ("a", "row", "column", "id", "c", "values")
    with_sets = lambda df: df.join(known.withColumnRenamed("doc_id", "id"), "id").select(*[F.col(f).alias(f) for f in fields]).groupBy("a", "row", "column")

    def meet(l: pd.DataFrame, r: pd.DataFrame) -> pd.DataFrame:  # noqa: E741
        links = _links_of_block(l, r, per_cent) if len(l) and len(r) else []
        return pd.DataFrame([(min(p), max(p)) for p in links], columns=["a", "b"])

    found = common.materialise(with_sets(left).cogroup(with_sets(right)).applyInPandas(meet, "a long, b long").distinct(), "dup-met")
    common.discard(ids, known, grid)
    return found


def components(edges: DataFrame) -> DataFrame:
    """node, component (its smallest node) for every node of ``edges`` (a, b): least labels with pointer jumps.

    Nodes with a large share of the edges, as leaders of families have, are at most ``LARGE_NODES``: their labels are broadcast.
    """
    both = common.materialise(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "cc-edges")
    large = common.materialise(both.groupBy("b").agg(F.count("*").alias("held")).where(F.col("held") > max(HOT_LEAST, both.count() // LARGE_NODES)).select("b"), "cc-large")
    some = large.limit(1).count() > 0
    labels = common.materialise(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("a"), F.min("b")).alias("component")), "cc")
    while True:
        named = labels.withColumnRenamed("node", "b")
        if some:
            told = F.broadcast(named.join(F.broadcast(large), "b", "left_semi"))
            met = both.join(told, "b").select("a", "component").unionByName(both.join(F.broadcast(large), "b", "left_anti").join(named, "b").select("a", "component"))
        else:
            met = both.join(named, "b").select("a", "component")
        near = met.groupBy(F.col("a").alias("node")).agg(F.min("component").alias("least"))
        hooked = labels.join(near, "node").select("node", "component", F.least("component", "least").alias("next"))
        roots = labels.select(F.col("node").alias("next"), F.col("component").alias("root"))
        jumped = common.materialise(hooked.join(roots, "next", "left").select("node", F.least("next", F.coalesce("root", "next")).alias("component"), (F.col("component") != F.least("next", F.coalesce("root", "next"))).alias("moved")), "cc")
        common.discard(labels)
        moved = jumped.where("moved").limit(1).count()
        labels = jumped.drop("moved")
        labels._stored_at = jumped._stored_at
        if not moved:
            common.discard(both, large)
            return labels


def _labelled(rows: DataFrame, labels: DataFrame, column: str, into: str) -> DataFrame:
    named = labels.select(F.col("node").alias(column), F.col("component").alias(into))
    return rows.join(named, column, "left").withColumn(into, F.coalesce(F.col(into), F.col(column)))


def _classes(base: DataFrame, n_docs: int) -> tuple[DataFrame, DataFrame | None, DataFrame]:
    """(copies: doc_id and rep of all but one document of each class of equal sets, links of copies whose doc_id has another text too or None, the rows of the others).

    Only the text that is a copy leaves the search, not another text of its doc_id.
    """
    filled = base.where("n > 0")
    classes = filled.groupBy("sig").agg(F.min("doc_id").alias("rep"), F.count("*").alias("rows")).where("rows > 1")
    classes = common.materialise(classes, "dup-classes")
    # A large class would meet its representative in one task; there are at most ``n_docs / crowd`` of them, so those are broadcast.
    large = F.broadcast(classes.where(F.col("rows") > crowd(n_docs)).select("sig", "rep"))
    small = classes.where(F.col("rows") <= crowd(n_docs)).select("sig", "rep")
    ids = filled.select("doc_id", "sig")
    held = ids.join(large, "sig").unionByName(ids.join(large.select("sig"), "sig", "left_anti").join(small, "sig")).where("doc_id != rep")
    several = common.materialise(filled.groupBy("doc_id").agg((F.min("sig") != F.max("sig")).alias("several")).where("several"), "dup-several")
    if not several.limit(1).count():
        copies = common.materialise(held.select("doc_id", "rep").distinct(), "dup-copies")
        common.discard(several, classes)
        return copies, None, filled.join(copies.select("doc_id"), "doc_id", "left_anti")
    held = held.distinct().join(several, "doc_id", "left").withColumn("several", F.col("several").isNotNull())
    held = common.materialise(held, "dup-copies")
    copies = held.where("NOT several").select("doc_id", "rep")
    bridges = held.where("several").select(F.col("rep").alias("a"), F.col("doc_id").alias("b"))
    copies._stored_at = held._stored_at
    common.discard(several, classes)
    return copies, bridges, filled.join(held.select("doc_id", "sig"), ["doc_id", "sig"], "left_anti")


def link(docs: DataFrame, width: int = 5, per_cent: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for every row of ``docs`` (doc_id, text)."""
    with common.small_batches(docs.sparkSession):
        return _linked(docs, width, per_cent)


def _linked(docs: DataFrame, width: int, per_cent: int) -> DataFrame:
    docs = docs.select("doc_id", "text")
    n_docs = docs.count()
    hot = frequent_values(docs, width, n_docs)
    base = common.materialise(sketches(docs, width, per_cent, hot), "dup-sketches")
    copies, bridges, reps = _classes(base, n_docs)
    # Counting in blocks misses values that are thinly spread; exact lists show them, and they move to the end too.
    cool = reps.select("doc_id", "n", "cool", F.posexplode("prefix").alias("place", "v")).where("place < cool").select("doc_id", "v")
    values = _most_frequent(cool.groupBy("v").agg(F.count("*").alias("times")).where(F.col("times") > crowd(n_docs)))
    if len(values):
        # Prefixes are cut again where the texts are read: no text is shuffled for it.
        common.discard(base, copies)
        base = common.materialise(sketches(docs, width, per_cent, np.union1d(hot, values)), "dup-sketches")
        copies, bridges, reps = _classes(base, n_docs)
    rows = reps.select("doc_id", "n", "cool", F.posexplode("prefix").alias("place", "v"))
    sketched = reps.select("doc_id", "n", "sketch")

    # Frequent values may have very long lists: their leaders come from a pre-aggregated minimum.
    hot_rows = rows.where("place >= cool").select("v", "doc_id", "n", (F.col("cool") / F.col("n")).alias("own"))
    leaders = hot_rows.groupBy("v").agg(F.min(F.struct("own", "doc_id", "n")).alias("lead"), F.count("*").alias("held")).where("held > 1")
    leaders = common.materialise(leaders, "dup-leaders")
    hot_rows = _met_by_key(hot_rows, leaders, "v", F.col("held") > max(1000, n_docs // 1000))
    hot_star = hot_rows.where("doc_id != lead.doc_id").select(F.col("lead.doc_id").alias("a"), F.col("lead.n").alias("n_a"), F.col("doc_id").alias("b"), F.col("n").alias("n_b"), "own").distinct()
    hot_star = common.materialise(hot_star, "dup-hot")
    # Lists of the other values are short, so one window gives each its leader.
    whole = Window.partitionBy("v")
    cool_rows = rows.where("place < cool").select("v", "doc_id", "n")
    cool_rows = cool_rows.select("*", F.min(F.struct("doc_id", "n")).over(whole).alias("lead"), F.count("*").over(whole).alias("held")).where("held > 1")
    cool_rows = common.materialise(cool_rows.select("v", "doc_id", "n", F.col("lead.doc_id").alias("lead"), F.col("lead.n").alias("lead_n"), "held"), "dup-lists")
    cool_star = cool_rows.where("doc_id != lead").select(F.col("lead").alias("a"), F.col("lead_n").alias("n_a"), F.col("doc_id").alias("b"), F.col("n").alias("n_b"))

    star = hot_star.drop("own").unionByName(cool_star).where(_sizes_fit(F.col("n_a"), F.col("n_b"), per_cent)).select("a", "b").distinct()
    first = _verified(common.materialise(_estimated(star, sketched, per_cent), "dup-pairs"), docs, width, per_cent)
    labels = components(first.where("linked"))

    # Families of frequent values: those not with their leader meet a few hubs that are.
    spread = (100 - per_cent) / 100 + 1e-9
    family = hot_star.join(first.select("a", "b", "distance"), ["a", "b"], "left")
    family = common.materialise(_labelled(_labelled(family, labels, "a", "c_a"), labels, "b", "c_b"), "dup-family")
    ranked = family.where(F.col("distance") <= spread).withColumn("turn", F.row_number().over(Window.partitionBy("a").orderBy("own", "b"))).where(F.col("turn") <= HUBS)
    hubs = ranked.select("a", F.col("b").alias("hub"), F.col("n_b").alias("n_hub"))
    away = family.where("c_a != c_b").select("a", "b", "n_b")
    tried = away.join(hubs, "a").where(_sizes_fit(F.col("n_b"), F.col("n_hub"), per_cent)).select(F.least("b", "hub").alias("a"), F.greatest("b", "hub").alias("b")).distinct()
    second = _verified(common.materialise(_estimated(tried, sketched, per_cent), "dup-pairs"), docs, width, per_cent)
    linked = first.where("linked").select("a", "b").unionByName(second.where("linked").select("a", "b"))
    labels = components(linked)

    # What is left: pairs of one list in different components.
    known = family.select("a", "b")
    known = common.materialise(_labelled(known, labels, "b", "c"), "dup-family")
    mixed = known.groupBy("a").agg(F.min("c").alias("c1"), F.max("c").alias("c2"), F.count("*").alias("members")).where("c1 != c2").select("a", "members")
    # The component with the leader is the large one; pairs need one member outside it.
    main = labels.select(F.col("node").alias("a"), F.col("component").alias("main"))
    mixed = common.materialise(mixed.join(main, "a", "left").withColumn("main", F.coalesce("main", "a")), "dup-mixed")
    open_families = _met_by_key(known, mixed, "a", F.col("members") > FAMILY_BLOCK)
    outside = open_families.where("c != main").select("a", F.col("b").alias("x"), F.col("c").alias("c_x"))
    anyone = open_families.select("a", F.col("b").alias("y"), F.col("c").alias("c_y"))
    met = _met_in_blocks(outside, anyone, docs, width, per_cent)
    lists = _labelled(cool_rows.where("held > 2").select("v", "doc_id", "n", "lead"), labels, "doc_id", "c")
    split = lists.groupBy("v").agg(F.min("c").alias("c1"), F.max("c").alias("c2")).where("c1 != c2").select("v")
    lists = lists.join(split, "v", "left_semi").where("doc_id != lead").select("v", "doc_id", "n", "c")
    left, right = (lists.select("v", F.col("doc_id").alias(s), F.col("n").alias(f"n_{s}"), F.col("c").alias(f"c_{s}")) for s in ("a", "b"))
    cool_rest = left.join(right, "v").where((F.col("a") < F.col("b")) & (F.col("c_a") != F.col("c_b")) & _sizes_fit(F.col("n_a"), F.col("n_b"), per_cent)).select("a", "b")
    done = first.select("a", "b").unionByName(second.select("a", "b"))
    rest = cool_rest.distinct().join(done, ["a", "b"], "left_anti")
    third = _verified(common.materialise(_estimated(rest, sketched, per_cent), "dup-pairs"), docs, width, per_cent)
    linked = linked.unionByName(third.where("linked").select("a", "b")).unionByName(met)
    labels = components(linked if bridges is None else linked.unionByName(bridges))

    # Copies take the component of their representative, which a large class shares: pre-joined on the side of the classes.
    placed = base.groupBy("doc_id").agg(F.max("n").cast("long").alias("n_shingles"), F.count("*").cast("int").alias("times"))
    placed = placed.join(_of_copies(copies, labels), "doc_id", "left").join(labels.withColumnRenamed("node", "doc_id"), "doc_id", "left")
    placed = placed.withColumn("component_id", F.coalesce("of_rep", "component", "doc_id")).withColumn("_row", F.explode(F.array_repeat(F.lit(0), F.col("times"))))
    out = placed.select("doc_id", "n_shingles", "component_id", (F.col("doc_id") == F.col("component_id")).alias("kept"))
    # A null doc_id links with nothing, but its set has a size too.
    unknown = set_sizes(docs.where(F.col("doc_id").isNull()), width)
    return out.unionByName(unknown.select("doc_id", "n_shingles", F.lit(None).cast("long").alias("component_id"), F.lit(True).alias("kept")))


def _met_by_key(rows: DataFrame, unique: DataFrame, key: str, large: Column) -> DataFrame:
    """Inner join with a table of unique keys; the rows of its ``large`` keys, few by that condition, never meet in one task."""
    top, few = F.broadcast(unique.where(large)), unique.where(~large)
    return rows.join(top, key).unionByName(rows.join(top.select(key), key, "left_anti").join(few, key))


def _of_copies(copies: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, of_rep: the component of the representative of every copy."""
    sizes = common.materialise(copies.groupBy("rep").agg(F.count("*").alias("held")), "dup-reps")
    named = sizes.join(labels.withColumnRenamed("node", "rep"), "rep", "left").select("rep", "held", F.coalesce("component", "rep").alias("of_rep"))
    named = common.materialise(named, "dup-reps")
    common.discard(sizes)
    return _met_by_key(copies, named, "rep", F.col("held") > max(HOT_LEAST, copies.count() // LARGE_NODES)).select("doc_id", "of_rep")


def op2_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return link(common.table(spark, sf_dir, "documents"), width=3, per_cent=85)


OP2_SQL = r"""
WITH RECURSIVE d AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) >= 3 THEN list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2]) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END) AS g
  FROM d),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS same FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY a.doc_id, b.doc_id),
e AS (SELECT x, y FROM p JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE 100 * same >= 85 * (a.n + b.n - same)),
both_ways AS (SELECT x, y FROM e UNION ALL SELECT y, x FROM e),
walk AS (SELECT doc_id AS node, doc_id AS root FROM documents UNION SELECT b.y, w.root FROM walk w JOIN both_ways b ON b.x = w.node WHERE w.root < b.y),
c AS (SELECT node, min(root) AS component_id FROM walk GROUP BY node)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, c.component_id, d.doc_id = c.component_id AS kept FROM d LEFT JOIN n ON n.doc_id = d.doc_id JOIN c ON c.node = d.doc_id
"""
