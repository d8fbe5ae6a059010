"""SimHash near-duplicate groups, searched through pivot distance tables.

Every distinct 64-bit fingerprint carries its Hamming distances to a set of reference
fingerprints (pivots). By the triangle inequality two fingerprints within r bits differ by at most
r in each coordinate, so a pair with a larger coordinate difference is dropped before its exact
distance is taken. Rows meet in the tables of a pigeonhole scheme: the 64 bits are cut into blocks,
and at most r differing bits leave some choice of (blocks - r) blocks equal, so no link is missed. A
bucket over HOT rows is dealt out as pairs of slots; every pair of its rows meets in one of them.

Defined results: a null text counts as empty and gets fingerprint zero; a null id is kept and takes
its group's smallest id (null if there is none); repeated rows give repeated result rows; an empty
table gives an empty result; other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from deltamp.llm.common import as_bytes, mix64, settle

RADIUS = 3
PIVOTS = 16
HOT = 4000
_LOWER = bytes.maketrans(b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"abcdefghijklmnopqrstuvwxyz")


def fingerprint(raw: bytes, shingle: int = 3) -> int:
    """The 64-bit SimHash of one text's word shingles, as an unsigned integer."""
    words = raw.translate(_LOWER).split()
    if not words:
        return 0
    if len(words) <= shingle:
        return xxhash.xxh64_intdigest(b" ".join(words), 42)
    flat = b" ".join(words)
    ends = np.cumsum(np.fromiter(map(len, words), np.int64, len(words)) + 1) - 1
    starts = [0, *(ends[: -shingle] + 1).tolist()]
    digest = xxhash.xxh64_intdigest
    hashes = np.array([digest(flat[a:b], 42) for a, b in zip(starts, ends[shingle - 1 :].tolist())], np.uint64)
    total = np.zeros(64, np.int64)
    for at in range(0, len(hashes), 1 << 16):
        part = hashes[at : at + (1 << 16)]
        total += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * total > len(hashes), bitorder="little").view(np.uint64)[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", shingle: int = 3) -> DataFrame:
    """One row per input row: the id and fp, the fingerprint as a signed 64-bit integer."""
    id_type = docs.schema[id_col].dataType
    schema = T.StructType([T.StructField(id_col, id_type), T.StructField("fp", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = np.array([fingerprint(x, shingle) for x in as_bytes(b.column(1))], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps)], names=[id_col, "fp"])

    return docs.select(id_col, F.col(text_col).cast("string")).mapInArrow(run, schema)


def block_masks(blocks: int, radius: int = RADIUS) -> list[int]:
    """Signed masks of every choice of (blocks - radius) out of so many nearly equal blocks of 64 bits."""
    from itertools import combinations

    cuts = [64 * i // blocks for i in range(blocks + 1)]
    part = [((1 << cuts[i + 1]) - (1 << cuts[i])) for i in range(blocks)]
    masks = [sum(part[i] for i in c) for c in combinations(range(blocks), blocks - radius)]
    return [m - (1 << 64) if m >= 1 << 63 else m for m in masks]


def blocks_for(rows: int) -> int:
    """Blocks whose keys are wide enough that random rows seldom share a bucket."""
    return 5 if rows < 1 << 23 else 6 if rows < 1 << 30 else 7


def pivots(n: int = PIVOTS) -> np.ndarray:
    """Reference fingerprints by rule: the finaliser over 1..n."""
    return mix64(np.arange(1, n + 1, dtype=np.uint64))


def pivot_table(fps: np.ndarray, n: int = PIVOTS) -> np.ndarray:
    """Hamming distances of every fingerprint to every pivot, as int8."""
    return np.bitwise_count(fps[:, None] ^ pivots(n)[None, :]).astype(np.int8)


def close_pairs(fps: np.ndarray, coords: np.ndarray, radius: int = RADIUS) -> tuple[np.ndarray, np.ndarray]:
    """Links that span each group of a bucket: (child, parent) positions, fewer than rows."""
    n = len(fps)
    root = np.arange(n)

    def find(i: int) -> int:
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    left, right = [], []
    order = np.argsort(coords[:, 0], kind="stable")
    fps, coords = fps[order], coords[order]
    step = 512
    for a in range(0, n, step):
        rows = slice(a, min(n, a + step))
        stop = int(np.searchsorted(coords[:, 0], coords[rows.stop - 1, 0] + radius, side="right"))
        near = np.abs(coords[rows, None, 0] - coords[None, a:stop, 0]) <= radius
        for k in (1, 2, 3):
            near &= np.abs(coords[rows, None, k] - coords[None, a:stop, k]) <= radius
        i, j = np.nonzero(np.triu(near, 1))
        keep = (np.abs(coords[a + i, 4:] - coords[a + j, 4:]) <= radius).all(axis=1)
        i, j = i[keep] + a, j[keep] + a
        exact = np.bitwise_count(fps[i] ^ fps[j]) <= radius
        for x, y in zip(i[exact].tolist(), j[exact].tolist()):
            p, q = find(x), find(y)
            if p != q:
                root[max(p, q)] = min(p, q)
                left.append(x)
                right.append(y)
    return order[np.array(left, int)], order[np.array(right, int)]


def _bucket_links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by (bucket, key, slots): compares the rows of each bucket; a bucket may span batches."""
    held: np.ndarray | None = None

    def out(rows: np.ndarray) -> pa.RecordBatch | None:
        """rows: columns key parts 0..3, then the fingerprint; whole buckets."""
        cut = np.flatnonzero((rows[1:, :4] != rows[:-1, :4]).any(axis=1)) + 1
        starts = np.concatenate([[0], cut])
        sizes = np.diff(np.concatenate([starts, [len(rows)]]))
        fps = rows[:, 4].view(np.uint64)
        a, b = [], []
        two = starts[sizes == 2]
        x, y = fps[two], fps[two + 1]
        near = (np.abs(pivot_table(x) - pivot_table(y)) <= RADIUS).all(axis=1) & (np.bitwise_count(x ^ y) <= RADIUS)
        a.append(x[near]), b.append(y[near])
        for s, n in zip(starts[sizes > 2].tolist(), sizes[sizes > 2].tolist()):
            part = fps[s : s + n]
            i, j = close_pairs(part, pivot_table(part))
            a.append(part[i]), b.append(part[j])
        a, b = np.concatenate(a).view(np.int64), np.concatenate(b).view(np.int64)
        return pa.RecordBatch.from_arrays([pa.array(np.maximum(a, b)), pa.array(np.minimum(a, b))], names=["a", "b"]) if len(a) else None

    for batch in batches:
        rows = np.stack([c.to_numpy(zero_copy_only=False).astype(np.int64) for c in batch.columns], axis=1)
        rows = rows if held is None else np.concatenate([held, rows])
        if not len(rows):
            continue
        last = int(np.flatnonzero((rows[:, :4] != rows[-1, :4]).any(axis=1))[-1]) + 1 if (rows[0, :4] != rows[-1, :4]).any() else 0
        held = rows[last:]
        if last and (done := out(rows[:last])) is not None:
            yield done
    if held is not None and len(held) and (done := out(held)) is not None:
        yield done


def links(distinct: DataFrame, rows: int, hot: int = HOT) -> DataFrame:
    """Links (a > b) that span the groups of distinct fingerprints (column fp), within RADIUS bits."""
    masks = block_masks(blocks_for(rows))
    keyed = distinct.select("fp", F.explode(F.array(*[F.struct(F.lit(t).alias("t"), F.col("fp").bitwiseAND(F.lit(m)).alias("key")) for t, m in enumerate(masks)])).alias("k")).select("k.t", "k.key", "fp")
    sizes = keyed.groupBy("t", "key").agg(F.count("*").alias("n")).where("n > 1")
    slots = F.when(F.col("n") <= hot, F.lit(1)).otherwise(F.ceil(F.col("n") / (hot // 2))).cast("int")
    mine = F.pmod(F.xxhash64("fp"), F.col("slots")).cast("int")
    met = keyed.join(sizes, ["t", "key"]).withColumn("slots", slots).withColumn("mine", mine)
    met = met.select("t", "key", "mine", "fp", F.explode(F.sequence(F.lit(0), F.col("slots") - 1)).alias("other"))
    met = met.select("t", "key", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"), "fp")
    parts = max(16, min(20_000, rows * len(masks) // 50_000))
    dealt = met.repartition(parts, "t", "key", "i", "j").sortWithinPartitions("t", "key", "i", "j")
    return dealt.mapInArrow(_bucket_links, "a long, b long").distinct()


def components(edges: DataFrame) -> DataFrame:
    """The smallest node of each node's component, by alternating large and small stars.

    edges (a > b). Each round is a few joins and minima over the edges, settled in the shared folder; rounds go on
    until one changes nothing, some log(nodes) of them.
    Nodes without an edge don't appear. Result: node, root.
    """

    def mark(e: DataFrame) -> tuple:
        r = e.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        return tuple(r)

    e = settle(edges.select("a", "b").where("a <> b").distinct())
    before = mark(e)
    while before[0]:
        both = e.union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        e = both.where("b > a").join(low, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        low = e.groupBy("a").agg(F.min("b").alias("m"))
        joined = e.join(low, "a")
        e = settle(joined.select(F.col("b").alias("a"), F.col("m").alias("b")).union(joined.select("a", F.col("m").alias("b"))).where("a <> b").distinct())
        after = mark(e)
        if after == before:
            break
        before = after
    return e.select(F.col("a").alias("node"), F.col("b").alias("root"))


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: the id, fp and component_id, the smallest id reachable over links, itself included."""
    marked = settle(fingerprints(docs, id_col, text_col))
    distinct = marked.groupBy("fp").agg(F.min(id_col).alias("least"))
    rows = distinct.count()
    found = components(links(distinct.select("fp"), rows))
    grouped = distinct.join(found, distinct["fp"] == found["node"], "left").select(distinct["fp"], "least", F.coalesce("root", distinct["fp"]).alias("root"))
    heads = grouped.groupBy("root").agg(F.min("least").alias("component_id"))
    named = grouped.join(heads, "root").select("fp", "component_id")
    return marked.join(named, "fp").select(id_col, "fp", "component_id")
