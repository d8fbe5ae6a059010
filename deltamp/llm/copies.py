"""Near copies by word shingles: groups of texts linked by a Jaccard similarity of LEAST_SIMILAR or more.

Pairs are proposed twice and judged once. The SimHash of a text's shingles is searched through pivot distance tables
(deltamp.llm.simhash): rows within its RADIUS of 3 bits meet, pivots discard, Hamming verifies. Most texts at a
similarity of 0.8 differ in more bits, so MinHash bands propose what lies farther: BANDS keys of ROWS minima each, so a pair at 0.8 shares no key with
probability (1 - 0.8 ** ROWS) ** BANDS, 2 in a million, and a closer one with less. Every pair is judged by its
exact similarity. A bucket is first compared with its smallest fingerprint, which links most of it. Buckets that
then still hold several groups are gathered with their rows' shingle sets, and each pair of rows in different
groups is compared there, inside the task: sizes and SimHash fingerprints of the sets discard pairs (over RADIUS
bits at a similarity of 0.8 has a chance of 2 in ten million), shared shingles are counted for the survivors, and
only links that join two groups come out, fewer than rows. A bucket over HOT rows is dealt out as pairs of slots;
every pair of its rows meets in one of them.

Defined results: upper and lower ASCII letters are the same; a text of fewer than SHINGLE words is one shingle;
null counts as empty, and texts without words are copies of each other. One row of each group stays, the one
with the smallest id (a null id comes last; of equal ids the smallest row hash), with all its columns; equal
ids in different groups don't touch each other.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from deltamp.llm.common import as_bytes, mix64, run_hashes, settle, word_hashes_many
from deltamp.llm import simhash
from deltamp.llm.simhash import components

SHINGLE, LEAST_SIMILAR = 5, 0.8
BANDS, ROWS = 25, 4
RADIUS, HOT = 26, 4000
_FLIP, _TIMES = mix64(np.arange(1, BANDS * ROWS + 1, dtype=np.uint64)), mix64(np.arange(1001, BANDS * ROWS + 1001, dtype=np.uint64)) | np.uint64(1)


def shingle_sets(raws: list[bytes], shingle: int = SHINGLE) -> list[np.ndarray]:
    """The sorted distinct shingle hashes of each text."""
    flat, sizes = word_hashes_many(raws, lower=True)
    stops = np.cumsum(sizes)
    return [np.unique(run_hashes(flat[z - n : z], min(shingle, n))) if n else np.zeros(0, np.uint64) for n, z in zip(sizes.tolist(), stops.tolist())]


def set_hash(shingles: np.ndarray) -> np.uint64:
    with np.errstate(over="ignore"):
        return mix64(np.array([mix64(shingles).sum(dtype=np.uint64) + np.uint64(len(shingles))], np.uint64))[0]


def band_keys(shingles: np.ndarray) -> np.ndarray:
    least = np.full(BANDS * ROWS, ~np.uint64(0))
    with np.errstate(over="ignore"):
        for a in range(0, len(shingles), 2048):
            least = np.minimum(least, ((shingles[a : a + 2048, None] ^ _FLIP) * _TIMES).min(axis=0))
        rows = mix64(least ^ _FLIP).reshape(BANDS, ROWS)
        return mix64((rows * _TIMES[:ROWS]).sum(axis=1, dtype=np.uint64) + np.arange(BANDS, dtype=np.uint64))


def similarity(a: np.ndarray, b: np.ndarray) -> float:
    both = len(np.intersect1d(a, b, assume_unique=True))
    return both / (len(a) + len(b) - both)


def fingerprint(shingles: np.ndarray) -> np.uint64:
    """The SimHash of a shingle set."""
    total = np.zeros(64, np.int64)
    for at in range(0, len(shingles), 1 << 14):
        part = np.ascontiguousarray(shingles[at : at + (1 << 14)])
        total += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return np.packbits(2 * total > len(shingles), bitorder="little").view(np.uint64)[0]


def bucket_links(fps: list[int], roots: list[int], sims: np.ndarray, sets: list[np.ndarray]) -> list[tuple[int, int]]:
    """Pairs (greater, smaller) of similar rows that join the groups of one bucket."""
    n = len(fps)
    number = {r: k for k, r in enumerate(dict.fromkeys(roots))}
    group = [number[r] for r in roots]
    up = list(range(len(number)))

    def find(k: int) -> int:
        while up[k] != k:
            up[k] = up[up[k]]
            k = up[k]
        return k

    order = np.argsort(np.array([len(x) for x in sets]), kind="stable")
    sizes = np.array([len(sets[k]) for k in order])
    flat = np.concatenate([sets[k] for k in order])
    _, kind = np.unique(flat, return_inverse=True)
    begins = np.concatenate([[0], np.cumsum(sizes)])
    by_kind = np.argsort(kind, kind="stable")  # postings: rows in order of size, by shingle
    starts = np.concatenate([[0], np.cumsum(np.bincount(kind))])
    owner = np.repeat(np.arange(n), sizes)[by_kind]
    mine, sim = np.array(group)[order], sims[order]
    out = []
    for i in range(n):
        stop = int(np.searchsorted(sizes, sizes[i] / LEAST_SIMILAR + 1e-9, side="right"))
        near = np.flatnonzero((np.bitwise_count(sim[i + 1 : stop] ^ sim[i]) <= RADIUS) & (mine[i + 1 : stop] != mine[i])) + i + 1
        near = [j for j in near.tolist() if find(mine[j]) != find(mine[i])]
        if not near:
            continue
        if len(near) > 16:
            words = kind[begins[i] : begins[i + 1]]
            shared = np.bincount(np.concatenate([owner[starts[w] : starts[w + 1]] for w in words.tolist()]), minlength=n)
            alike = shared[near] >= LEAST_SIMILAR * (sizes[i] + sizes[near] - shared[near]) - 1e-9
        else:
            alike = [similarity(sets[order[i]], sets[order[j]]) >= LEAST_SIMILAR for j in near]
        for j, yes in zip(near, alike):
            p, q = find(mine[i]), find(mine[j])
            if yes and p != q:
                up[max(p, q)] = min(p, q)
                x, y = fps[order[i]], fps[order[j]]
                out.append((max(x, y), min(x, y)))
    return out


def fingered(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """The rows with _fp, the hash of their shingle set."""
    schema = T.StructType([*docs.schema.fields, T.StructField("_fp", T.LongType())])
    at = docs.columns.index(text_col)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            fps = np.array([set_hash(s) for s in shingle_sets(as_bytes(b.column(at)))], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(fps)], names=schema.names)

    return docs.mapInArrow(run, schema)


def banded(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """Per row (id, row hash, _fp, sim, keys); sim is the SimHash."""
    schema = "id {}, row long, _fp long, sim long, keys array<long>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            sets = shingle_sets(as_bytes(b.column(2)))
            fps = np.array([set_hash(s) for s in sets], np.uint64).view(np.int64)
            sims = np.array([fingerprint(s) for s in sets], np.uint64).view(np.int64)
            keys = [band_keys(s).view(np.int64).tolist() if len(s) else [] for s in sets]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(fps), pa.array(sims), pa.array(keys, pa.list_(pa.int64()))], names=["id", "row", "_fp", "sim", "keys"])

    return docs.mapInArrow(run, schema.format(docs.schema["id"].dataType.simpleString()))


def pivot_pairs(slim: DataFrame) -> DataFrame:
    """Pairs (a > b) of shingle-set hashes whose SimHashes are equal or linked through the pivot tables, spanning their groups."""
    heads = settle(slim.groupBy("sim").agg(F.min("_fp").alias("head")))
    found = simhash.links(heads.select(F.col("sim").alias("fp")), heads.count())
    one, two = (heads.select(F.col("sim").alias(k), F.col("head").alias(f"h{k}")) for k in "ab")
    apart = found.join(one, "a").join(two, "b").select("ha", "hb")
    pairs = slim.select("_fp", "sim").distinct().join(heads, "sim").select(F.col("_fp").alias("ha"), F.col("head").alias("hb")).union(apart)
    return pairs.where("ha <> hb").select(F.greatest("ha", "hb").alias("a"), F.least("ha", "hb").alias("b")).distinct()


def judged(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """Of pairs (a > b), those similar enough."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            one, two = ([np.frombuffer(s, np.uint64) for s in x.column(k).to_pylist()] for k in (2, 3))
            near = [similarity(p, q) >= LEAST_SIMILAR for p, q in zip(one, two)]
            yield x.select(["a", "b"]).filter(pa.array(near, pa.bool_()))

    one, two = (sets.select(F.col("fp").alias(k), F.col("set").alias(f"s{k}")) for k in "ab")
    return settle(pairs.join(one, "a").join(two, "b").select("a", "b", "sa", "sb").mapInArrow(run, "a long, b long"))


def _gathered_links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (key, i, j, fp, root, sim, set) in order of their buckets to the links of each; a bucket may span batches."""
    held: list[tuple] = []

    def out() -> pa.RecordBatch:
        found = bucket_links([r[3] for r in held], [r[4] for r in held], np.array([r[5] for r in held], np.int64).view(np.uint64), [np.frombuffer(r[6], np.uint64) for r in held])
        return pa.RecordBatch.from_arrays([pa.array([x[k] for x in found], pa.int64()) for k in (0, 1)], names=["a", "b"])

    for batch in batches:
        for row in zip(*(c.to_pylist() for c in batch.columns)):
            if held and row[:3] != held[0][:3]:
                yield out()
                held = []
            held.append(row)
    if held:
        yield out()


def links(slim: DataFrame, texts: DataFrame, text_col: str = "text", hot: int = HOT) -> DataFrame:
    """Links (a > b) that span the groups of distinct shingle sets. slim: _fp, sim, keys; texts: _fp and the text."""
    keyed = slim.groupBy("_fp").agg(F.first("keys").alias("keys")).select(F.col("_fp").alias("fp"), F.explode("keys").alias("key"))
    buckets = keyed.groupBy("key").agg(F.min("fp").alias("centre"), F.count("*").alias("n")).where("n > 1")
    met = settle(keyed.join(buckets, "key"))
    stars = met.where("fp <> centre").select(F.col("fp").alias("a"), F.col("centre").alias("b")).distinct()
    near = settle(pivot_pairs(slim))
    wanted = met.select(F.col("fp").alias("_fp")).union(near.select("a")).union(near.select("b")).distinct()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            found = shingle_sets(as_bytes(b.column(1)))
            sims = np.array([fingerprint(x) for x in found], np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(sims), pa.array([x.tobytes() for x in found], pa.binary())], names=["fp", "sim", "set"])

    one_each = texts.select("_fp", F.col(text_col).cast("string").alias("t")).join(wanted, "_fp", "left_semi").dropDuplicates(["_fp"])
    sets = settle(one_each.mapInArrow(run, "fp long, sim long, set binary"))
    first = judged(stars.union(near).distinct(), sets)
    root = settle(components(first))
    rooted = settle(met.join(root, F.col("fp") == F.col("node"), "left").select("key", "n", "fp", F.coalesce("root", "fp").alias("root")))
    several = rooted.groupBy("key").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo <> hi").select("key")
    slots = F.when(F.col("n") <= hot, F.lit(1)).otherwise(F.ceil(F.col("n") / (hot // 2))).cast("int")
    open_rows = rooted.join(several, "key", "left_semi").withColumn("slots", slots).withColumn("mine", F.pmod(F.xxhash64("fp"), F.col("slots")).cast("int"))
    dealt = open_rows.select("key", "mine", "fp", "root", F.explode(F.sequence(F.lit(0), F.col("slots") - 1)).alias("other"))
    dealt = dealt.select("key", F.least("mine", "other").alias("i"), F.greatest("mine", "other").alias("j"), "fp", "root").join(sets, "fp")
    gathered = dealt.select("key", "i", "j", "fp", "root", "sim", "set").repartition("key", "i", "j").sortWithinPartitions("key", "i", "j")
    return first.union(gathered.mapInArrow(_gathered_links, "a long, b long").distinct())


def keep_one_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One determined row of each group of near copies, with the columns of docs."""
    hashed = docs.withColumn("_row", F.xxhash64(*docs.columns))
    slim = settle(banded(hashed.select(F.col(id_col).alias("id"), F.col("_row").alias("row"), F.col(text_col).cast("string").alias("text"))))
    rows = fingered(hashed, text_col)
    root = components(links(slim, rows, text_col))
    best = lambda: F.min(F.struct("none", "id", "row", "fp")).alias("best")
    heads = slim.select(F.col("_fp").alias("fp"), F.col("id").isNull().alias("none"), "id", "row").groupBy("fp").agg(F.min(F.struct("none", "id", "row")).alias("m")).select("fp", "m.*")
    heads = heads.join(root, F.col("fp") == F.col("node"), "left").groupBy(F.coalesce("root", "fp").alias("g")).agg(best())
    heads = heads.select(F.col("best.fp").alias("_fp"), F.col("best.row").alias("_row"))
    return rows.join(heads, ["_fp", "_row"], "left_semi").dropDuplicates(["_fp", "_row"]).select(*docs.columns)
