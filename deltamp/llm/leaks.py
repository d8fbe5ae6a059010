"""Benchmark decontamination by latent semantic retrieval, then subsequence and answer checks.

The benchmark's passages give a TF-IDF matrix over their own words, with document frequencies counted
over all documents. A distributed randomised SVD (sketch, one power step, Gram matrix; every pass sums
blocks by key) gives its latent space, of at most RANK dimensions. Documents stream in half-overlapping
passages of 2 * HALF words; a passage's latent inner product with an item over both lengths (the
passage's counts the words that the space knows: those of the benchmark in at most COMMON of all
documents, and all words of an item with under LEAST_RARE such) is its cosine, and at NEAR or more the item is a
candidate: no cap on their number. An item that keeps under KEPT of its energy in the space, or is longer
than a passage, isn't searched there but through an exact index of its rarest words: what holds the item
lacks at most n - need of its n words, so of n - need + t listed ones it has t. A candidate holds if the longest common subsequence of the item and
the passage with an item's length on either side covers LEAST_COMMON of the item, and LEAST_ANSWER of its
answer: what follows its last question mark, else its last sentence of ANSWER_WORDS or more words.

Broadcast: the space of the items of a passage's length or less, MOST_FEATURES rows at most, and the items,
MOST_ITEMS and MOST_WORDS at most. A larger benchmark is cut by hash into parts that fit, and each part
searches all documents; an item over the bounds is a part of its own.

Defined results: null texts and texts that share nothing match nothing; an item of fewer than LEAST_WORDS
words is held only by a text with all its words in a row, and one of fewer than EVIDENCE words by none;
repeated rows repeat their matches; empty tables give
no rows; columns other than id and text pass through keep_clean() unchanged.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from deltamp.llm.common import WORD_CLASS, as_bytes, lower_ascii, word_hashes_many

HALF, RANK, NEAR = 24, 256, 0.3
LEAST_COMMON, LEAST_ANSWER, ANSWER_WORDS, LEAST_WORDS, EVIDENCE = 0.65, 0.5, 4, 6, 3
MOST_FEATURES, MOST_ITEMS, MOST_WORDS, COMMON, LEAST_RARE = 50_000, 50_000, 5_000_000, 0.02, 5
KEPT = 0.98  # share of an item's squared length; what is lost lowers a cosine by at most sqrt(1 - KEPT) times the passage's lost share
STEP = 1_000  # half passages scored at once: a worker holds their words' latent rows


def hashes_of(raw: bytes) -> np.ndarray:
    return word_hashes_many([raw], lower=True)[0]


def answer_of(raw: bytes) -> int:
    """How many words at the item's end are its answer."""
    head, mark, tail = raw.rpartition(b"?")
    if mark and tail.split():
        return len(tail.split())
    n = 0
    for sentence in reversed(raw.strip().rstrip(b".!").replace(b"!", b".").split(b".")):
        n += len(sentence.split())
        if n >= ANSWER_WORDS:
            break
    return n


def common_length(item: np.ndarray, text: np.ndarray) -> int:
    """Length of the longest common subsequence, a machine word's worth of items at a time."""
    masks: dict[int, int] = {}
    for i, w in enumerate(item.tolist()):
        masks[w] = masks.get(w, 0) | 1 << i
    full = (1 << len(item)) - 1
    row = full
    for w in text.tolist():
        if m := masks.get(w):
            both = row & m
            row = (row + both | row - both) & full
    return len(item) - row.bit_count()


@dataclass
class Index:
    """The listed words of items: postings of words[i] stand at starts[i] to starts[i + 1]."""

    words: np.ndarray
    starts: np.ndarray
    items: np.ndarray
    times: np.ndarray  # how often the item has the word
    least: np.ndarray  # by item number: listed words that whatever holds the item must have


def least_words(n: int) -> int:
    """How many of an item's n words a text must have to hold it."""
    return n if n < LEAST_WORDS else math.ceil(LEAST_COMMON * n - 1e-9)


def build_index(items: list[np.ndarray], numbers: np.ndarray, known: np.ndarray, df: np.ndarray) -> Index:
    """The rarest words of the items of these numbers, as many as no text that holds the item can miss."""
    words, owners, times, least = [], [], [], np.zeros(len(items), np.int64)
    for k in numbers.tolist():
        word, count = np.unique(items[k], return_counts=True)
        need = least_words(len(items[k]))
        least[k] = need if need == len(items[k]) else max(1, need // 3)
        order = np.lexsort((word, df[_positions(known, word)]))
        most = int(np.searchsorted(np.cumsum(count[order]), len(items[k]) - need + least[k])) + 1
        words.append(word[order[:most]]), times.append(count[order[:most]]), owners.append(np.full(len(order[:most]), k))
    none = np.zeros(0, np.int64)
    flat = np.concatenate([none.astype(np.uint64), *words])
    order = np.argsort(flat, kind="stable")
    word, starts = np.unique(flat[order], return_index=True)
    return Index(word, np.append(starts, len(flat)), np.concatenate([none, *owners])[order], np.concatenate([none, *times])[order], least)


@dataclass
class Space:
    """What the search broadcasts: known word hashes (sorted), their latent rows, squared weights and the items."""

    known: np.ndarray
    rows: np.ndarray
    weight2: np.ndarray
    ids: list
    items: list[np.ndarray]
    answers: list[int]
    latent: np.ndarray  # of the items in near only
    near: np.ndarray  # numbers of the items searched in the space
    index: Index  # of all others


def _positions(known: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    """Where each hash stands among the known ones, or -1."""
    if not len(known) or not len(hashes):
        return np.full(len(hashes), -1, np.int64)
    i = np.searchsorted(known, hashes)
    i[i == len(known)] = 0
    return np.where(known[i] == hashes, i, -1)


def document_frequencies(docs: DataFrame, known: np.ndarray, text_col: str = "text") -> tuple[np.ndarray, int]:
    """In how many documents each known word is, and how many documents there are."""
    shared = docs.sparkSession.sparkContext.broadcast(known)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counts, n = np.zeros(len(shared.value), np.int64), 0
        for b in batches:
            for chunk in _chunks(as_bytes(b.column(0))):
                flat, sizes = word_hashes_many(chunk, lower=True)
                at = _positions(shared.value, flat)
                here = at >= 0
                pairs = np.unique(np.repeat(np.arange(len(chunk)), sizes)[here] * len(counts) + at[here])
                counts += np.bincount(pairs % max(1, len(counts)), minlength=len(counts))
                n += len(chunk)
        there = np.flatnonzero(counts)
        yield pa.RecordBatch.from_arrays([pa.array(np.append(there, -1)), pa.array(np.append(counts[there], n))], names=["f", "n"])

    total = docs.select(F.col(text_col).cast("string")).mapInArrow(run, "f long, n long").groupBy("f").agg(F.sum("n").alias("n"))
    out, n = np.zeros(len(known), np.int64), 0
    for r in total.collect():  # a row a known word
        if r["f"] < 0:
            n = r["n"]
        else:
            out[r["f"]] = r["n"]
    return out, n


def _summed_rows(frame: DataFrame, make, rows: int, width: int, block: int = 1024) -> np.ndarray:
    """Sum over all texts of make(item hash arrays): (row numbers, their values), into a (rows, width) matrix.

    A task holds the blocks of rows that its own texts touch; blocks meet by number.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[int, np.ndarray] = {}
        for b in batches:
            for at, values in make([hashes_of(x) for x in as_bytes(b.column(0))]):
                for n in np.unique(at // block).tolist():
                    mine = at // block == n
                    np.add.at(held.setdefault(n, np.zeros((min(block, rows - n * block), width))), at[mine] - n * block, values[mine])
        for n, m in held.items():
            yield pa.RecordBatch.from_arrays([pa.array([n], pa.int64()), pa.array([m.tobytes()], pa.binary())], names=["at", "m"])

    def add(table):
        m = np.frombuffer(table.column("m")[0].as_py()).copy()
        for x in table.column("m").to_pylist()[1:]:
            m += np.frombuffer(x)
        return pa.table({"at": table.column("at")[:1], "m": pa.array([m.tobytes()], pa.binary())})

    summed = frame.mapInArrow(run, "at long, m binary").groupBy("at").applyInArrow(add, "at long, m binary")
    out = np.zeros((rows, width))
    for r in summed.toLocalIterator():  # rows * width numbers in all, bounded by MOST_FEATURES and RANK
        m = np.frombuffer(r["m"]).reshape(-1, width)
        out[r["at"] * block : r["at"] * block + len(m)] = m
    return out


def randomised_svd(frame: DataFrame, known: np.ndarray, weight: np.ndarray, rank: int = RANK, extra: int = 16, seed: int = 11) -> np.ndarray:
    """Right singular vectors (features by rank) of the TF-IDF matrix of a one-column frame of texts."""
    k = max(1, min(rank + extra, len(known)))
    shared = frame.sparkSession.sparkContext.broadcast((known, weight))

    def terms(h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        known, weight = shared.value
        at = _positions(known, h)
        f, tf = np.unique(at[at >= 0], return_counts=True)
        return f, tf * weight[f]

    def back(into: np.ndarray):
        held = frame.sparkSession.sparkContext.broadcast(into)

        def make(items: list[np.ndarray]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
            for h in items:
                f, v = terms(h)
                yield f, v[:, None] * (v @ held.value[f])[None, :]

        return make

    q = np.random.default_rng(seed).standard_normal((len(known), k))
    for _ in range(2):
        q, _ = np.linalg.qr(_summed_rows(frame, back(q), len(known), k))
    held = frame.sparkSession.sparkContext.broadcast(q)

    def gram(items: list[np.ndarray]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        y = [v @ held.value[f] for f, v in map(terms, items)]
        if y:
            yield np.arange(k), np.array(y).T @ np.array(y)

    values, vectors = np.linalg.eigh(_summed_rows(frame, gram, q.shape[1], q.shape[1]))
    keep = [i for i in np.argsort(values)[::-1][:rank] if values[i] > 1e-9 * max(values.max(), 1e-300)]
    return q @ vectors[:, keep]


def benchmark_parts(benchmark: DataFrame, item_col: str = "item_id", item_text_col: str = "text") -> list[DataFrame]:
    """The benchmark in as few parts of a power of two as fit the bounds: columns i and t."""
    rows = benchmark.select(F.col(item_col).alias("i"), F.col(item_text_col).cast("string").alias("t")).where("t is not null")
    words = F.regexp_extract_all(lower_ascii(F.col("t")), F.lit(WORD_CLASS), F.lit(0))
    sized = rows.withColumn("w", words).withColumn("n", F.size("w")).withColumn("h", F.xxhash64("i", "t"))
    parts = 1
    while True:
        own = sized.withColumn("p", F.pmod("h", F.lit(parts)))
        counts = own.groupBy("p").agg(F.count("*").alias("items"), F.sum("n").alias("words"))
        kinds = own.where(F.col("n") <= 2 * HALF).select("p", F.explode("w").alias("x")).distinct().groupBy("p").agg(F.count("*").alias("kinds"))
        over = (F.col("items") > MOST_ITEMS) | (F.col("words") > MOST_WORDS) | (F.coalesce("kinds", F.lit(0)) > MOST_FEATURES)
        if not counts.join(kinds, "p", "left").where(over & (F.col("items") > 1)).head(1) or parts >= 1 << 16:
            return [rows.where(F.pmod(F.xxhash64("i", "t"), F.lit(parts)) == p) for p in range(parts)]
        parts *= 2


def fit(docs: DataFrame, part: DataFrame, text_col: str = "text") -> Space:
    """What the search for a part of the benchmark (columns i, t) needs; document frequencies are those of docs."""
    rows = [(r["i"], r["t"].encode()) for r in part.collect()]  # bounded by benchmark_parts()
    rows = [(i, raw) for i, raw in rows if len(raw.split()) >= EVIDENCE]
    items = [hashes_of(raw) for _, raw in rows]
    fits = [LEAST_WORDS <= len(h) <= 2 * HALF for h in items]
    known = np.unique(np.concatenate([np.zeros(0, np.uint64), *items]))
    df, n = document_frequencies(docs, known, text_col)
    idf = np.log((n + 1) / (df + 1))
    rare = df <= COMMON * n
    ours = np.zeros(len(known), bool)
    for h, short in zip(items, fits):
        at = _positions(known, h)
        if short and rare[at].sum() < LEAST_RARE:  # an item of common words only is searched by them all
            rare[at] = True
        ours[at] |= short
    every = known
    known, weight = known[rare & ours], idf[rare & ours] + 1e-6
    texts = part.where(F.size(F.regexp_extract_all("t", F.lit(WORD_CLASS), F.lit(0))).between(LEAST_WORDS, 2 * HALF)).select("t")
    basis = randomised_svd(texts.repartition(max(1, len(rows) // 500)), known, weight) if len(known) else np.zeros((0, 0))
    scaled = (weight[:, None] * basis).astype(np.float32)
    latent, kept = [], []
    for h, short in zip(items, fits):
        at = _positions(known, h)
        f, tf = np.unique(at[at >= 0], return_counts=True)
        row = tf @ scaled[f]
        latent.append(row / max(1e-9, float(np.sqrt((tf * weight[f] ** 2).sum()))))
        kept.append(short and row @ row >= KEPT * float(((tf * weight[f]) ** 2).sum()))
    near = np.flatnonzero(np.array(kept, bool))
    index = build_index(items, np.flatnonzero(~np.array(kept, bool)), every, df)
    latent = np.array(latent, np.float32).reshape(len(rows), scaled.shape[1])[near]
    return Space(known, scaled, (weight**2).astype(np.float32), [i for i, _ in rows], items, [answer_of(raw) for _, raw in rows], latent, near, index)


def _share(space: Space, item: int, region: np.ndarray) -> float | None:
    """The share of the item that the region has in common, if the region holds the item."""
    want = space.items[item]
    if np.isin(want, region).sum() < LEAST_COMMON * len(want):
        return None
    if len(want) < LEAST_WORDS:
        return 1.0 if len(region) >= len(want) and (np.lib.stride_tricks.sliding_window_view(region, len(want)) == want).all(axis=1).any() else None
    share = common_length(want, region) / len(want)
    tail = want[len(want) - space.answers[item] :]
    return share if share >= LEAST_COMMON and (not len(tail) or common_length(tail, region) >= LEAST_ANSWER * len(tail)) else None


def _cosine(space: Space, item: int, passage: np.ndarray) -> float:
    """The score of the search without its truncation."""
    mine, other = (p[p >= 0] for p in (_positions(space.known, space.items[item]), _positions(space.known, passage)))
    f, tf = np.unique(mine, return_counts=True)
    times = dict(zip(f.tolist(), tf.tolist()))
    dot = sum(float(space.weight2[p]) * times.get(p, 0) for p in other.tolist())
    return dot / max(1e-12, float(np.sqrt(space.weight2[mine].sum() * space.weight2[other].sum())))


def indexed(flat: np.ndarray, begins: np.ndarray, space: Space, slice_size: int = 1 << 20) -> Iterator[tuple[int, int, float, float]]:
    """(text, item, share, cosine) for the items of the index that texts hold; flat[begins[k] : begins[k + 1]] is text k.

    The region about a passage spans two neighbouring cells of its own length, so an item is tried only
    about cells that have enough of its listed words.
    """
    x = space.index
    at = _positions(x.words, flat)
    here = np.flatnonzero(at >= 0)
    if not len(here):
        return
    at = at[here]
    owner = np.searchsorted(begins, here, side="right") - 1
    lengths = np.array([len(h) for h in space.items], np.int64)
    wide = 2 * HALF + 2 * lengths
    cells = int(np.diff(begins).max()) // int(wide.min()) + 2
    posted = np.cumsum(x.starts[at + 1] - x.starts[at])
    keys, sums = np.zeros(0, np.int64), np.zeros(0, np.int64)
    a = 0
    while a < len(at):
        z = max(a + 1, int(np.searchsorted(posted, (posted[a - 1] if a else 0) + slice_size, side="right")))
        n = x.starts[at[a:z] + 1] - x.starts[at[a:z]]
        row = np.repeat(np.arange(z - a), n)
        post = x.starts[at[a:z]][row] + np.arange(len(row)) - (np.cumsum(n) - n)[row]
        item = x.items[post]
        cell = (here[a:z] - begins[owner[a:z]])[row] // wide[item]
        key = np.concatenate([keys, (owner[a:z][row] * len(lengths) + item) * cells + cell])
        keys, where = np.unique(key, return_inverse=True)
        sums = np.bincount(where, weights=np.concatenate([sums, x.times[post]])).astype(np.int64)
        a = z
    tried = np.unique(np.concatenate([keys, keys[keys % cells > 0] - 1]))

    def total(k: np.ndarray) -> np.ndarray:
        i = np.minimum(np.searchsorted(keys, k), len(keys) - 1)
        return np.where(keys[i] == k, sums[i], 0)

    item = tried // cells % len(lengths)
    enough = total(tried) + total(tried + 1) >= x.least[item]  # the last cell of a text is always empty
    found = None
    for key in tried[enough].tolist():
        pair, cell = divmod(key, cells)
        if pair == found:
            continue
        k, item = divmod(pair, len(lengths))
        want, text = space.items[item], flat[begins[k] : begins[k + 1]]
        n, span = len(want), int(wide[item])
        low = cell * span + n if cell else 0
        starts = np.arange(-(-low // HALF) * HALF, min(len(text), (cell + 1) * span + n), HALF)
        base = max(0, int(low) - n)
        run = np.concatenate([[0], np.cumsum(np.isin(text[base : (cell + 2) * span], want))])
        left, right = np.maximum(0, starts - n), np.minimum(len(text), starts + 2 * HALF + n)
        for b, lo, hi in zip(starts.tolist(), left.tolist(), right.tolist()):
            if run[hi - base] - run[lo - base] < least_words(n):
                continue
            if (share := _share(space, item, text[lo:hi])) is not None:
                found = pair
                yield k, item, share, _cosine(space, item, text[b : b + 2 * HALF])
                break


def search(raws: list[bytes], space: Space) -> list[list[tuple]]:
    """Per text: (item, share of the item in common, cosine) for each item that it holds."""
    out: list[list[tuple]] = [[] for _ in raws]
    if not space.items:
        return out
    flat, sizes = word_hashes_many(raws, lower=True)
    begins = np.concatenate([[0], np.cumsum(sizes)])
    for k, item, share, cosine in indexed(flat, begins, space):
        out[k].append((space.ids[item], share, cosine))
    if not len(space.near):
        return out
    halves = -(-sizes // HALF)
    first = np.concatenate([[0], np.cumsum(halves + 1)])  # one empty half after each text
    at = _positions(space.known, flat)
    here = np.flatnonzero(at >= 0)
    owner = np.searchsorted(begins, here, side="right") - 1
    inside = here - begins[owner]
    half = first[owner] + inside // HALF
    at = at[here]
    light = space.weight2[at]
    norm = np.bincount(half, weights=light, minlength=first[-1])
    both = norm[:-1] + norm[1:] if len(norm) > 1 else norm
    cuts = np.flatnonzero(np.concatenate([[True], half[1:] != half[:-1]])) if len(half) else np.zeros(0, int)
    filled = half[cuts]
    stop = np.append(cuts[1:], len(half))
    done: set[tuple[int, int]] = set()
    for a in range(0, len(filled), STEP):  # halves in order; the next half joins from the next row
        z = min(len(filled), a + STEP + 1)
        lo, hi = cuts[a], stop[z - 1]
        vectors = np.add.reduceat(space.rows[at[lo:hi]], cuts[a:z] - lo, axis=0)
        ids = filled[a:z]
        follows = np.flatnonzero(ids[1:] == ids[:-1] + 1)
        joined = vectors.copy()
        joined[follows] += vectors[follows + 1]
        score = (joined @ space.latent.T) / np.sqrt(np.maximum(both[np.minimum(ids, len(both) - 1)], 1e-12))[:, None].astype(np.float32)
        if z - a == STEP + 1:
            score = score[:-1]
        r, c = np.nonzero(score >= NEAR)
        for h, item, cosine in zip(ids[r].tolist(), space.near[c].tolist(), score[r, c].tolist()):
            k = int(np.searchsorted(first, h, side="right")) - 1
            if (k, item) in done:
                continue
            want = space.items[item]
            begin = (h - int(first[k])) * HALF
            region = flat[begins[k] + max(0, begin - len(want)) : min(begins[k + 1], begins[k] + begin + 2 * HALF + len(want))]
            if (share := _share(space, item, region)) is not None:
                done.add((k, item))
                out[k].append((space.ids[item], share, cosine))
    return out


CHUNK_BYTES = 1_000_000


def _chunks(raws: list[bytes]) -> Iterator[list[bytes]]:
    held, size = [], 0
    for x in raws:
        if held and size + len(x) > CHUNK_BYTES:
            yield held
            held, size = [], 0
        held.append(x)
        size += len(x)
    if held:
        yield held


def matches(docs: DataFrame, benchmark: DataFrame, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id") -> DataFrame:
    """One row per document row and item it holds: id, item, common (share of the item's words), cosine."""
    schema = T.StructType([T.StructField(id_col, docs.schema[id_col].dataType), T.StructField(item_col, benchmark.schema[item_col].dataType), T.StructField("common", T.DoubleType()), T.StructField("cosine", T.DoubleType())])

    def found_with(shared):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                found = [m for c in _chunks(as_bytes(b.column(1))) for m in search(c, shared.value)]
                at = [k for k, m in enumerate(found) for _ in m]
                flat = [x for m in found for x in m]
                if flat:
                    yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(at)), pa.array([x[0] for x in flat]), pa.array([x[1] for x in flat]), pa.array([float(x[2]) for x in flat])], names=schema.names)

        return run

    narrow = docs.select(id_col, F.col(text_col).cast("string"))
    out = None
    for part in benchmark_parts(benchmark, item_col):
        shared = docs.sparkSession.sparkContext.broadcast(fit(docs, part, text_col))
        rows = narrow.mapInArrow(found_with(shared), schema)
        out = rows if out is None else out.unionByName(rows)
    return out


def keep_clean(docs: DataFrame, benchmark: DataFrame, text_col: str = "text") -> DataFrame:
    """The rows that hold no item, with all their columns."""
    at = docs.columns.index(text_col)

    def clean_of(shared):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for b in batches:
                found = [m for c in _chunks(as_bytes(b.column(at))) for m in search(c, shared.value)]
                yield b.filter(pa.array([not m for m in found], pa.bool_()))

        return run

    out = docs
    for part in benchmark_parts(benchmark):
        out = out.mapInArrow(clean_of(docs.sparkSession.sparkContext.broadcast(fit(docs, part, text_col))), docs.schema)
    return out
