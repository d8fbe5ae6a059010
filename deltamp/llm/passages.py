"""Exact removal of word runs that occur more than once in a corpus, and automata for bounded references.

Corpus-wide removal (repeated_runs): the named method broadcasts suffix automata of reference shards
and streams every document past every shard. With the corpus as its own reference that is shards
times corpus, so it can't finish at scale. Here each group of documents sends its distinct run
hashes once to the bucket of the hash, each bucket answers which of them two groups hold, and the
answers meet the documents again. Work is linear, and a passage in a third of all documents counts
once per group. Hashes have 64 bits.

Bounded references (Automaton, matching_spans): a suffix automaton over words gives, per text
position, the longest match that ends there; spans at or over the threshold are maximal matches.

Defined results: null text is empty; texts under the window lose nothing; repeated rows repeat
each other and so go whole; empty tables give empty results; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import compress

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from deltamp.llm.common import as_bytes, run_hashes, size_units, word_hashes_many

WINDOW = 35
GROUP_BYTES = 2 << 20
BUCKET_BYTES = 16 << 20


class Automaton:
    """A suffix automaton over word sequences, with how often each state's strings occur."""

    def __init__(self, sequences: list[list]):
        self.next, self.link, self.length, self.count = [{}], [-1], [0], [0]
        for words in sequences:
            last = 0
            for w in words:
                last = self._grow(last, w)
        for s in sorted(range(1, len(self.next)), key=self.length.__getitem__, reverse=True):
            if self.link[s] > 0:
                self.count[self.link[s]] += self.count[s]

    def _state(self, length: int, link: int, moves: dict, count: int) -> int:
        self.next.append(moves), self.link.append(link), self.length.append(length), self.count.append(count)
        return len(self.next) - 1

    def _split(self, p: int, q: int, w) -> int:
        twin = self._state(self.length[p] + 1, self.link[q], dict(self.next[q]), 0)
        while p >= 0 and self.next[p].get(w) == q:
            self.next[p][w] = twin
            p = self.link[p]
        self.link[q] = twin
        return twin

    def _grow(self, last: int, w) -> int:
        if (q := self.next[last].get(w)) is not None:
            q = q if self.length[q] == self.length[last] + 1 else self._split(last, q, w)
            self.count[q] += 1
            return q
        new, p = self._state(self.length[last] + 1, 0, {}, 1), last
        while p >= 0 and w not in self.next[p]:
            self.next[p][w] = new
            p = self.link[p]
        if p >= 0:
            q = self.next[p][w]
            self.link[new] = q if self.length[q] == self.length[p] + 1 else self._split(p, q, w)
        return new

    def matches(self, words: list) -> list[int]:
        """Matching statistics: the longest run that ends at each word and occurs in the reference."""
        s = n = 0
        out = []
        for w in words:
            while s and w not in self.next[s]:
                s = self.link[s]
                n = self.length[s]
            if w in self.next[s]:
                s, n = self.next[s][w], n + 1
            out.append(n)
        return out

    def spans(self, words: list, least: int = WINDOW) -> list[tuple[int, int]]:
        """Merged maximal spans of at least so many words that occur in the reference."""
        out: list[tuple[int, int]] = []
        for end, n in enumerate(self.matches(words), 1):
            if n >= least:
                a = end - n
                while out and out[-1][1] >= a:
                    a = min(a, out.pop()[0])
                out.append((a, end))
        return out


def remove_reference_spans(docs: DataFrame, reference: list[str], least: int = WINDOW, id_col: str = "doc_id", text_col: str = "text", most_words: int = 1_000_000) -> DataFrame:
    """Cut every maximal span of least or more words that occurs in a bounded reference.

    The reference's automaton is broadcast; its words are checked against most_words first.
    """
    sequences = [x.encode().split() for x in reference]
    if sum(map(len, sequences)) > most_words:
        raise ValueError("the reference is over most_words; use repeated_runs or shard it")
    shared = docs.sparkSession.sparkContext.broadcast(Automaton(sequences))
    schema = T.StructType([T.StructField(id_col, docs.schema[id_col].dataType), T.StructField("text", T.StringType()), T.StructField("n_removed", T.LongType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            texts, gone = [], []
            for raw in as_bytes(b.column(1)):
                words = raw.split()
                keep = np.ones(len(words), bool)
                for a, z in shared.value.spans(words, least):
                    keep[a:z] = False
                texts.append(b" ".join(compress(words, keep.tolist())).decode())
                gone.append(int((~keep).sum()))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(texts, pa.string()), pa.array(gone, pa.int64())], names=schema.names)

    return docs.select(id_col, F.col(text_col).cast("string")).mapInArrow(run, schema)


def _windows(raws: list[bytes], window: int) -> list[np.ndarray]:
    """Window hashes of each text."""
    flat, sizes = word_hashes_many(raws)
    ends = np.cumsum(sizes)
    return [run_hashes(flat[z - n : z], window) for n, z in zip(sizes.tolist(), ends.tolist())]


def _bucket_of(hashes: np.ndarray, buckets: int) -> np.ndarray:
    return ((hashes >> np.uint64(33)) * np.uint64(buckets) >> np.uint64(31)).astype(np.int64)


def repeated_runs(docs: DataFrame, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: id, n_words, n_removed and kept (the kept words joined by one space, UTF-8 bytes).

    A word goes if some window over it has a word sequence that starts anywhere else too.
    """
    id_type = docs.schema[id_col].dataType
    narrow = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    groups, buckets = size_units(docs, text_col, GROUP_BYTES, BUCKET_BYTES, least=64)
    # The partition's number goes in, so that rows which repeat all over the input don't meet in one group.
    grouped = narrow.withColumn("g", F.pmod(F.xxhash64("id", "text", F.spark_partition_id()), F.lit(groups)).cast("int"))
    parts = max(16, groups // 8)
    dealt = grouped.repartition(parts, "g")

    def send(key, group):
        parts = _windows(as_bytes(group.column("text").combine_chunks()), window)
        mine = np.unique(np.concatenate(parts)) if parts else np.zeros(0, np.uint64)
        at = np.searchsorted(_bucket_of(mine, buckets), np.arange(buckets + 1))
        there = np.flatnonzero(np.diff(at))
        return pa.table({"bucket": pa.array(there, pa.int32()), "g": pa.array([key[0].as_py()] * len(there), pa.int32()), "hashes": pa.array([mine[at[i] : at[i + 1]].tobytes() for i in there], pa.binary())})

    def answer(group):
        blobs = [np.frombuffer(x, np.uint64) for x in group.column("hashes").to_pylist()]
        flat = np.sort(np.concatenate(blobs))
        twice = np.unique(flat[1:][flat[1:] == flat[:-1]])
        out = []
        for b in blobs:
            i = np.searchsorted(twice, b)
            i[i == len(twice)] = 0
            out.append(b[twice[i] == b].tobytes() if len(twice) else b"")
        return pa.table({"g": group.column("g"), "hashes": pa.array(out, pa.binary())}).filter(pa.array([bool(x) for x in out], pa.bool_()))

    def strike(key, docs, told):
        raws = as_bytes(docs.column("text").combine_chunks()) if docs.num_rows else []
        known = np.sort(np.concatenate([np.zeros(0, np.uint64), *(np.frombuffer(x, np.uint64) for x in told.column("hashes").to_pylist())]))
        runs = _windows(raws, window)
        flat = np.sort(np.concatenate(runs)) if runs else known
        known = np.union1d(known, flat[1:][flat[1:] == flat[:-1]])
        n, gone, kept = [], [], []
        for raw, run in zip(raws, runs):
            words = raw.split()
            n.append(len(words))
            hit = np.zeros(0, int)
            if len(run) and len(known):
                i = np.searchsorted(known, run)
                i[i == len(known)] = 0
                hit = np.flatnonzero(known[i] == run)
            if len(hit):
                edge = np.zeros(len(words) + 1, np.int64)
                np.add.at(edge, hit, 1)
                np.add.at(edge, hit + window, -1)
                keep = np.cumsum(edge[:-1]) == 0
                words = list(compress(words, keep.tolist()))
            gone.append(n[-1] - len(words))
            kept.append(b" ".join(words))
        return pa.table({"id": docs.column("id"), "n_words": pa.array(n, pa.int64()), "n_removed": pa.array(gone, pa.int64()), "kept": pa.array(kept, pa.binary())})

    sent = dealt.groupBy("g").applyInArrow(send, "bucket int, g int, hashes binary")
    told = sent.repartition(parts, "bucket").groupBy("bucket").applyInArrow(answer, "g int, hashes binary").repartition(parts, "g")
    schema = T.StructType([T.StructField("id", id_type), T.StructField("n_words", T.LongType()), T.StructField("n_removed", T.LongType()), T.StructField("kept", T.BinaryType())])
    out = dealt.groupBy("g").cogroup(told.groupBy("g")).applyInArrow(strike, schema)
    return out.withColumnRenamed("id", id_col)


def brute_force(texts: list[str | None], window: int = WINDOW) -> list[tuple[int, int, str]]:
    """The contract by direct counting, for tests: (n_words, n_removed, digest) per text."""
    from collections import Counter

    docs = [(t or "").encode().split() for t in texts]
    seen = Counter(tuple(d[i : i + window]) for d in docs for i in range(len(d) - window + 1))
    out = []
    for d in docs:
        gone = {j for i in range(len(d) - window + 1) if seen[tuple(d[i : i + window])] > 1 for j in range(i, i + window)}
        out.append((len(d), len(gone), hashlib.sha256(b" ".join(w for j, w in enumerate(d) if j not in gone)).hexdigest()))
    return out
