"""Vectors in one array column, added on Arrow batches: 64 sums as 64 columns cost seconds of planning and code generation.

add_up() sums inside each batch before the shuffle, and afterwards over rows sorted by vertex, where a run that
crosses a batch is carried on as one row; a task holds a batch and a row, however many messages a hub gets.

Messages along edges aren't made one by one: carried() sends an input once to each part of destinations that it has
edges to, in the narrowest integers that hold it, with those edges beside; received() adds it up there.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from deltamp.functions.grid import DIMS, dense
from deltamp.operators.aggregators import X

VECTOR = "array<bigint>"
_SUMS = f"v long, s {VECTOR}, n long"
# Edges beside one carried input, edges added at a time, and vertices whose sums a task holds.
RUN, STEP, HELD = 256, 1 << 14, 1 << 17


def pack(rows: DataFrame) -> DataFrame:
    """(v, x*) to (v, x)."""
    return rows.selectExpr("v", f"array({', '.join(X)}) AS x")


def half_up_mean(total: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Rows of sums over their counts, rounded half up; zero without messages."""
    return np.where(n[:, None] > 0, np.floor(total / np.maximum(n, 1)[:, None] + 0.5), 0).astype(np.int64)


def vectors(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """A list column as rows of integers, zero where it is null, and where it isn't."""
    there = column.is_valid().to_numpy(zero_copy_only=False)
    rows = column.flatten().to_numpy(zero_copy_only=False).reshape(-1, DIMS)
    if there.all():
        return rows, there
    out = np.zeros((len(there), DIMS), np.int64)
    out[there] = rows
    return out, there


def lists(rows: np.ndarray, there: np.ndarray | None = None) -> pa.Array:
    """Rows as a list column, null where not there."""
    if there is None or there.all():
        return pa.ListArray.from_arrays(pa.array(np.arange(len(rows) + 1, dtype=np.int32) * DIMS), pa.array(np.ascontiguousarray(rows).ravel()))
    ends = np.concatenate([[0], np.cumsum(there)]).astype(np.int32) * DIMS
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(rows[there].ravel()), mask=pa.array(~there))


def _ints(column: pa.Array) -> np.ndarray:
    return column.fill_null(0).to_numpy(zero_copy_only=False)


def _starts(keys: np.ndarray) -> np.ndarray:
    return np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]]))


def _sums(v: np.ndarray, s: np.ndarray, n: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(v), lists(s), pa.array(n)], names=["v", "s", "n"])


def _within(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(v, s, n, sign) to one row (v, s, n) a vertex and batch."""
    for b in batches:
        if b.num_rows:
            v, sign = _ints(b.column(0)), _ints(b.column(3))
            order = np.argsort(v, kind="stable")
            v, at = v[order], _starts(v[order])
            s = (vectors(b.column(1))[0] * sign[:, None])[order]
            yield _sums(v[at], np.add.reduceat(s, at, axis=0), np.add.reduceat((_ints(b.column(2)) * sign)[order], at))


def _across(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (v, s, n) in the order of v to one row a vertex; a vertex that all cancels goes."""
    kept = None
    for b in batches:
        if not b.num_rows:
            continue
        v, s, n = _ints(b.column(0)), vectors(b.column(1))[0], _ints(b.column(2))
        if kept is not None:
            v, s, n = (np.concatenate([a, c]) for a, c in zip(kept, (v, s, n)))
        at = _starts(v)
        v, s, n = v[at], np.add.reduceat(s, at, axis=0), np.add.reduceat(n, at)
        kept = v[-1:], s[-1:], n[-1:]
        yield from _live(v[:-1], s[:-1], n[:-1])
    if kept is not None:
        yield from _live(*kept)


def _live(v: np.ndarray, s: np.ndarray, n: np.ndarray) -> Iterator[pa.RecordBatch]:
    some = (n != 0) | (s != 0).any(axis=1)
    if some.any():
        yield _sums(v[some], s[some], n[some])


def add_up(rows: DataFrame, by: Column | None = None, parts: int | None = None) -> DataFrame:
    """(v, s, n, sign) to (v, s, n): sums of sign * s and sign * n. The rows of a vertex meet by a function of v, if given, in so many parts."""
    some = rows.where("v IS NOT NULL AND s IS NOT NULL").select("v", "s", "n", "sign").mapInArrow(_within, _SUMS)
    by = F.col("v") if by is None else by
    met = some.repartition(by) if parts is None else some.repartition(parts, by)
    return met.sortWithinPartitions("v").mapInArrow(_across, _SUMS)


def _blobs(flat: np.ndarray, ends: np.ndarray) -> pa.Array:
    """A binary column of flat's bytes, cut at the byte offsets ends."""
    return pa.Array.from_buffers(pa.binary(), len(ends) - 1, [None, pa.py_buffer(ends.astype(np.int32)), pa.py_buffer(np.ascontiguousarray(flat))])


def _bytes_of(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """A binary column without nulls as its bytes and the offsets into them."""
    ends = np.frombuffer(column.buffers()[1], np.int32)[column.offset : column.offset + len(column) + 1]
    return np.frombuffer(column.buffers()[2] or b"", np.uint8)[ends[0] : ends[-1]], ends - ends[0]


def _narrow(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(src, s, n) with s as the bytes of the narrowest integers that hold the batch."""
    for b in batches:
        if b.num_rows:
            rows = vectors(b.column(1))[0]
            lo, hi = int(rows.min()), int(rows.max())
            kind = next(k for k in (np.int16, np.int32, np.int64) if np.iinfo(k).min <= lo and hi <= np.iinfo(k).max)
            s = _blobs(rows.astype(kind), np.arange(len(rows) + 1) * DIMS * np.dtype(kind).itemsize)
            yield pa.RecordBatch.from_arrays([b.column(0), s, b.column(2)], names=["src", "s", "n"])


def _wide(column: pa.Array) -> np.ndarray:
    """Rows of integers from what _narrow made."""
    flat, ends = _bytes_of(column)
    widths = np.diff(ends) // DIMS
    out = np.empty((len(widths), DIMS), np.int64)
    for w in np.unique(widths).tolist():
        at = np.flatnonzero(widths == w)
        part = flat if len(at) == len(widths) else flat[ends[at][:, None] + np.arange(w * DIMS)]
        out[at] = np.ascontiguousarray(part).view(f"i{w}").reshape(-1, DIMS)
    return out


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Edges (src, p, dst, sign) to rows (src, p, to): neighbouring edges of one src and p, at most RUN a row."""
    for b in batches:
        if b.num_rows:
            src, p, dst, sign = (_ints(b.column(k)) for k in range(4))
            new = np.concatenate([[True], (src[1:] != src[:-1]) | (p[1:] != p[:-1])])
            first = np.flatnonzero(new)
            at = np.flatnonzero((np.arange(len(src)) - first[np.cumsum(new) - 1]) % RUN == 0)
            to = _blobs(np.stack([dst, sign], axis=1), np.append(at, len(src)) * 16)
            yield pa.RecordBatch.from_arrays([pa.array(src[at]), pa.array(p[at]), to], names=["src", "p", "to"])


def carried(inputs: DataFrame, edges: DataFrame, by: Column) -> DataFrame:
    """(src, s, n) and edges (src, dst, sign) to rows (p, s, n, to); by is the part of a destination.

    Edges that lie in the order of src and part make the fewest rows; any order is right. Inputs aren't broadcast,
    as shuffled bytes tell little of what they take in memory.
    """
    told = edges.where("src IS NOT NULL AND dst IS NOT NULL").select("src", by.cast("int").alias("p"), "dst", "sign")
    slim = inputs.where("src IS NOT NULL AND s IS NOT NULL").select("src", "s", "n").mapInArrow(_narrow, "src long, s binary, n long")
    return told.mapInArrow(_runs, "src long, p int, to binary").join(slim.hint("merge"), "src").select("p", "s", "n", "to")


class _Held:
    """Sums of vertices in the order they came, found through a sorted index."""

    def __init__(self):
        self.keys, self.slots = np.zeros(0, np.int64), np.zeros(0, np.int64)
        self.s, self.n = np.zeros((1024, DIMS), np.int64), np.zeros(1024, np.int64)

    def add(self, v: np.ndarray, s: np.ndarray, n: np.ndarray) -> None:
        """v: distinct, ascending."""
        at = np.searchsorted(self.keys, v)
        known = np.zeros(len(v), bool)
        known[at < len(self.keys)] = self.keys[at[at < len(self.keys)]] == v[at < len(self.keys)]
        fresh, size = np.flatnonzero(~known), len(self.keys)
        if len(fresh):
            while size + len(fresh) > len(self.n):
                self.s, self.n = np.concatenate([self.s, np.zeros_like(self.s)]), np.concatenate([self.n, np.zeros_like(self.n)])
            self.slots = np.insert(self.slots, at[fresh], np.arange(size, size + len(fresh)))
            self.keys = np.insert(self.keys, at[fresh], v[fresh])
        to = self.slots[np.searchsorted(self.keys, v)]
        self.s[to] += s
        self.n[to] += n

    def rows(self) -> Iterator[pa.RecordBatch]:
        for a in range(0, len(self.keys), STEP):
            to = self.slots[a : a + STEP]
            yield _sums(self.keys[a : a + STEP], self.s[to], self.n[to])


def _received(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (s, n, to) to sums (v, s, n): one row a vertex, or a few where a task meets more than HELD vertices."""
    held = _Held()
    for b in batches:
        if not b.num_rows:
            continue
        x, n = _wide(b.column(0)), _ints(b.column(1))
        flat, ends = _bytes_of(b.column(2))
        edges = np.ascontiguousarray(flat).view(np.int64).reshape(-1, 2)
        row = np.repeat(np.arange(len(x)), np.diff(ends) // 16)
        for a in range(0, len(row), STEP):
            v, sign, of = edges[a : a + STEP, 0], edges[a : a + STEP, 1], row[a : a + STEP]
            order = np.argsort(v, kind="stable")
            v, sign, of = v[order], sign[order], of[order]
            at = _starts(v)
            s = x[of] if (sign == 1).all() else x[of] * sign[:, None]
            held.add(v[at], np.add.reduceat(s, at, axis=0), np.add.reduceat(n[of] * sign, at))
            if len(held.keys) > HELD:
                yield from held.rows()
                held = _Held()
    yield from held.rows()


def received(rows: DataFrame, parts: int) -> DataFrame:
    """Rows (p, s, n, to) to (v, s, n), one a vertex: sums of sign * s and sign * n, in so many parts."""
    some = rows.repartition(parts, "p").select("s", "n", "to").mapInArrow(_received, _SUMS)
    return some.sortWithinPartitions("v").mapInArrow(_across, _SUMS)


INPUT, SUM, OUTPUT = 0, 1, 2


def _whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """The same rows, ordered by v, so cut that a vertex lies in one batch."""
    kept = None
    for b in batches:
        if not b.num_rows:
            continue
        b = pa.concat_batches([kept, b]) if kept is not None else b
        v = _ints(b.column(0))
        cut = int(np.searchsorted(v, v[-1]))
        if cut:
            yield b.slice(0, cut)
        kept = b.slice(cut)
    if kept is not None:
        yield kept


def update(rows: DataFrame, layer: int) -> DataFrame:
    """Rows (v, kind, seq, x, n) in the order of v, kind, seq to (v, old, new) where a layer's output changes.

    The last INPUT and OUTPUT of a vertex count, and the sum of its SUMs. An output is null without an input.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in _whole(batches):
            v, kind = _ints(b.column(0)), _ints(b.column(1))
            x, there = vectors(b.column(3))
            first = _starts(v)
            of = np.zeros(len(v), np.int64)
            of[first[1:]] = 1
            of = np.cumsum(of)
            last = np.concatenate([(of[1:] != of[:-1]) | (kind[1:] != kind[:-1]), [True]])

            def latest(k: int) -> tuple[np.ndarray, np.ndarray]:
                out, has = np.zeros((len(first), DIMS), np.int64), np.zeros(len(first), bool)
                at = last & (kind == k)
                out[of[at]], has[of[at]] = x[at], there[at]
                return out, has

            (own, has), (old, had) = latest(INPUT), latest(OUTPUT)
            total, n = np.zeros((len(first), DIMS), np.int64), np.zeros(len(first), np.int64)
            sums = np.flatnonzero(kind == SUM)
            if len(sums):
                at = _starts(of[sums])
                total[of[sums][at]] = np.add.reduceat(x[sums], at, axis=0)
                n[of[sums][at]] = np.add.reduceat(_ints(b.column(4))[sums], at)
            new = dense(own, half_up_mean(total, n), layer)
            moved = (has != had) | (has & (new != old).any(axis=1))
            if moved.any():
                yield pa.RecordBatch.from_arrays([pa.array(v[first][moved]), lists(old[moved], had[moved]), lists(new[moved], has[moved])], names=["v", "old", "new"])

    return rows.select("v", "kind", "seq", "x", "n").mapInArrow(run, f"v long, old {VECTOR}, new {VECTOR}")
