"""Message passing: full inference, and the same state kept up by deltas (deltamp.operators.store).

A layer's update is a dense product over rows of DIMS integers; it runs on Arrow batches, after the sums.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltamp.durable import settle
from deltamp.functions.grid import DIMS, dense
from deltamp.operators.aggregators import S, X, absorb, merge



def matrix(batch: pa.RecordBatch, first: int, width: int = DIMS) -> np.ndarray:
    """Columns first to first + width of a batch as rows of integers, null counting as zero."""
    return np.stack([batch.column(k).fill_null(0).to_numpy(zero_copy_only=False) for k in range(first, first + width)], axis=1)


LAYOUT = f"v long, {', '.join(f'{x} long' for x in X)}"


def half_up_mean(total: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Rows of sums over their counts, rounded half up; zero without messages."""
    return np.where(n[:, None] > 0, np.floor(total / np.maximum(n, 1)[:, None] + 0.5), 0).astype(np.int64)


def update_rows(vertices: DataFrame, sums: DataFrame, layer: int) -> DataFrame:
    """Outputs (v, x*) of vertices (v, x*) with aggregates (dst, s*, n); no aggregate counts as zero."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n = b.column(1 + 2 * DIMS).fill_null(0).to_numpy(zero_copy_only=False)
            h = dense(matrix(b, 1), half_up_mean(matrix(b, 1 + DIMS), n), layer)
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(h[:, k]) for k in range(DIMS))], names=["v", *X])

    j = vertices.select("v", *X).join(sums.select("dst", *S, "n"), F.expr("v = dst"), "left").select("v", *X, *S, "n")
    return j.mapInArrow(run, LAYOUT)


def messages(edges: DataFrame, values: DataFrame) -> DataFrame:
    """(dst, x*) for every edge whose source has a value."""
    return edges.select("src", "dst").join(values, F.col("src") == F.col("v")).select("dst", *X)


def full(vertices: DataFrame, edges: DataFrame, layers: int = 2) -> DataFrame:
    """Mean-aggregated layers over the whole graph: the truth that deltas must reach."""
    h = vertices.select("v", *X)
    for layer in range(layers):
        h = update_rows(h, merge(absorb(messages(edges, h))), layer)
    return h


WEIGHT = "decimal(30,18)"  # sums of it are exact in any order, so a retracted weight leaves nothing behind


def attention_messages(edges: DataFrame, values: DataFrame, sign: int) -> DataFrame:
    """Delta rows (dst, num, den, n) of edges whose two ends have a value (v, x*), under one head's scores of both ends."""
    a, b = (values.select("v", *[(F.col(x) / 1024.0).alias(x) for x in X]).alias(k) for k in "ab")
    j = edges.join(a, F.expr("src = a.v")).join(b, F.expr("dst = b.v"))
    w = j.select("dst", F.exp(F.expr("0.5 * a.x0 - 0.25 * b.x1")).alias("w"), F.col("a.x0").alias("m"))
    return w.select("dst", *[(sign * c).cast(WEIGHT).alias(n) for c, n in ((F.col("w") * F.col("m"), "num"), (F.col("w"), "den"))], F.lit(sign).cast("long").alias("n"))


def delta_attention(state: DataFrame, inputs: DataFrame, old_inputs: DataFrame, changed: DataFrame, edges_kept: DataFrame, added: DataFrame, deleted: DataFrame) -> DataFrame:
    """The state (dst, num, den, n) after one batch, arguments as in delta_layer().

    A score reads the destination too, so a kept edge is sent again when either of its ends changed.
    """
    moved = edges_kept.join(changed.withColumnRenamed("v", "src"), "src", "left_semi").select("eid")
    moved = moved.union(edges_kept.join(changed.withColumnRenamed("v", "dst"), "dst", "left_semi").select("eid")).distinct()
    again = edges_kept.join(moved, "eid", "left_semi")
    rows = state
    for edges, values, sign in ((again, old_inputs, -1), (again, inputs, 1), (deleted, old_inputs, -1), (added, inputs, 1)):
        rows = rows.unionByName(attention_messages(edges, values, sign))
    summed = rows.groupBy("dst").agg(*[F.sum(c).cast(WEIGHT).alias(c) for c in ("num", "den")], F.sum("n").alias("n"))
    return settle(summed.where("n > 0"))


def attention_cascade(batches: list[tuple[DataFrame, DataFrame, DataFrame]]) -> DataFrame:
    """The state after batches of (values after it, added, deleted edges), from an empty graph."""
    values, live = batches[0][0].where("false"), batches[0][1].select("eid", "src", "dst").where("false")
    state = attention_messages(live, values, 1)
    for after, added, deleted in batches:
        added, deleted = added.select("eid", "src", "dst"), deleted.select("eid", "src", "dst")
        both = added.join(deleted.select("eid"), "eid", "left_semi").select("eid")  # in one batch they cancel
        added, deleted = added.join(both, "eid", "left_anti"), deleted.join(both, "eid", "left_anti")
        kept = live.join(deleted.select("eid"), "eid", "left_anti")
        after = settle(after.select("v", *X))
        old, new = values.select("v", *X), after
        changed = settle(new.exceptAll(old).select("v").union(old.exceptAll(new).select("v")).distinct())
        state = delta_attention(state, new, old, changed, kept, added, deleted)
        values, live = after, settle(kept.unionByName(added))
    return state


def influenced(edges: DataFrame, start_at: DataFrame, hops: int) -> DataFrame:
    """Vertices (v) that an edge into start_at (v) reaches within so many layers."""
    seen = start_at.select("v").distinct()
    for _ in range(hops):
        seen = seen.union(edges.join(seen, edges["src"] == seen["v"]).select(edges["dst"].alias("v"))).distinct()
    return seen


def snapshot(events: DataFrame, until: int | None = None) -> DataFrame:
    """Edges that are live after the events up to a time: each edge's last operation decides."""
    rows = events if until is None else events.where(F.col("us") <= until)
    last = rows.groupBy("eid").agg(F.max_by(F.struct("op", "src", "dst"), F.struct("us", "seq")).alias("e"))
    return last.where("e.op <> 'del'").select("eid", "e.src", "e.dst")
