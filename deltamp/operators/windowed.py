"""The windowed forward pass over a whole event log: what each layer sends, when, and the values that leave it.

Two windows act in a layer. The gather window holds back the edges of a destination: until it closes an edge
isn't part of the layer's graph, and its message reads its source as it is then. The emit window holds back a
vertex' output: updates that fall into one window leave as one. Policies (deltamp.operators.window) give the
times; None acts at once. At one time sources come first, then gathered edges, then outputs.

A layer is one join and two aggregations, whatever the number of events: an edge meets the versions of its
source that are valid when it is gathered (a message) or later (a swap by the difference); messages are summed
by destination and time, then by window; a running sum over a destination's windows is its aggregate at each.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from deltamp.durable import kept as settle
from deltamp.functions.grid import DIMS, dense
from deltamp.operators.aggregators import S, X
from deltamp.operators.infer import half_up_mean, matrix

Policy = Callable[[DataFrame], DataFrame]  # rows (key, us, seq) to the same with due
ALWAYS = -(2**62)
IDS = 1 << 18  # the most vertex ids of a broadcast


@dataclass
class Layer:
    """gathered: src, dst, us, at. messages: src, dst, at, kind, first. emissions: v, at, n, first, x (null without values).

    last: each vertex' last emission (none without values).
    """

    gathered: DataFrame
    messages: DataFrame
    emissions: DataFrame
    last: DataFrame | None = None


def _gather(edges: DataFrame, policy: Policy | None) -> DataFrame:
    rows = edges.select(F.col("dst").alias("key"), "us", "seq", "src")
    due = policy(rows) if policy else rows.withColumn("due", F.col("us"))
    return due.select("src", F.col("key").alias("dst"), "us", "seq", F.col("due").cast("long").alias("at"))


def _joined(edges: DataFrame, vertices: DataFrame) -> DataFrame:
    """Edges whose two ends are vertices; the ids are broadcast while they are few, so edges aren't shuffled for it."""
    ids = vertices.select("v")
    ids = F.broadcast(ids) if ids.count() <= IDS else ids
    for end in ("src", "dst"):
        edges = edges.join(ids.withColumnRenamed("v", end), end, "left_semi")
    return edges


def _emit(requests: DataFrame, policy: Policy | None) -> DataFrame:
    """requests (key, us, ...) with due; what holds from the start isn't delayed."""
    begun, later = requests.where(F.col("us") == ALWAYS), requests.where(F.col("us") > ALWAYS).withColumn("seq", F.col("us"))
    due = policy(later) if policy else later.withColumn("due", F.col("us"))
    return begun.withColumn("due", F.col("us")).unionByName(due.drop("seq"))


def _outputs(rows: DataFrame, layer: int) -> DataFrame:
    """(v, at, n, first, x*, s*, m) to (v, at, n, first, x)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            count = b.column(4 + 2 * DIMS).fill_null(0).to_numpy(zero_copy_only=False)
            h = dense(matrix(b, 4), half_up_mean(matrix(b, 4 + DIMS), count), layer)
            x = pa.FixedSizeListArray.from_arrays(pa.array(h.ravel()), DIMS).cast(pa.list_(pa.int64()))
            yield pa.RecordBatch.from_arrays([*(b.column(k) for k in range(4)), x], names=["v", "at", "n", "first", "x"])

    return rows.mapInArrow(run, "v long, at long, n long, first long, x array<bigint>")


def _last(messages: DataFrame, versions: DataFrame, emit: Policy | None, layer: int) -> DataFrame:
    """(v, at, n, first, x): the last emission of each vertex.

    The windows run over all requests without vectors. Once the last has closed, every message of a destination is
    part of its output, so messages are summed by destination and the vectors of the emissions before aren't made.
    """
    asked = messages.groupBy(F.col("dst").alias("key"), F.col("at").alias("us")).agg(F.count("*").alias("n"), F.min("first").alias("first"))
    own = versions.select(F.col("v").alias("key"), F.col("at").alias("us"), F.lit(1).cast("long").alias("n"), "first")
    closed = _emit(asked.unionByName(own), emit).groupBy("key", "due").agg(F.sum("n").alias("n"), F.min("first").alias("first"))
    ends = closed.groupBy(F.col("key").alias("v")).agg(F.max(F.struct("due", "n", "first")).alias("e"))
    sums = messages.groupBy(F.col("dst").alias("v")).agg(*_changes(), F.sum((F.col("kind") == "absorb").cast("long")).alias("m"))
    held = versions.groupBy("v").agg(F.max_by("x", "at").alias("x")).join(ends, "v").join(sums, "v", "left")
    return _outputs(held.selectExpr("v", "e.due AS at", "e.n AS n", "e.first AS first", *[f"x[{i}] AS {x}" for i, x in enumerate(X)], *S, "m"), layer)


def _changes() -> list[Column]:
    return [F.expr(f"sum(x[{i}] - coalesce(old[{i}], 0L)) AS {c}") for i, c in enumerate(S)]


def run(vertices: DataFrame, edges: DataFrame, gather: Policy | None, emit: Policy | None, layers: int = 2, values: bool = True) -> list[Layer]:
    """The trace of every layer. vertices (v, x*); edges (seq, us, src, dst).

    Without values no vector is moved and every emission counts as a change; with them an output that
    equals the last one isn't sent on, and edges count where both ends are vertices. The gather windows are the same in every layer and stored once; the last
    layer's emissions aren't stored, as no layer reads them.
    """
    vector = F.array(*X) if values else F.lit(None).cast("array<bigint>")
    none = F.lit(None).cast("array<bigint>")
    versions = vertices.select("v", F.lit(ALWAYS).cast("long").alias("at"), F.lit(None).cast("long").alias("first"), vector.alias("x"))
    out = []
    gathered = _gather(edges, gather)
    gathered = _joined(gathered, vertices) if values else gathered
    gathered = settle(gathered) if gather and layers > 1 else gathered
    for layer in range(layers):
        w = Window.partitionBy("v").orderBy("at")
        spans = versions.select("v", "at", "first", "x", F.lag("x").over(w).alias("old"), F.lag("at").over(w).alias("since"), F.coalesce(F.lead("at").over(w), F.lit(2**62)).alias("until"))
        e, s = gathered.withColumnRenamed("at", "got"), spans.withColumnRenamed("v", "src")
        met = e.join(s.hint("merge"), "src").where("until > got")
        absorbs = (F.col("at") <= F.col("got")) | F.col("since").isNull()
        messages = met.select("src", "dst", F.greatest("at", "got").alias("at"), F.when(absorbs, "absorb").otherwise("swap").alias("kind"), F.when(F.col("at") <= F.col("got"), F.col("us")).otherwise(F.greatest("us", "first")).alias("first"), "x", F.when(~absorbs, F.col("old")).alias("old"))
        new = F.col("kind") == "absorb"
        sums = _changes() if values else []
        summed = messages.groupBy(F.col("dst").alias("key"), F.col("at").alias("us")).agg(*sums, F.sum(new.cast("long")).alias("m"), F.count("*").alias("n"), F.min("first").alias("first"))
        own = versions.select(F.col("v").alias("key"), F.col("at").alias("us"), *[F.expr(f"0L AS {c}") for c in (S if values else [])], F.lit(0).cast("long").alias("m"), F.lit(1).cast("long").alias("n"), "first", F.struct("x").alias("own"))
        requests = summed.withColumn("own", F.lit(None).cast("struct<x:array<bigint>>")).unionByName(own)
        due = _emit(requests, emit)
        total = [F.expr(f"sum({c}) AS {c}") for c in (S if values else [])]
        closed = due.groupBy("key", "due").agg(*total, F.sum("m").alias("m"), F.sum("n").alias("n"), F.min("first").alias("first"), F.max_by("own", F.when(F.col("own").isNotNull(), F.col("us"))).alias("own"))
        w = Window.partitionBy("key").orderBy("due").rowsBetween(Window.unboundedPreceding, 0)
        held = closed.select(F.col("key").alias("v"), F.col("due").alias("at"), "n", "first", F.last("own", ignorenulls=True).over(w)["x"].alias("x"), F.last("own", ignorenulls=True).over(w).isNotNull().alias("there"), *[F.expr(f"sum({c}) OVER (PARTITION BY key ORDER BY due ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS {c}") for c in ([*S, "m"] if values else ["m"])]).where("there")
        if values:
            wide = held.selectExpr("v", "at", "n", "first", *[f"x[{i}] AS {x}" for i, x in enumerate(X)], *S, "m")
            told = _outputs(wide, layer)
            before = F.lag("x").over(Window.partitionBy("v").orderBy("at"))
            told = told.withColumn("same", before.eqNullSafe(F.col("x"))).where("NOT same").drop("same")
        else:
            told = held.select("v", "at", "n", "first", none.alias("x"))
        emissions = settle(told) if layer < layers - 1 else told
        last = _last(messages, versions, emit, layer) if values and layer == layers - 1 else None
        out.append(Layer(gathered, messages.select("src", "dst", "at", "kind", "first"), emissions, last))
        versions = emissions.select("v", "at", "first", "x")
    return out


def final(trace: list[Layer]) -> DataFrame:
    """(v, x*) after the last window has closed."""
    return trace[-1].last.selectExpr("v", *[f"x[{i}] AS {x}" for i, x in enumerate(X)])


def counts(trace: list[Layer]) -> DataFrame:
    """Per layer: messages absorbed, swaps, the updates they come to, and outputs sent (initial ones left out)."""
    rows = None
    for k, layer in enumerate(trace, 1):
        sent = layer.messages.agg(F.count_if(F.col("kind") == "absorb").alias("absorbs"), F.count_if(F.col("kind") == "swap").alias("swaps"))
        left = layer.emissions.where(F.col("at") > ALWAYS).agg(F.count("*").alias("outputs"))
        one = sent.crossJoin(left).select(F.lit(k).alias("layer"), "*")  # one row each
        rows = one if rows is None else rows.unionByName(one)
    return rows


def partials(trace: list[Layer], edges_part, parts: int) -> DataFrame:
    """(layer, messages, bytes): partial sums that cross from an edge's part to its destination's master part.

    edges_part gives (src, dst) rows their part as a column; a master lies at destination mod parts. All messages
    of one part for one destination and time travel as one partial sum with its count.
    """
    rows = None
    for k, layer in enumerate(trace, 1):
        home = F.pmod(F.col("dst"), F.lit(parts))
        sent = layer.messages.select(edges_part.alias("part"), "dst", "at").where(F.col("part") != home).distinct()
        one = sent.agg(F.count("*").alias("messages")).select(F.lit(k).alias("layer"), "messages", (F.col("messages") * (8 * DIMS + 24)).alias("bytes"))
        rows = one if rows is None else rows.unionByName(one)
    return rows
