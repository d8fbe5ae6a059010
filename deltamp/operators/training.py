"""Stale-free training on a frozen version: votes, backward passes as transposed joins, averaging, rebuild.

The exact variant is linear with squared loss on integers, so every gradient is an integer in any
order; production widths run the same plans on doubles.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from deltamp.functions.grid import DIMS, weights
from deltamp.operators.aggregators import X
from deltamp.operators.infer import matrix

G = [f"g{i}" for i in range(DIMS)]


def should_start(votes: int, operators: int) -> bool:
    """Strictly more than half of the output operators have asked."""
    return 2 * votes > operators


def plan_batches(n_labels: int, per_part: int, epochs: int) -> list[tuple[int, int, int]]:
    """(epoch, first row, end row)."""
    return [(e, a, min(n_labels, a + per_part)) for e in range(epochs) for a in range(0, n_labels, per_part)]


def _products(rows: DataFrame, own: np.ndarray, other: np.ndarray | None, names: list[str]) -> DataFrame:
    """(v, own columns, other columns) to (v, names): own times its matrix plus other times its own, exact on integers."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            h = matrix(b, 1).astype(np.float64) @ own
            if other is not None:
                h += matrix(b, 1 + DIMS).astype(np.float64) @ other
            h = h.astype(np.int64)
            yield pa.RecordBatch.from_arrays([b.column(0), *(pa.array(h[:, k]) for k in range(DIMS))], names=["v", *names])

    return rows.mapInArrow(run, f"v long, {', '.join(f'{n} long' for n in names)}")


def forward_linear(vertices: DataFrame, edges: DataFrame, layer: int) -> DataFrame:
    """(v, x*) of a linear sum layer: own weights on x plus neighbour weights on the sum of messages."""
    ws, wn, _ = (np.array(w, np.float64) for w in weights(layer))
    sums = edges.join(vertices, edges["src"] == vertices["v"]).groupBy("dst").agg(*[F.sum(x).alias(f"a{i}") for i, x in enumerate(X)])
    j = vertices.select("v", *X).join(sums, F.col("v") == F.col("dst"), "left")
    return _products(j.select("v", *X, *[f"a{i}" for i in range(DIMS)]), ws.T, wn.T, X)


def output_gradient(final: DataFrame, labels: DataFrame) -> DataFrame:
    """Squared loss of the first output against the label: (v, g*)."""
    j = final.join(labels.select("v", F.col("label").cast("long").alias("y")), "v")
    return j.select("v", (2 * (F.col("x0") - F.col("y"))).alias("g0"), *[F.lit(0).cast("long").alias(g) for g in G[1:]])


def accumulate(gradients: DataFrame) -> DataFrame:
    """One gradient a vertex: the shuffle is the barrier before a layer's backward pass."""
    return gradients.groupBy("v").agg(*[F.sum(g).cast("long").alias(g) for g in G])


def backward_update(gradients: DataFrame, layer: int) -> tuple[DataFrame, DataFrame]:
    """Phase one: gradients by the aggregate and by the own input."""
    ws, wn, _ = (np.array(w, np.float64) for w in weights(layer))
    g = gradients.select("v", *G)
    return _products(g, wn, None, G), _products(g, ws, None, G)


def backward_message(edges: DataFrame, by_aggregate: DataFrame) -> DataFrame:
    """Phase two: the aggregate's gradient back along every in-edge: (v, g*) at sources."""
    j = edges.select("src", "dst").join(by_aggregate, F.col("dst") == F.col("v"))
    return j.groupBy("src").agg(*[F.sum(g).cast("long").alias(g) for g in G]).withColumnRenamed("src", "v")


def backward_layer(gradients: DataFrame, edges: DataFrame, layer: int) -> DataFrame:
    by_aggregate, own = backward_update(accumulate(gradients), layer)
    return accumulate(own.unionByName(backward_message(edges, by_aggregate)))


def weight_gradient(inputs: DataFrame, gradients: DataFrame) -> DataFrame:
    """(i, j, g): the sum over vertices of output gradient i times input j; a batch sends one partial matrix."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((DIMS, DIMS))
        for b in batches:
            total += matrix(b, DIMS).astype(np.float64).T @ matrix(b, 0).astype(np.float64)
        i, j = np.divmod(np.arange(DIMS * DIMS), DIMS)
        yield pa.RecordBatch.from_arrays([pa.array(i.astype(np.int32)), pa.array(j.astype(np.int32)), pa.array(total.ravel().astype(np.int64))], names=["i", "j", "g"])

    rows = inputs.join(gradients, "v").select(*X, *G).mapInArrow(run, "i int, j int, g long")
    return rows.groupBy("i", "j").agg(F.sum("g").alias("g"))


def average(parameters: DataFrame) -> DataFrame:
    """(part, i, j, value) to the unweighted mean over parts."""
    return parameters.groupBy("i", "j").agg(F.avg("value").alias("value"))


@dataclass
class Optimiser:
    """SGD, Adam or Adamax over flat parameter vectors."""

    kind: str = "sgd"
    rate: float = 2.0**-10
    b1: float = 0.9
    b2: float = 0.999
    eps: float = 1e-8
    step_n: int = 0
    m: np.ndarray = field(default_factory=lambda: np.zeros(0))
    v: np.ndarray = field(default_factory=lambda: np.zeros(0))

    def step(self, p: np.ndarray, g: np.ndarray) -> np.ndarray:
        if self.kind == "sgd":
            return p - self.rate * g
        self.step_n += 1
        if not len(self.m):
            self.m, self.v = np.zeros_like(p), np.zeros_like(p)
        self.m = self.b1 * self.m + (1 - self.b1) * g
        first = self.m / (1 - self.b1**self.step_n)
        if self.kind == "adam":
            self.v = self.b2 * self.v + (1 - self.b2) * g * g
            return p - self.rate * first / (np.sqrt(self.v / (1 - self.b2**self.step_n)) + self.eps)
        self.v = np.maximum(self.b2 * self.v, np.abs(g))
        return p - self.rate * first / (self.v + self.eps)


class Coordinator:
    """The life cycle: running, pausing, flushing, training, rebuilding, running."""

    ORDER = ("running", "pausing", "flushing", "training", "rebuilding")

    def __init__(self, operators: int):
        self.operators, self.votes, self.state = operators, set(), "running"

    def vote(self, operator: int) -> bool:
        self.votes.add(operator)
        if self.state == "running" and should_start(len(self.votes), self.operators):
            self.state = "pausing"
        return self.state == "pausing"

    def advance(self) -> str:
        if self.state != "running":
            self.state = self.ORDER[(self.ORDER.index(self.state) + 1) % len(self.ORDER)]
            if self.state == "running":
                self.votes.clear()
        return self.state
