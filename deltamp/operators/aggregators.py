"""Invertible aggregators in column form: operations become signed delta rows that one sum merges."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from deltamp.functions.grid import DIMS

X = [f"x{i}" for i in range(DIMS)]
S = [f"s{i}" for i in range(DIMS)]


# SQL text and not Column calls: at 64 components the calls themselves would take seconds.


def absorb(messages: DataFrame) -> DataFrame:
    """Delta rows (dst, s*, n) that add messages (dst, x*)."""
    return messages.selectExpr("dst", *[f"{x} AS {s}" for x, s in zip(X, S)], "1L AS n")


def retract(messages: DataFrame) -> DataFrame:
    return messages.selectExpr("dst", *[f"-{x} AS {s}" for x, s in zip(X, S)], "-1L AS n")


def swap(new: DataFrame, old: DataFrame) -> DataFrame:
    """absorb(new) and retract(old); the counts cancel."""
    return absorb(new).unionByName(retract(old))


def merge(deltas: DataFrame, state: DataFrame | None = None) -> DataFrame:
    """State (dst, s*, n) after all delta rows; partial sums combine before the shuffle."""
    rows = deltas if state is None else state.unionByName(deltas)
    return rows.groupBy("dst").agg(*[F.expr(f"sum({s}) AS {s}") for s in (*S, "n")])


def read_mean(state: DataFrame) -> DataFrame:
    means = [f"CASE WHEN n > 0 THEN CAST(floor(CAST({s} AS DOUBLE) / n + 0.5D) AS BIGINT) ELSE 0L END AS m{i}" for i, s in enumerate(S)]
    return state.selectExpr("dst", *means, "n")


def extremum(values: DataFrame, kind: str) -> DataFrame:
    """(dst, value, mult) signed multiplicities to the least or greatest value still held."""
    held = values.groupBy("dst", "value").agg(F.sum("mult").alias("mult")).where("mult > 0")
    return held.groupBy("dst").agg((F.min if kind == "min" else F.max)("value").alias("value"), F.sum("mult").alias("n"))


def concat(messages: DataFrame) -> DataFrame:
    """(dst, seq, value) to the values in seq order, as text."""
    packed = messages.groupBy("dst").agg(F.array_sort(F.collect_list(F.struct("seq", "value"))).alias("a"))
    return packed.select("dst", F.array_join(F.transform("a", lambda p: p["value"].cast("string")), ",").alias("messages"))


def recurrent_linear(messages: DataFrame) -> DataFrame:
    """An ordered fold h := (h + 3 m) mod 1000003: the linear cell, exact on integers."""
    packed = messages.groupBy("dst").agg(F.array_sort(F.collect_list(F.struct("seq", "value"))).alias("a"))
    return packed.select("dst", F.aggregate("a", F.lit(0).cast("long"), lambda h, p: F.pmod(2 * h + 3 * p["value"], F.lit(1_000_003))).alias("h"))


def distinct_sketch(messages: DataFrame) -> DataFrame:
    """Add-only sketch: a retract can't be undone in it."""
    return messages.groupBy("dst").agg(F.approx_count_distinct("src", 0.02).alias("n_distinct"))


def last_per_key(rows: DataFrame, key: str, order: str) -> DataFrame:
    w = Window.partitionBy(key).orderBy(F.col(order).desc())
    return rows.withColumn("_r", F.row_number().over(w)).where("_r = 1").drop("_r")
