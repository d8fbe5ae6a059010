"""Queries and their DuckDB twins.

pair() registers a DataFrame function with a hand-written SQL twin; portable() registers one SQL body
that both engines run over their own views. Graph views are built by each engine on its own: here by
deltamp.sources.graphs, in DuckDB by the CTEs of GRAPH_SQL.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from deltamp.sources.graphs import BUILDERS, GRAPH_SQL

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def table(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/{name}.parquet")


def graph(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return BUILDERS[name](lambda t: table(spark, sf, t))


def with_graphs(graphs: tuple[str, ...], body: str) -> str:
    if not graphs:
        return body
    ctes = ", ".join(f"{g} AS ({GRAPH_SQL[g]})" for g in graphs)
    body = body.strip()
    return f"WITH RECURSIVE {ctes}, {body[5:].removeprefix('RECURSIVE ')}" if body.upper().startswith("WITH ") else f"WITH {ctes} {body}"


def pair(name: str, sql: str | None = None, graphs: tuple[str, ...] = ()):
    """Register a function under a name, with SQL over the graphs' CTEs if there is any."""

    def take(fn):
        QUERIES[name] = fn
        if sql is not None:
            ORACLES[name] = with_graphs(graphs, sql)
        return fn

    return take


def portable(name: str, body: str, graphs: tuple[str, ...] = (), tables: tuple[str, ...] = (), spark_body: str | None = None) -> None:
    def run(spark: SparkSession, sf: str) -> DataFrame:
        for t in tables:
            table(spark, sf, t).createOrReplaceTempView(t)
        for g in graphs:
            graph(spark, sf, g).createOrReplaceTempView(g)
        return spark.sql(spark_body or body)

    QUERIES[name] = run
    ORACLES[name] = with_graphs(graphs, body)
