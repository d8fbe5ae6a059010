"""Incremental inference over stored state, at the cost of what a batch touches.

State lies in Parquet tables cut by the hash of a vertex into buckets. Nothing is rewritten: a batch appends
its edges (sign +1 or -1, filed by source), the sums it adds to aggregates, and the outputs it changes, each
in a folder of its own attempt. Sums of all attempts are an aggregate, the latest output of a vertex is its
output, and a deleted edge's rows cancel, as every message is linear in the edge's sign. Reads name only the
buckets that the batch touches, which the folder names of what was just written tell. An attempt counts once
its commit mark exists, so a replayed or broken batch leaves no trace. compact() folds all attempts into one.

One layer, one batch: an input that changes from old to new sends sign * (new - old) along each of its stored
edges (one more or less message where it appears or goes), the batch's own edges send sign * new, and only the
vertices that a message or their own input reached are evaluated again.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamp.operators import packed
from deltamp.operators.aggregators import S, X
from deltamp.operators.packed import INPUT, OUTPUT, SUM, VECTOR
from deltamp.plans.shared import names, remove, scratch, touch

SCHEMAS = {
    "edges": "src long, dst long, sign long, seq long",
    "sums": f"v long, s {VECTOR}, n long, seq long",
    "values": f"v long, old {VECTOR}, new {VECTOR}, seq long",
}
_CHANGE = "CASE WHEN old IS NULL THEN new WHEN new IS NULL THEN transform(old, o -> -o) ELSE zip_with(new, old, (p, o) -> p - o) END"


def _kind(name: str) -> str:
    return "edges" if name == "edges" else name.rstrip("0123456789")


class Store:
    """The state of a model of so many layers: edges, sums1.. (aggregates), values0.. (inputs and outputs).

    A Store over a folder that has commits goes on from them.
    """

    def __init__(self, spark: SparkSession, layers: int = 2, buckets: int = 16, root: str | None = None):
        self.spark, self.layers, self.buckets = spark, layers, buckets
        self.root = root or scratch(spark)
        marks = [m.split("~") for m in names(spark, f"{self.root}/commits") if "~" in m]
        self.done = {int(batch): attempt for batch, attempt in marks}
        bases = [m for m in names(spark, f"{self.root}/bases") if "~" in m]
        self.base = max(bases, key=lambda m: int(m.split("~")[0])) if bases else None
        self.last: str | None = None
        self._written: dict[tuple[str, str], list[int]] = {}

    # ---- tables -------------------------------------------------------------------------------

    def _bucket(self, key: str) -> Column:
        return F.pmod(F.xxhash64(key), F.lit(self.buckets)).cast("int")

    def _attempts(self) -> list[str]:
        """Committed folders: the base and the batches after it."""
        upto = int(self.base.split("~")[0]) if self.base else -1
        return ([self.base.split("~")[1]] if self.base else []) + [a for b, a in sorted(self.done.items()) if b > upto]

    def _write(self, rows: DataFrame, name: str, key: str, attempt: str, placed: bool = False) -> list[int]:
        """Append rows, placed by bucket already or not, and tell which buckets they are in."""
        path = f"{self.root}/{name}/a={attempt}"
        rows = rows.withColumn("b", self._bucket(key))
        if name == "edges":  # in the order in which inputs are carried along them
            rows = rows.repartition(self.buckets, "b").sortWithinPartitions("b", "src", self._bucket("dst"))
        elif not placed:
            rows = rows.repartition(self.buckets, "b")
        rows.write.partitionBy("b").parquet(path)
        return self._there(name, attempt)

    def _there(self, name: str, attempt: str) -> list[int]:
        """The buckets that an attempt wrote to."""
        if (name, attempt) not in self._written:
            self._written[name, attempt] = [int(x[2:]) for x in names(self.spark, f"{self.root}/{name}/a={attempt}") if x.startswith("b=")]
        return self._written[name, attempt]

    def _read(self, name: str, attempts: list[str], buckets: list[int] | None = None) -> DataFrame:
        """The rows of some attempts; with buckets, only their folders are listed and read."""
        schema, wanted = SCHEMAS[_kind(name)], None if buckets is None else set(buckets)
        there = {a: [b for b in self._there(name, a) if wanted is None or b in wanted] for a in attempts}
        if not any(there.values()):
            return self.spark.createDataFrame([], schema)
        reader, top = self.spark.read, f"{self.root}/{name}"
        if wanted is None:
            rows = reader.schema(f"{schema}, a string, b int").option("basePath", top).parquet(*[f"{top}/a={a}" for a in there if there[a]])
            return rows.drop("a", "b")
        return reader.schema(schema).parquet(*[f"{top}/a={a}/b={b}" for a in there for b in there[a]])

    def _latest(self, level: int, buckets: list[int] | None = None, attempts: list[str] | None = None) -> DataFrame:
        """(v, x): the values of a level that are there; a deleted one has a null."""
        rows = self._read(f"values{level}", attempts or self._attempts(), buckets)
        return rows.groupBy("v").agg(F.max_by(F.struct(F.col("new").alias("x")), "seq").alias("l")).select("v", "l.x").where("x is not null")

    def _sums(self, level: int) -> DataFrame:
        return packed.add_up(self._read(f"sums{level}", self._attempts()).selectExpr("v", "s", "n", "1L AS sign"))

    # ---- what callers read --------------------------------------------------------------------

    def outputs(self, level: int | None = None) -> DataFrame:
        """(v, x*) of the last layer, or of a level (0 are the inputs)."""
        return self._latest(self.layers if level is None else level).selectExpr("v", *[f"x[{i}] AS {x}" for i, x in enumerate(X)])

    def aggregates(self, level: int = 1) -> DataFrame:
        """(dst, s*, n) of the vertices that hold a message."""
        rows = self._sums(level).where("n > 0")
        return rows.selectExpr("v AS dst", *[f"s[{i}] AS {s}" for i, s in enumerate(S)], "n")

    def changed(self, level: int) -> DataFrame:
        """(v) whose value at a level the last batch changed."""
        return self._read(f"values{level}", [self.last] if self.last else []).select("v")

    def messages(self, level: int) -> int:
        """How many aggregates the last batch sent sums to at a level."""
        return self._read(f"sums{level}", [self.last] if self.last else []).count()

    # ---- a batch ------------------------------------------------------------------------------

    def apply(self, batch: int, added: DataFrame | None = None, deleted: DataFrame | None = None, features: DataFrame | None = None) -> bool:
        """Take one batch in: edges (src, dst) added and deleted, features (v, x or null). False if it was applied before.

        An edge that is added and deleted in one batch cancels. Batches are numbered in the order of their application.
        """
        if batch in self.done:
            return False
        attempt, before = uuid.uuid4().hex, self._attempts()
        both = None
        for frame, sign in ((added, 1), (deleted, -1)):
            if frame is not None:
                rows = frame.select("src", "dst", F.lit(sign).cast("long").alias("sign"))
                both = rows if both is None else both.unionByName(rows)
        edge_buckets: list[int] = []
        if both is not None:
            net = both.groupBy("src", "dst").agg(F.sum("sign").alias("sign")).where("sign <> 0")
            edge_buckets = self._write(net.withColumn("seq", F.lit(batch).cast("long")), "edges", "src", attempt)
        value_buckets: list[int] = []
        if features is not None:
            value_buckets = self._write_inputs(features.select("v", F.col("x").alias("new")), batch, attempt, before)
        for level in range(1, self.layers + 1):
            value_buckets = self._layer(level, batch, attempt, before, edge_buckets, value_buckets)
        touch(self.spark, f"{self.root}/commits/{batch}~{attempt}")
        self.done[batch], self.last = attempt, attempt
        return True

    def _write_inputs(self, new: DataFrame, batch: int, attempt: str, before: list[str]) -> list[int]:
        """Write those of (v, new) that differ from what is stored, with the old value beside."""
        old = self._latest(0, None, before).withColumnRenamed("x", "old") if before else self.spark.createDataFrame([], f"v long, old {VECTOR}")
        rows = new.join(old, "v", "left").where(~F.col("new").eqNullSafe(F.col("old")))
        return self._write(rows.select("v", "old", "new", F.lit(batch).cast("long").alias("seq")), "values0", "v", attempt)

    def _layer(self, level: int, batch: int, attempt: str, before: list[str], edge_buckets: list[int], value_buckets: list[int]) -> list[int]:
        """One layer; returns the buckets of the outputs that changed."""
        own, now, seq = [attempt], [*before, attempt], F.lit(batch).cast("long").alias("seq")
        deltas, place = None, self._bucket("dst")
        if value_buckets and before:  # stored edges of the inputs that changed
            moved = self._read(f"values{level - 1}", own, value_buckets).selectExpr("v AS src", f"{_CHANGE} AS s", "CAST(new IS NOT NULL AS BIGINT) - CAST(old IS NOT NULL AS BIGINT) AS n")
            deltas = packed.carried(moved, self._read("edges", before, value_buckets), place)
        if edge_buckets:  # the batch's own edges, over inputs as they are now
            fresh = self._read("edges", own, edge_buckets)
            inputs = self._latest(level - 1, edge_buckets, now).selectExpr("v AS src", "x AS s", "1L AS n")
            rows = packed.carried(inputs, fresh, place)
            deltas = rows if deltas is None else deltas.unionByName(rows)
        sum_buckets: list[int] = []
        if deltas is not None:
            sums = packed.received(deltas, self.buckets)
            sum_buckets = self._write(sums.select("v", "s", "n", seq), f"sums{level}", "v", attempt, placed=True)
        reached = sorted({*sum_buckets, *value_buckets})
        if not reached:
            return []
        keys = self._read(f"sums{level}", own, sum_buckets).select("v").union(self._read(f"values{level - 1}", own, value_buckets).select("v"))
        none = "CAST(NULL AS BIGINT) AS n"
        rows = self._read(f"values{level - 1}", now, reached).selectExpr("v", f"{INPUT} AS kind", "seq", "new AS x", none)
        rows = rows.union(self._read(f"sums{level}", now, reached).selectExpr("v", f"{SUM}", "seq", "s", "n"))
        rows = rows.union(self._read(f"values{level}", before, reached).selectExpr("v", f"{OUTPUT}", "seq", "new", none))
        rows = rows.join(keys, "v", "left_semi").repartition(self.buckets, self._bucket("v")).sortWithinPartitions("v", "kind", "seq")
        return self._write(packed.update(rows, level - 1).select("v", "old", "new", seq), f"values{level}", "v", attempt, placed=True)

    # ---- upkeep -------------------------------------------------------------------------------

    def load(self, vertices: DataFrame, edges: DataFrame | None = None) -> Store:
        """The first batch: all vertices (v, x*) and, if given, edges (src, dst)."""
        self.apply(0, edges, None, packed.pack(vertices))
        return self

    def compact(self) -> None:
        """Fold all attempts into one base: aggregates summed, latest values, edges by net multiplicity."""
        attempts, upto, attempt = self._attempts(), max(self.done), uuid.uuid4().hex
        seq = F.lit(upto).cast("long").alias("seq")
        edges = self._read("edges", attempts).groupBy("src", "dst").agg(F.sum("sign").alias("sign")).where("sign <> 0")
        self._write(edges.select("src", "dst", "sign", seq), "edges", "src", attempt)
        for level in range(self.layers + 1):
            values = self._latest(level)
            self._write(values.select("v", F.lit(None).cast(VECTOR).alias("old"), F.col("x").alias("new"), seq), f"values{level}", "v", attempt)
            if level:
                self._write(self._sums(level).where("n <> 0").select("v", "s", "n", seq), f"sums{level}", "v", attempt)
        touch(self.spark, f"{self.root}/bases/{upto}~{attempt}")
        self.base = f"{upto}~{attempt}"
        for old in attempts:
            for name in names(self.spark, self.root):
                if name not in ("commits", "bases"):
                    remove(self.spark, f"{self.root}/{name}/a={old}")


def cascade(vertices: DataFrame, batches: list[tuple[DataFrame, DataFrame]], layers: int = 2, buckets: int = 4) -> Store:
    """The state after (added, deleted) edge batches over the vertices, from a graph without edges."""
    store = Store(vertices.sparkSession, layers, buckets).load(vertices)
    for k, (added, deleted) in enumerate(batches, 1):
        store.apply(k, added, deleted)
    return store
