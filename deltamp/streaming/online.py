"""Structured Streaming forms: event-time windows, stateful aggregators, and inference by deltas per batch.

Streams end by availableNow. Append mode holds what lies beyond the watermark, so flush() feeds one
far-future sentinel row, which the caller's filter drops.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from deltamp.operators.store import Store
from deltamp.plans.shared import names, scratch

EVENT = "event_id long, ts timestamp, user_id long, event_type string, value double"
SENTINEL = -1


def replay(spark: SparkSession, events: DataFrame, files: int = 4, sentinel: bool = True) -> DataFrame:
    """The events as a file stream in event order, one file a batch, with the sentinel last."""
    path = scratch(spark)
    rows = events.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value")
    low, high = rows.agg(F.min("event_id"), F.max("event_id")).first()
    step = max(1, -(-((high or 0) - (low or 0) + 1) // files))
    for k in range(files):  # one write each: the file source takes files by their time
        rows.where((F.col("event_id") >= (low or 0) + k * step) & (F.col("event_id") < (low or 0) + (k + 1) * step)).coalesce(1).write.mode("append").parquet(path)
    if sentinel:
        spark.sql(f"SELECT cast({SENTINEL} AS long) AS event_id, timestamp '2200-01-01' AS ts, cast({SENTINEL} AS long) AS user_id, 'end' AS event_type, 0.0D AS value").coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(EVENT).option("maxFilesPerTrigger", 1).parquet(path)


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a streaming frame to its end into Parquet, and read that; in other modes each batch is a folder that a replay overwrites."""
    spark = stream.sparkSession
    root = scratch(spark)
    writer = stream.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{root}/check")
    if mode == "append":
        writer.format("parquet").option("path", f"{root}/out").start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{root}/out")
    writer.foreachBatch(lambda rows, k: rows.write.mode("overwrite").parquet(f"{root}/out/batch={k}")).start().awaitTermination()
    return spark.read.schema(stream.schema).option("basePath", f"{root}/out").parquet(*[f"{root}/out/{x}" for x in names(spark, f"{root}/out")])


def running_sums(stream: DataFrame) -> DataFrame:
    """A per-user aggregator in keyed state: sum and count, emitted with every batch that touches it."""

    def update(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        s, n = state.get if state.exists else (0.0, 0)
        for b in batches:
            s, n = s + float(b["value"].sum()), n + len(b)
        state.update((s, n))
        yield pd.DataFrame({"user_id": [key[0]], "s": [s], "n": [n]})

    return stream.groupBy("user_id").applyInPandasWithState(update, "user_id long, s double, n long", "s double, n long", "update", "NoTimeout")


def evict_idle(stream: DataFrame, gap_us: int) -> DataFrame:
    """(user_id, due, n): each user's pending events leave together, a gap after the last of them.

    State holds the pending count and due time. Events that come later close what was due before them; what no
    event closes, the event-time timer evicts.
    """

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        due, n = state.get if state.exists else (None, 0)
        if state.hasTimedOut:
            state.remove()
            yield pd.DataFrame({"user_id": [key[0]], "due": [due], "n": [n]})
            return
        times = sorted(t for b in batches for t in b["us"].tolist())
        out = []
        for t in times:
            if due is not None and t >= due:
                out.append((key[0], due, n))
                n = 0
            due, n = t + gap_us, n + 1
        now = state.getCurrentWatermarkMs()
        if due // 1000 <= now:
            out.append((key[0], due, n))
            state.remove()
        else:
            state.update((due, n))
            state.setTimeoutTimestamp(-(-due // 1000))
        yield pd.DataFrame(out, columns=["user_id", "due", "n"])

    rows = stream.select("ts", "user_id", F.unix_micros("ts").alias("us"))
    return rows.groupBy("user_id").applyInPandasWithState(update, "user_id long, due long, n long", "due long, n long", "append", GroupStateTimeout.EventTimeTimeout)


def sums_from(stream: DataFrame, initial: DataFrame) -> DataFrame:
    """running_sums() that go on from an earlier state (user_id, s, n), joined in when a user first appears."""

    def update(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        s, n = state.get if state.exists else (0.0, 0)
        for b in batches:
            if not state.exists and n == 0 and len(b) and b["n0"].notna().any():
                s, n = float(b["s0"].iloc[0]), int(b["n0"].iloc[0])
            s, n = s + float(b["value"].sum()), n + len(b)
        state.update((s, n))
        yield pd.DataFrame({"user_id": [key[0]], "s": [s], "n": [n]})

    rows = stream.join(initial.select("user_id", F.col("s").alias("s0"), F.col("n").alias("n0")), "user_id", "left")
    return rows.groupBy("user_id").applyInPandasWithState(update, "user_id long, s double, n long", "s double, n long", "update", "NoTimeout")


def online(spark: SparkSession, vertices: DataFrame, stream: DataFrame, to_edges: Callable[[DataFrame], DataFrame], layers: int = 2, root: str | None = None) -> Store:
    """Inference over a stream: each batch's changes are one delta cascade over the stored state.

    State and the query's checkpoint lie in one folder. A batch is taken in when its commit mark is written, so a
    query that is started again over the folder neither loses nor repeats one. to_edges gives src and dst, and op
    (add or del) if there are deletions.
    """
    root = root or scratch(spark)
    store = Store(spark, layers, root=f"{root}/state")
    if not store.done:
        store.load(vertices)

    def apply(batch: DataFrame, batch_id: int) -> None:
        edges = to_edges(batch)
        gone = edges.where("op = 'del'") if "op" in edges.columns else None
        store.apply(batch_id + 1, edges.where("op = 'add'") if "op" in edges.columns else edges, gone)

    query = stream.writeStream.foreachBatch(apply).trigger(availableNow=True).option("checkpointLocation", f"{root}/check").start()
    query.awaitTermination()
    return store
