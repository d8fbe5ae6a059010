"""Streaming queries; each has a batch twin in SQL where the result is deterministic."""

from __future__ import annotations

from pyspark.sql import functions as F

from deltamp.operators import infer
from deltamp.queries.layers import full_sql
from deltamp.registry import graph, pair, table
from deltamp.streaming import online as st

_DAY = 86_400_000_000


def _stream(spark, sf, **options):
    return st.replay(spark, table(spark, sf, "events"), **options).withWatermark("ts", "1 hour")


def _windowed(spark, sf, window, **options):
    out = _stream(spark, sf, **options).groupBy(window.alias("w"), "user_id").agg(F.count("*").alias("n"))
    # Filtered after the stream: before it, the filter would be pushed below the watermark and take the sentinel.
    return st.drain(out.select(F.unix_micros("w.end").alias("due"), "user_id", "n")).where(f"user_id <> {st.SENTINEL}")


@pair("st_tumbling", f"SELECT CAST((floor(epoch_us(ts) / {_DAY}) + 1) * {_DAY} AS BIGINT) AS due, user_id, count(*) AS n FROM events GROUP BY 1, 2")
def st_tumbling(spark, sf):
    return _windowed(spark, sf, F.window("ts", "1 day"))


@pair("st_sliding", f"SELECT CAST((CAST(floor(epoch_us(ts) / {_DAY // 2}) AS BIGINT) - k) * {_DAY // 2} + {_DAY} AS BIGINT) AS due, user_id, count(*) AS n FROM events, (SELECT 0 AS k UNION ALL SELECT 1) GROUP BY 1, 2")
def st_sliding(spark, sf):
    return _windowed(spark, sf, F.window("ts", "1 day", "12 hours"))


def _merged_sql(gap: str) -> str:
    """Sessions as runs of overlapping spans [us, us + gap)."""
    spans = f"SELECT user_id, epoch_us(ts) AS us, epoch_us(ts) + {gap} AS z FROM events"
    fresh = f"SELECT *, CASE WHEN us >= max(z) OVER (PARTITION BY user_id ORDER BY us ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) THEN 1 ELSE 0 END AS fresh FROM ({spans})"
    return f"SELECT CAST(max(z) AS BIGINT) AS due, user_id, count(*) AS n FROM (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY us) AS part FROM ({fresh})) GROUP BY user_id, part"


_SIX = 6 * 3_600_000_000


@pair("st_session", _merged_sql(str(_SIX)))
def st_session(spark, sf):
    return _windowed(spark, sf, F.session_window("ts", "6 hours"))


@pair("st_dynamic_session", _merged_sql(f"CASE WHEN event_type = 'error' THEN {_SIX // 6} ELSE {_SIX} END"))
def st_dynamic_session(spark, sf):
    return _windowed(spark, sf, F.session_window("ts", F.when(F.col("event_type") == "error", "1 hour").otherwise("6 hours")))


@pair("st_flush_complete", "SELECT count(*) AS windows, CAST(sum(n) AS BIGINT) AS rows_ FROM (SELECT count(*) AS n FROM events GROUP BY floor(epoch_us(ts) / 86400000000), user_id)")
def st_flush_complete(spark, sf):
    return st_tumbling(spark, sf).agg(F.count("*").alias("windows"), F.sum("n").alias("rows_"))


@pair("st_late_drop")
def st_late_drop(spark, sf):
    """Without the sentinel the windows beyond the watermark stay open."""
    return _windowed(spark, sf, F.window("ts", "1 day"), sentinel=False).agg(F.count("*").alias("closed"))


@pair("st_dedup", "SELECT count(*) AS n FROM events")
def st_dedup(spark, sf):
    e = table(spark, sf, "events")
    out = st.replay(spark, e.union(e), sentinel=False).withWatermark("ts", "60 days").dropDuplicatesWithinWatermark(["event_id"])
    return st.drain(out.select("event_id")).agg(F.count("*").alias("n"))


@pair("st_aggregator_state", "SELECT user_id, count(*) AS n FROM events GROUP BY user_id")
def st_aggregator_state(spark, sf):
    out = st.drain(st.running_sums(st.replay(spark, table(spark, sf, "events"), sentinel=False)), "update")
    return out.groupBy("user_id").agg(F.max("n").alias("n"))


@pair("ss_join_static", "SELECT event_type, count(*) AS n FROM events JOIN embeddings ON user_id = vec_id GROUP BY event_type")
def ss_join_static(spark, sf):
    e = table(spark, sf, "embeddings").select(F.col("vec_id").alias("user_id"))
    return st.drain(_stream(spark, sf).join(e, "user_id").select("event_type")).groupBy("event_type").agg(F.count("*").alias("n"))


@pair("ss_join_interval", "SELECT count(*) AS n FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR AND a.event_type = 'view' AND b.event_type = 'purchase'")
def ss_join_interval(spark, sf):
    s = _stream(spark, sf)
    a = s.where("event_type = 'view'").select(F.col("user_id").alias("u"), F.col("ts").alias("t"))
    b = s.where("event_type = 'purchase'")
    j = a.join(b, F.expr("u = user_id AND ts > t AND ts <= t + INTERVAL 1 HOUR"))
    return st.drain(j.select("user_id")).agg(F.count("*").alias("n"))


@pair("ss_join_outer", "SELECT CAST(b.user_id IS NOT NULL AS INTEGER) AS met, count(*) AS n FROM (SELECT * FROM events WHERE event_type = 'view') a LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR GROUP BY 1")
def ss_join_outer(spark, sf):
    """Views with the purchases of the hour after; a view that none meets leaves once the watermark has passed its hour."""
    s = _stream(spark, sf)
    a = s.select(F.col("user_id").alias("u"), F.col("ts").alias("t"), F.col("event_type").alias("k"))
    b = s.select("user_id", "ts", F.col("event_type").alias("kind"))
    j = a.join(b, F.expr("u = user_id AND ts > t AND ts <= t + INTERVAL 1 HOUR AND kind = 'purchase'"), "left_outer")
    return st.drain(j.select("k", "user_id")).where("k = 'view'").groupBy(F.col("user_id").isNotNull().cast("int").alias("met")).agg(F.count("*").alias("n"))


@pair("st_timer_evict", _merged_sql(str(_SIX)))
def st_timer_evict(spark, sf):
    """Pending events evicted by a key's event-time timer, which every arrival sets back."""
    return st.drain(st.evict_idle(_stream(spark, sf), _SIX)).where(f"user_id <> {st.SENTINEL}")


@pair("st_chained_layers", f"SELECT CAST((floor(due / {_DAY}) + 1) * {_DAY} AS BIGINT) AS day_end, count(*) AS windows, CAST(sum(n) AS BIGINT) AS n FROM (SELECT CAST((floor(epoch_us(ts) / {_SIX}) + 1) * {_SIX} AS BIGINT) - 1 AS due, user_id, count(*) AS n FROM events GROUP BY 1, 2) GROUP BY 1")
def st_chained_layers(spark, sf):
    """Two stateful operators in a row: the windows that the first closes are the second's input."""
    first = _stream(spark, sf).groupBy(F.window("ts", "6 hours"), "user_id").agg(F.count("*").alias("n"))
    second = first.groupBy(F.window(F.window_time("window"), "1 day").alias("w")).agg(F.count("*").alias("windows"), F.sum("n").alias("n"))
    return st.drain(second.select(F.unix_micros("w.end").alias("day_end"), "windows", "n")).where("day_end < 7000000000000000")


@pair("st_initial_state", "SELECT user_id, count(*) AS n FROM events GROUP BY user_id")
def st_initial_state(spark, sf):
    """A stream of the later events that goes on from the state of the earlier ones."""
    e = table(spark, sf, "events")
    half = e.agg(F.expr("percentile(event_id, 0.5)")).first()[0]
    early = e.where(F.col("event_id") <= half).groupBy("user_id").agg(F.sum("value").alias("s"), F.count("*").alias("n"))
    out = st.drain(st.sums_from(st.replay(spark, e.where(F.col("event_id") > half), sentinel=False), early), "update")
    return out.select("user_id", "n").union(early.select("user_id", "n")).groupBy("user_id").agg(F.max("n").alias("n"))


@pair("stream_sage_final", full_sql("(SELECT src, dst FROM topic WHERE src < 1000000 UNION ALL SELECT src, dst FROM hop)").replace("topic WHERE src < 1000000", "hop WHERE etype <> 'view'"), ("hop", "emb0"))
def stream_sage_final(spark, sf):
    """Two layers kept up over a stream of the hop graph's edges, a cascade a batch; all but views count twice, and one copy of the views goes again."""
    v = infer.settle(graph(spark, sf, "emb0"))
    hops = graph(spark, sf, "hop").select("seq", "src", "dst", "etype")
    root = st.scratch(spark)
    doubled = hops.withColumn("op", F.lit("add")).unionByName(hops.withColumn("op", F.lit("add"))).unionByName(hops.where("etype = 'view'").withColumn("op", F.lit("del")).withColumn("seq", F.col("seq") + 1_000_000_000))
    low, high = hops.agg(F.min("seq"), F.max("seq")).first()
    for part in (doubled.where(F.col("seq") <= (low + high) // 2), doubled.where(F.col("seq").between((low + high) // 2 + 1, high)), doubled.where(F.col("seq") > high)):
        part.coalesce(1).write.mode("append").parquet(f"{root}/in")
    stream = spark.readStream.schema(doubled.schema).option("maxFilesPerTrigger", 1).parquet(f"{root}/in")
    return st.online(spark, v, stream, lambda b: b.select("src", "dst", "op"), root=root).outputs()
