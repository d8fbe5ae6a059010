"""Baselines, cost and accuracy measures, and the experiment workloads as deterministic tables."""

from __future__ import annotations

from pyspark.sql import functions as F

from deltamp.functions.grid import DIMS
from deltamp.operators import infer
from deltamp.operators.store import cascade
from deltamp.queries.layers import hop_and_features
from deltamp.queries.windows import ADAPTIVE, POLICIES, SESSION, TUMBLING, H, W, due_sql
from deltamp.registry import pair, portable
from deltamp.sources.graphs import DAY

_BYTES = 8 * DIMS + 24
_F6 = lambda x: f"CAST(floor({x} * 1e6 + 0.5) AS BIGINT)"


def degrees(g):
    return f"(SELECT avg(CAST(o AS DOUBLE)) AS dout, avg(CAST(i AS DOUBLE)) AS din FROM (SELECT v, sum(o) AS o, sum(i) AS i FROM (SELECT src AS v, 1 AS o, 0 AS i FROM {g} UNION ALL SELECT dst, 0, 1 FROM {g}) GROUP BY v))"


portable("cost_influence_expected", f"SELECT {_F6('1.0')} AS layers1, {_F6('(1 + dout)')} AS layers2, {_F6('(1 + dout + dout * dout)')} AS layers3 FROM {degrees('topic')}", ("topic",))
portable("cost_influence_exact", "SELECT e.seq, 1 + count(DISTINCT f.dst) AS influenced FROM hop e LEFT JOIN hop f ON f.src = e.dst AND f.dst <> e.dst AND f.seq <= e.seq GROUP BY e.seq", ("hop",))
portable("cost_incremental_vs_recompute", f"SELECT {_F6('dout')} AS incremental, {_F6('(dout + (1 + dout) * din * din)')} AS recompute FROM {degrees('topic')}", ("topic",))
# Baselines: what a static library recomputes per event and per fixed batch.
_I = "SELECT e.seq, e.dst AS v FROM hop e UNION SELECT e.seq, f.dst FROM hop e JOIN hop f ON f.src = e.dst AND f.seq <= e.seq"
portable("base_event_influenced", f"SELECT seq, count(*) AS influenced FROM ({_I}) GROUP BY seq", ("hop",))
_IN = "(SELECT seq, dst, row_number() OVER (PARTITION BY dst ORDER BY seq) AS n FROM hop)"
portable("base_event_recompute", f"SELECT i.seq, CAST(sum(n) AS BIGINT) AS reads FROM (SELECT i.seq, i.v, count(*) AS n FROM ({_I}) i JOIN hop h ON h.dst = i.v AND h.seq <= i.seq GROUP BY i.seq, i.v) i GROUP BY i.seq", ("hop",))
_B = "hop_batches"
_IB = f"SELECT DISTINCT e.b, f.dst AS v FROM {_B} e JOIN {_B} f ON f.src = e.dst AND f.b <= e.b UNION SELECT b, dst FROM {_B}"
portable("base_batch_influenced", f"SELECT b, count(*) AS influenced FROM ({_IB}) GROUP BY b", ("hop_batches",))
portable("base_batch_recompute", f"SELECT i.b, count(*) AS reads FROM ({_IB}) i JOIN {_B} h ON h.dst = i.v AND h.b <= i.b GROUP BY i.b", ("hop_batches",))
portable("base_periodic", f"SELECT d, CAST(sum(n) OVER (ORDER BY d) AS BIGINT) AS edges_read FROM (SELECT CAST(floor(us / {DAY}) AS BIGINT) AS d, count(*) AS n FROM hop GROUP BY CAST(floor(us / {DAY}) AS BIGINT))", ("hop",))
portable("base_ego_volume", f"SELECT a.dst AS v, count(*) * {_BYTES} AS bytes FROM hop a JOIN hop b ON b.dst = a.src GROUP BY a.dst", ("hop",))
# Messages: layer 1 is one an edge; layer 2 is the out-degree at each layer-1 output.
portable("msgs_layer1", "SELECT 'absorb' AS kind, count(*) AS n FROM hop", ("hop",))
OUTDEG = "(SELECT src AS v, us, seq, row_number() OVER (PARTITION BY src ORDER BY seq) AS d FROM hop)"
SWAPS = "SELECT o.key, o.at, max(CASE WHEN h.seq <= o.at THEN 1 ELSE 0 END) AS any_, sum(CASE WHEN h.seq <= o.at THEN 1 ELSE 0 END) AS d FROM {} o LEFT JOIN hop h ON h.src = o.key GROUP BY o.key, o.at"
# As of an output: a running count over both, one pass.
_ASOF = "(SELECT v, seq, kind, sum(1 - kind) OVER (PARTITION BY v ORDER BY seq, kind ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS d FROM (SELECT src AS v, seq, 0 AS kind FROM hop UNION ALL SELECT {}))"
EVENT_OUT = _ASOF.format("dst, seq, 1 FROM hop")
portable("msgs_layer2_streaming", f"SELECT CAST(sum(d) AS BIGINT) AS swaps FROM {EVENT_OUT} WHERE kind = 1", ("hop",))


def window_out(width):
    return _ASOF.format(f"dst, max(seq), 1 FROM hop GROUP BY dst, {due_sql(width)}")


portable("msgs_layer2_windowed", " UNION ALL ".join(f"SELECT {h} AS hours, CAST(sum(d) AS BIGINT) AS swaps FROM {window_out(h * H)} WHERE kind = 1" for h in (1, 12, 24)), ("hop",))


portable("volume_by_partitioner", f"SELECT lpart, count(*) * {_BYTES} AS bytes FROM (SELECT (src * 31 + dst * 17 + seq * 7) % 16 AS lpart, src % 16 AS home FROM hop) WHERE lpart <> home GROUP BY lpart", ("hop",))
portable("imbalance_by_partitioner", f"SELECT by_, {_F6('max(n) / avg(CAST(n AS DOUBLE))')} AS imbalance FROM (SELECT 'hash' AS by_, (src * 31 + dst * 17 + seq * 7) % 16 AS p, count(*) AS n FROM topic GROUP BY (src * 31 + dst * 17 + seq * 7) % 16 UNION ALL SELECT 'destination', dst % 16, count(*) FROM topic GROUP BY dst % 16) GROUP BY by_", ("topic",))
for _p in ("tumbling", "session"):
    portable(f"latency_{_p}", f"SELECT CAST(floor(avg(CAST(due - us AS DOUBLE))) AS BIGINT) AS mean_us, max(due - us) AS max_us, min(due - us) AS min_us FROM {POLICIES[_p][1]}", ("hop",))


@pair("latency_adaptive", f"SELECT CAST(floor(avg(CAST(due - us AS DOUBLE))) AS BIGINT) AS mean_us, max(due - us) AS max_us, min(due - us) AS min_us FROM {ADAPTIVE}", ("hop",))
def latency_adaptive(spark, sf):
    from deltamp.queries.windows import rows_of

    d = POLICIES["adaptive"][0](rows_of(spark, sf)).withColumn("late", F.col("due") - F.col("us"))
    return d.agg(F.floor(F.avg(F.col("late").cast("double"))).cast("long").alias("mean_us"), F.max("late").alias("max_us"), F.min("late").alias("min_us"))


portable("latency_count", f"SELECT CAST(floor(avg(CAST(last - us AS DOUBLE))) AS BIGINT) AS mean_us, max(last - us) AS max_us FROM (SELECT us, max(us) OVER (PARTITION BY b) AS last FROM {_B})", ("hop_batches",))


@pair("accuracy_deviation", "SELECT CAST(0 AS BIGINT) AS deviation")
def accuracy_deviation(spark, sf):
    """The greatest deviation of the incremental state from full inference."""
    from deltamp.queries.layers import batches_of

    v, e = hop_and_features(spark, sf)
    a, b = cascade(v, batches_of(e, 3), 2).outputs().alias("a"), infer.full(v, e, 2).alias("b")
    d = F.greatest(*[F.expr(f"abs(coalesce(a.x{i}, 99999) - coalesce(b.x{i}, 99999))") for i in range(DIMS)])
    return a.join(b, F.expr("a.v = b.v"), "full").agg(F.max(d).cast("long").alias("deviation"))


_P10 = " UNION ALL ".join(f"SELECT {p} AS p" for p in range(1, 11))
portable("scaling_model", f"SELECT p, {_F6('sum(n) / CAST(max(n) AS DOUBLE)')} AS speed_up FROM (SELECT p, dst % p AS part, count(*) AS n FROM hop, ({_P10}) GROUP BY p, dst % p) GROUP BY p", ("hop",))
portable("explosion_ratio", f"SELECT {_F6('b.n / CAST(a.n AS DOUBLE)')} AS ratio FROM (SELECT count(*) AS n FROM hop) a, (SELECT sum(d) AS n FROM {EVENT_OUT} WHERE kind = 1) b", ("hop",))

# Workloads.
_REC = "SELECT 'incremental' AS method, count(*) AS units FROM {g} e JOIN {g} f ON f.src = e.dst AND f.seq <= e.seq UNION ALL SELECT 'recompute', CAST(sum(n) AS BIGINT) FROM (SELECT i.seq, count(*) AS n FROM (SELECT e.seq, e.dst AS v FROM {g} e UNION SELECT e.seq, f.dst FROM {g} e JOIN {g} f ON f.src = e.dst AND f.seq <= e.seq) i JOIN {g} h ON h.dst = i.v AND h.seq <= i.seq GROUP BY i.seq)"
portable("wl_w2_link", _REC.format(g="link"), ("link",))
portable("wl_w2_topic", "SELECT 'incremental' AS method, CAST(sum(d) AS BIGINT) AS units FROM (SELECT v, seq, kind, sum(1 - kind) OVER (PARTITION BY v ORDER BY seq, kind ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS d FROM (SELECT src AS v, seq, 0 AS kind FROM topic UNION ALL SELECT dst, seq, 1 FROM topic)) WHERE kind = 1 UNION ALL SELECT 'in_degree_rescan', CAST(sum(n) AS BIGINT) FROM (SELECT row_number() OVER (PARTITION BY dst ORDER BY seq) AS n FROM topic)", ("topic",))
portable("wl_w3_messages", "SELECT label, count(*) AS forward, count(*) * 2 AS backward FROM topic JOIN emb0 ON src = v GROUP BY label", ("topic", "emb0"))
portable("wl_w4_lambda", "SELECT g AS growth, layer, max(n) AS most FROM (SELECT g, layer, dst % CAST(2 * power(g, layer - 1) AS BIGINT) AS part, count(*) AS n FROM hop, (" + " UNION ALL ".join(f"SELECT {g} AS g" for g in range(1, 9)) + "), (SELECT 1 AS layer UNION ALL SELECT 2) GROUP BY g, layer, dst % CAST(2 * power(g, layer - 1) AS BIGINT)) GROUP BY g, layer", ("hop",))
portable("wl_w6_random", f"SELECT 'hop' AS graph, {_F6('avg(CAST(n AS DOUBLE))')} AS factor FROM (SELECT v, count(DISTINCT p) AS n FROM (SELECT src AS v, (src * 31 + dst * 17 + seq * 7) % 16 AS p FROM hop UNION ALL SELECT dst, (src * 31 + dst * 17 + seq * 7) % 16 FROM hop) GROUP BY v)", ("hop",))
portable("wl_w7_reply", "SELECT count(*) AS edges, count(DISTINCT src) AS sources FROM reply", ("reply",))
portable("wl_w8_fk", "SELECT etype, count(*) AS messages, count(DISTINCT dst) AS outputs FROM fk GROUP BY etype", ("fk",))
portable("wl_w10_surge", f"SELECT hot, count(*) AS updates, count(DISTINCT due) AS outputs FROM (SELECT CASE WHEN dst % 1000 = 7 THEN 1 ELSE 0 END AS hot, dst * 100000 + CAST(floor((us + c * 1000000) / {W}) AS BIGINT) AS due FROM topic, (SELECT 0 AS c UNION ALL SELECT 1 UNION ALL SELECT 2) WHERE c = 0 OR dst % 1000 = 7) GROUP BY hot", ("topic",))
portable("wl_w12_sweep", " UNION ALL ".join(f"SELECT {h} AS hours, count(DISTINCT dst * 1000000 + CAST(floor(us / {h * H}) AS BIGINT)) AS outputs, CAST(floor(avg(CAST({due_sql(h * H)} - us AS DOUBLE))) AS BIGINT) AS mean_us FROM hop" for h in (1, 12, 24)), ("hop",))
__all__ = ["SESSION", "TUMBLING"]
