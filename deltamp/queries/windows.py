"""Windowed inference: policies, their due times, and the state they leave."""

from __future__ import annotations

from pyspark.sql import functions as F

from deltamp.operators import window as win
from deltamp.registry import graph, pair, portable
from deltamp.sources.graphs import DAY

H = DAY // 24
W = 12 * H
GAP = 6 * H


def rows_of(spark, sf, name="hop"):
    return graph(spark, sf, name).select(F.col("dst").alias("key"), "us", "seq")


def due_sql(width=W):
    return f"CAST((floor(us / {width}) + 1) * {width} AS BIGINT)"


_OUT = "SELECT key, due, count(*) AS n, max(us) AS last_us FROM {} GROUP BY key, due"
TUMBLING = f"(SELECT dst AS key, us, {due_sql()} AS due FROM hop)"
SESSION = f"(SELECT key, us, max(us) OVER (PARTITION BY key, s) + {GAP} AS due FROM (SELECT key, us, sum(fresh) OVER (PARTITION BY key ORDER BY us, seq) AS s FROM (SELECT dst AS key, us, seq, CASE WHEN us - lag(us) OVER (PARTITION BY dst ORDER BY us, seq) > {GAP} THEN 1 ELSE 0 END AS fresh FROM hop)))"
POLICIES = {
    "tumbling": (lambda r: win.tumbling(r, W), TUMBLING),
    "session": (lambda r: win.session(r, GAP), SESSION),
    "per_event": (win.per_event, "(SELECT dst AS key, us, us AS due FROM hop)"),
    "sliding": (lambda r: win.sliding(r, 2 * W, W), f"(SELECT dst AS key, us, (CAST(floor(us / {W}) AS BIGINT) - k) * {W} + {2 * W} AS due FROM hop, (SELECT 0 AS k UNION ALL SELECT 1))"),
    "count": (lambda r: win.fixed_count(r, 2000), "(SELECT dst AS key, us, CAST(floor((row_number() OVER (ORDER BY seq) - 1) / 2000) AS BIGINT) AS due FROM hop)"),
}
_GAPS = f"""SELECT key, day, CAST(floor(f * 1e6 + 0.5) AS BIGINT) AS freq, least(CAST({2 * DAY} AS BIGINT), greatest(CAST({H} AS BIGINT), CAST(floor(2 * CAST({DAY} AS DOUBLE) / f) AS BIGINT))) AS gap FROM (
  SELECT key, day, list_reduce(list(CAST(n AS DOUBLE)) OVER (PARTITION BY key ORDER BY day), lambda a, x: (a + x) / 2) AS f FROM (SELECT dst AS key, CAST(floor(us / {DAY}) AS BIGINT) AS day, count(*) AS n FROM hop GROUP BY dst, CAST(floor(us / {DAY}) AS BIGINT)))"""
ADAPTIVE = f"""(SELECT key, us, max(us * 1) OVER (PARTITION BY key, s) + last_value(gap) OVER (PARTITION BY key, s ORDER BY us, gap ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS due FROM (
  SELECT key, us, gap, sum(fresh) OVER (PARTITION BY key ORDER BY us, seq) AS s FROM (
    SELECT key, us, seq, gap, CASE WHEN us > lag(us + gap) OVER (PARTITION BY key ORDER BY us, seq) THEN 1 ELSE 0 END AS fresh FROM (
      SELECT hop.dst AS key, us, seq, coalesce(g.gap, {H}) AS gap FROM hop LEFT JOIN ({_GAPS}) g ON g.key = hop.dst AND g.day + 1 = CAST(floor(us / {DAY}) AS BIGINT)))))"""
POLICIES["adaptive"] = (win.adaptive, ADAPTIVE)
for _p, (_fn, _sql) in POLICIES.items():
    _name = {"count": "win_count_batches"}.get(_p, f"win_{_p}_counts")

    @pair(_name, _OUT.format(_sql), ("hop",))
    def _policy(spark, sf, _fn=_fn):
        return win.outputs(_fn(rows_of(spark, sf)))


@pair("win_adaptive_gaps", _GAPS, ("hop",))
def win_adaptive_gaps(spark, sf):
    return win.adaptive_gaps(rows_of(spark, sf))


@pair("win_tumbling_perkey", f"""WITH RECURSIVE o AS (SELECT dst AS key, min(us) AS open FROM hop GROUP BY dst UNION ALL
  SELECT key, nxt FROM (SELECT o.key, (SELECT min(us) FROM hop WHERE dst = o.key AND us >= o.open + {W}) AS nxt FROM o) WHERE nxt IS NOT NULL)
  SELECT key, open + {W} AS due, count(*) AS n, max(us) AS last_us FROM o JOIN hop ON dst = key AND us >= open AND us < open + {W} GROUP BY key, open""", ("hop",))
def win_tumbling_perkey(spark, sf):
    return win.outputs(win.tumbling_per_key(rows_of(spark, sf), W))


portable("win_emit_counts", f"SELECT dst AS key, count(*) AS updates, count(DISTINCT {due_sql()}) AS outputs FROM hop GROUP BY dst", ("hop",))


@pair("win_gather_partials", f"SELECT CAST((src * 31 + dst * 17 + seq * 7) % 16 AS INTEGER) AS lpart, dst, {due_sql()} AS due, count(*) AS n, count(DISTINCT src) AS sources FROM hop GROUP BY 1, 2, 3", ("hop",))
def win_gather_partials(spark, sf):
    return win.gather_partials(graph(spark, sf, "hop"), 16, W)


portable("win_gather_counts", f"SELECT dst, {due_sql()} AS due, count(*) AS edges, count(DISTINCT src) AS messages FROM hop GROUP BY dst, {due_sql()}", ("hop",))
_NOW = "(SELECT max(us) - 3600000000 FROM hop)"
portable("win_pending_edges", f"SELECT count(*) AS pending, CAST(sum(w) AS BIGINT) AS w FROM hop WHERE us <= {_NOW} AND {due_sql()} > {_NOW}", ("hop",))
portable("win_evict_asof", f"SELECT dst, count(*) AS evicted FROM hop WHERE {due_sql()} <= {_NOW} GROUP BY dst", ("hop",))
portable("win_count_split", "SELECT p, CAST(floor((r - 1) / 500) AS BIGINT) AS batch, count(*) AS n FROM (SELECT dst % 4 AS p, row_number() OVER (PARTITION BY dst % 4 ORDER BY seq) AS r FROM hop) GROUP BY p, CAST(floor((r - 1) / 500) AS BIGINT)", ("hop",))


@pair("win_coalesced_timers", f"SELECT count(DISTINCT due) AS timers, count(DISTINCT CAST(ceil(due / {W // 2}) * {W // 2} AS BIGINT)) AS coalesced FROM {SESSION}", ("hop",))
def win_coalesced_timers(spark, sf):
    d = win.session(rows_of(spark, sf), GAP)
    return d.agg(F.countDistinct("due").alias("timers")).crossJoin(win.coalesced(d, W // 2).agg(F.countDistinct("due").alias("coalesced")))


@pair("cms_cells")
def cms_cells(spark, sf):
    return win.CountMin().update(rows_of(spark, sf))


@pair("cms_error")
def cms_error(spark, sf):
    """Estimated less true counts per key: never below zero."""
    r, s = rows_of(spark, sf), win.CountMin(depth=4, width=64)
    true = r.groupBy("key").agg(F.count("*").alias("n"))
    return s.estimate(s.update(r), r).join(true, "key").select("key", (F.col("estimate") - F.col("n")).alias("error"))
