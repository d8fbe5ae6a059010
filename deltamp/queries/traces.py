"""The windowed forward pass by policy: flushed states, and messages, volume, imbalance and latency read from its trace."""

from __future__ import annotations

import math

from pyspark.sql import functions as F

from deltamp.durable import forget, kept
from deltamp.functions.grid import DIMS
from deltamp.operators import infer
from deltamp.operators import window as win
from deltamp.operators import windowed as wd
from deltamp.operators.aggregators import X
from deltamp.operators.store import Store
from deltamp.queries.layers import batches_of, full_sql, hop_and_features
from deltamp.queries.windows import GAP, W
from deltamp.registry import graph, pair

BYTES = 8 * DIMS + 24
tumble, wait = (lambda r: win.tumbling(r, W)), (lambda r: win.session(r, GAP))


def windows_of(policy: str, edges):
    """(gather, emit) of a policy; the emit and gather ablations have one window only."""
    return {
        "per_event": (None, None), "tumbling": (tumble, tumble), "session": (wait, wait), "adaptive": (win.adaptive, win.adaptive),
        "sketched": (lambda r: win.adaptive(r, sketch=win.CountMin()),) * 2, "count": (win.by_count(edges, 2000), None), "emit": (None, tumble), "gather": (tumble, None),
    }[policy]


# ---- SQL of the same trace, written from the definitions ----------------------------------------


def due_sql(policy: str, rel: str, columns: str) -> str:
    """columns and due of a relation with key, us and seq."""
    if policy == "tumbling":
        return f"SELECT {columns}, CAST((floor(us / {W}) + 1) * {W} AS BIGINT) AS due FROM {rel}"
    if policy == "session":
        fresh = f"SELECT *, CASE WHEN us - lag(us) OVER (PARTITION BY key ORDER BY us, seq) > {GAP} THEN 1 ELSE 0 END AS fresh FROM {rel}"
        return f"SELECT {columns}, max(us) OVER (PARTITION BY key, part) + {GAP} AS due FROM (SELECT *, sum(fresh) OVER (PARTITION BY key ORDER BY us, seq) AS part FROM ({fresh}))"
    return f"SELECT {columns}, us AS due FROM {rel}"


def trace_sql(policy: str, g: str = "hop") -> str:
    """CTEs of two layers: g (gathered edges), e1, s2 (swaps), e2, with the first cause of each."""
    gather, emit = {"emit": ("per_event", "tumbling"), "gather": ("tumbling", "per_event")}.get(policy, (policy, policy))
    keyed = f"(SELECT dst AS key, src, us, seq FROM {g})"
    return f"""g AS (SELECT src, key AS dst, us, due AS tm FROM ({due_sql(gather, keyed, 'src, key, us, seq')})),
 t1 AS (SELECT dst AS key, tm AS us, 0 AS seq, min(us) AS first FROM g GROUP BY dst, tm),
 e1 AS (SELECT key AS v, due AS tm, min(first) AS first FROM ({due_sql(emit, 't1', 'key, first')}) GROUP BY key, due),
 s2 AS (SELECT g.src, g.dst, e1.tm, greatest(g.us, e1.first) AS first FROM g JOIN e1 ON e1.v = g.src WHERE e1.tm > g.tm),
 m2 AS (SELECT src, dst, tm, us AS first FROM g UNION ALL SELECT src, dst, tm, first FROM s2),
 t2 AS (SELECT key, us, 0 AS seq, min(first) AS first FROM (SELECT dst AS key, tm AS us, first FROM m2 UNION ALL SELECT v, tm, first FROM e1) GROUP BY key, us),
 e2 AS (SELECT key AS v, due AS tm, min(first) AS first FROM ({due_sql(emit, 't2', 'key, first')}) GROUP BY key, due)"""


def over_policies(body: str, policies: tuple[str, ...], g: str = "hop") -> str:
    return " UNION ALL ".join(f"(WITH {trace_sql(p, g)} {body.format(p=p)})" for p in policies)


def trace_of(e, policy: str):
    v = e.select(F.col("src").alias("v")).union(e.select("dst")).distinct()
    return wd.run(v, e, *windows_of(policy, e), values=False)


def each_policy(spark, sf, policies, make, g: str = "hop"):
    out, e = None, kept(graph(spark, sf, g).select("seq", "us", "src", "dst"))
    for p in policies:
        rows = make(trace_of(e, p)).withColumn("policy", F.lit(p))
        out = rows if out is None else out.unionByName(rows)
    return out


# ---- states and counts --------------------------------------------------------------------------

for _p in ("tumbling", "session", "adaptive", "sketched", "count"):

    @pair("win_final_equals_full" if _p == "tumbling" else f"win_final_{_p}", full_sql(layers=2), ("hop", "emb0"))
    def _final(spark, sf, _p=_p):
        """After the last window has closed the state is that of full inference."""
        v, e = infer.settle(graph(spark, sf, "emb0")), kept(graph(spark, sf, "hop").select("seq", "us", "src", "dst"))
        return wd.final(wd.run(v, e, *windows_of(_p, e)))


MAIN = ("per_event", "tumbling", "session")
_COUNTS = "SELECT '{p}' AS policy, 1 AS layer, (SELECT count(*) FROM g) AS absorbs, CAST(0 AS BIGINT) AS swaps, (SELECT count(*) FROM e1) AS outputs UNION ALL SELECT '{p}', 2, (SELECT count(*) FROM g), (SELECT count(*) FROM s2), (SELECT count(*) FROM e2)"


@pair("trace_counts", over_policies(_COUNTS, MAIN), ("hop",))
def trace_counts(spark, sf):
    """Messages, swaps and outputs of both layers by policy."""
    return each_policy(spark, sf, MAIN, wd.counts)


@pair("wl_w11_ablation", over_policies(_COUNTS, ("per_event", "emit", "gather", "tumbling")), ("hop",))
def wl_w11_ablation(spark, sf):
    """Neither window, one of them, and both."""
    return each_policy(spark, sf, ("per_event", "emit", "gather", "tumbling"), wd.counts)


def placed():
    return F.pmod(F.col("src") * 31 + F.col("dst") * 17, F.lit(16))


_CROSS = lambda rel: f"(SELECT count(*) FROM (SELECT DISTINCT (src * 31 + dst * 17) % 16 AS part, dst, tm FROM {rel} WHERE (src * 31 + dst * 17) % 16 <> dst % 16))"
_VOLUME = f"SELECT '{{p}}' AS policy, 1 AS layer, {_CROSS('g')} AS messages, {_CROSS('g')} * {BYTES} AS bytes UNION ALL SELECT '{{p}}', 2, {_CROSS('m2')}, {_CROSS('m2')} * {BYTES}"


@pair("volume_by_policy", over_policies(_VOLUME, MAIN), ("hop",))
def volume_by_policy(spark, sf):
    """Partial sums that cross parts, by layer and policy."""
    return each_policy(spark, sf, MAIN, lambda t: wd.partials(t, placed(), 16))


def _latencies(trace):
    late = F.col("at") - F.col("first")
    d = trace[-1].emissions.where((F.col("at") > wd.ALWAYS) & F.col("first").isNotNull())
    return d.agg(F.floor(F.avg(late.cast("double")) / 1e6).cast("long").alias("mean_s"), F.max(late).alias("max_us"), F.min(late).alias("min_us"), F.floor(F.stddev_pop(late.cast("double")) / 1e6 + 0.5).cast("long").alias("deviation_s"))


_LATE = "SELECT '{p}' AS policy, CAST(floor(avg(CAST(tm - first AS DOUBLE)) / 1e6) AS BIGINT) AS mean_s, max(tm - first) AS max_us, min(tm - first) AS min_us, CAST(floor(stddev_pop(CAST(tm - first AS DOUBLE)) / 1e6 + 0.5) AS BIGINT) AS deviation_s FROM e2"


@pair("wl_w5_latency", over_policies(_LATE, MAIN), ("hop",))
def wl_w5_latency(spark, sf):
    """From the first event that an output of the last layer stands for to that output, over both layers."""
    return each_policy(spark, sf, MAIN, _latencies)


def _imbalance(trace, parts=(4, 16)):
    out, fine = None, math.lcm(*parts)
    for k, layer in enumerate(trace, 1):
        counted = infer.settle(layer.messages.groupBy(F.pmod(F.col("dst"), F.lit(fine)).alias("f")).agg(F.count("*").alias("n")))  # as many rows
        for n in parts:
            loads = counted.groupBy((F.col("f") % n).alias("q")).agg(F.sum("n").alias("n"))
            one = loads.agg(F.sum("n").alias("messages"), F.floor(F.max("n") * n / F.sum("n") * 1e6 + 0.5).cast("long").alias("imbalance")).select(F.lit(k).alias("layer"), F.lit(n).alias("parts"), "messages", "imbalance")
            out = one if out is None else out.unionByName(one)
    forget(*(x for layer in trace for x in (layer.gathered, layer.emissions)))  # all that is read of them is counted
    return out


_LOAD = " UNION ALL ".join(f"SELECT '{{p}}' AS policy, {k} AS layer, {n} AS parts, CAST(sum(n) AS BIGINT) AS messages, CAST(floor(max(n) * {n} / CAST(sum(n) AS DOUBLE) * 1e6 + 0.5) AS BIGINT) AS imbalance FROM (SELECT count(*) AS n FROM {rel} GROUP BY dst % {n})" for k, rel in ((1, "g"), (2, "m2")) for n in (4, 16))
for _g in ("hop", "topic", "copurchase"):
    _these = ("tumbling", "session") if _g == "topic" else MAIN

    @pair(f"wl_w1_{_g}", over_policies(_LOAD, _these, _g), (_g,))
    def _scaling(spark, sf, _g=_g, _these=_these):
        """Messages of both layers and the greatest over the mean load of the masters' parts, at two parallelisms."""
        return each_policy(spark, sf, _these, _imbalance, _g)


@pair("imbalance_by_policy", over_policies(_LOAD, MAIN), ("hop",))
def imbalance_by_policy(spark, sf):
    return each_policy(spark, sf, MAIN, _imbalance)


_DAILY = "SELECT '{p}' AS policy, count(*) AS days, max(n) AS most, CAST(sum(n) AS BIGINT) AS outputs FROM (SELECT floor(tm / 86400000000) AS d, count(*) AS n FROM e2 GROUP BY floor(tm / 86400000000))"


@pair("throughput_final_layer", over_policies(_DAILY, MAIN), ("hop",))
def throughput_final_layer(spark, sf):
    """Outputs of the last layer by event-time day."""
    def daily(trace):
        d = trace[-1].emissions.where(F.col("at") > wd.ALWAYS).groupBy(F.floor(F.col("at") / 86_400_000_000).alias("d")).agg(F.count("*").alias("n"))
        return d.agg(F.count("*").alias("days"), F.max("n").alias("most"), F.sum("n").alias("outputs"))

    return each_policy(spark, sf, MAIN, daily)


@pair("win_adaptive_gaps_sketch")
def win_adaptive_gaps_sketch(spark, sf):
    """Gaps from the averaged sketch beside the exact ones: a sketch never counts less."""
    r = graph(spark, sf, "hop").select(F.col("dst").alias("key"), "us", "seq")
    exact, told = win.adaptive_gaps(r), win.adaptive_gaps(r, sketch=win.CountMin())
    return exact.join(told.select("key", "day", F.col("freq").alias("sketch_freq")), ["key", "day"]).select("key", "day", "freq", "sketch_freq")


# ---- state kept up on larger graphs, and what recomputing costs ---------------------------------


def goods_of(spark, sf):
    return infer.settle(graph(spark, sf, "goods")), infer.settle(graph(spark, sf, "copurchase").select("seq", "us", "src", "dst"))


@pair("wl_w7_copurchase", full_sql("copurchase", 2, "goods"), ("copurchase", "goods"))
def wl_w7_copurchase(spark, sf):
    """The larger graph: loaded up to the last day, the rest kept up in a batch."""
    v, e = goods_of(spark, sf)
    last = e.agg(F.max("us")).first()[0]
    store = Store(spark, 2).load(v, e.where(F.col("us") < last))
    store.apply(1, e.where(F.col("us") == last))
    return store.outputs()


_LIVE = "(SELECT eid, src, dst FROM (SELECT eid, src, dst, max_by(op, us * 64 + seq % 64) AS op FROM trade GROUP BY eid, src, dst) WHERE op <> 'del')"


@pair("wl_w9_trade", full_sql(_LIVE, 2, "(SELECT * FROM goods UNION ALL SELECT * FROM buyers)"), ("trade", "goods", "buyers"))
def wl_w9_trade(spark, sf):
    """Deletions: purchases come in three batches by time, each with the returns that fall into it."""
    v = infer.settle(graph(spark, sf, "goods").unionByName(graph(spark, sf, "buyers")))
    t = infer.settle(graph(spark, sf, "trade").select("us", "src", "dst", "op"))
    store = Store(spark, 2).load(v)
    for k, (rows, _) in enumerate(batches_of(t, 3), 1):
        store.apply(k, rows.where("op = 'add'"), rows.where("op = 'del'"))
    return store.outputs()


def recompute(vertices, edges, batch, layers: int = 2):
    """What a static library does after a batch: find the influenced vertices and compute them anew from their in-edges."""
    reached = infer.influenced(edges, batch.select(F.col("dst").alias("v")).distinct(), layers - 1)
    needed = [reached]
    for _ in range(layers - 1):
        into = edges.join(needed[0].withColumnRenamed("v", "dst"), "dst", "left_semi").select(F.col("src").alias("v"))
        needed.insert(0, needed[0].union(into).distinct())
    h = vertices.select("v", *X)
    for layer, targets in enumerate(needed):
        own = edges.join(targets.withColumnRenamed("v", "dst"), "dst", "left_semi")
        h = infer.update_rows(h.join(targets, "v", "left_semi"), infer.merge(infer.absorb(infer.messages(own, h))), layer)
    return h


@pair("base_recompute_state", full_sql(layers=2).replace(" FROM h2", " FROM h2 WHERE v IN (SELECT dst FROM hop WHERE us >= (SELECT max(us) FROM hop) - 3600000000) OR v IN (SELECT b.dst FROM hop a JOIN hop b ON b.src = a.dst WHERE a.us >= (SELECT max(us) FROM hop) - 3600000000)"), ("hop", "emb0"))
def base_recompute_state(spark, sf):
    """The last hour's edges as a batch: its influenced vertices, recomputed."""
    v, e = hop_and_features(spark, sf)
    last = e.agg(F.max("us")).first()[0]
    return recompute(v, e, e.where(F.col("us") >= last - 3_600_000_000))

