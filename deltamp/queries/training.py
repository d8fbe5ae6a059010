"""Training on a frozen version: votes, gradients, averaging and rebuild."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from deltamp.functions.grid import DIMS, weights
from deltamp.operators import infer, training
from deltamp.queries.layers import full_sql, hop_and_features
from deltamp.registry import graph, pair, portable

N = range(DIMS)


def _through(w, g="g", out="g"):
    return ", ".join(f"CAST({' + '.join(f'({w[i][k]}) * {g}{i}' for i in N)} AS BIGINT) AS {out}{k}" for k in N)


def _linear(layer, source):
    ws, wn, _ = weights(layer)
    own = [" + ".join(f"({ws[i][k]}) * x{k} + ({wn[i][k]}) * coalesce(a{k}, 0)" for k in N) for i in N]
    sums = ", ".join(f"sum(h.x{k}) AS a{k}" for k in N)
    return f"(SELECT v, {', '.join(f'CAST({o} AS BIGINT) AS x{i}' for i, o in zip(N, own))} FROM {source} LEFT JOIN (SELECT e.dst, {sums} FROM hop e JOIN {source} h ON e.src = h.v GROUP BY e.dst) ON v = dst)"


_OUT = f"SELECT f.v, 2 * (f.x0 - e.label) AS g0, {', '.join(f'CAST(0 AS BIGINT) AS g{i}' for i in N if i)} FROM f2 f JOIN emb0 e ON e.v = f.v"
_GS = ", ".join(f"g{i}" for i in N)
_SUMS = ", ".join(f"CAST(sum(g{i}) AS BIGINT) AS g{i}" for i in N)


def _back(layer, source):
    ws, wn, _ = weights(layer)
    return f"SELECT v, {_SUMS} FROM (SELECT v, {_through(ws)} FROM {source} UNION ALL SELECT e.src AS v, {_GS} FROM (SELECT v AS gv, {_through(wn)} FROM {source}) JOIN hop e ON e.dst = gv) GROUP BY v"


_CTES = f"WITH f1 AS {_linear(0, 'emb0')}, f2 AS {_linear(1, 'f1')}, g2 AS ({_OUT}), g1 AS ({_back(1, 'g2')}), g0 AS ({_back(0, 'g1')})"


def state(spark, sf):
    v, e = hop_and_features(spark, sf)
    f1 = infer.settle(training.forward_linear(v, e, 0))
    f2 = infer.settle(training.forward_linear(f1, e, 1))
    return v, e, f1, f2, training.output_gradient(f2, v)


@pair("train_sq_loss_grad", f"{_CTES} SELECT v, {_GS} FROM g2", ("hop", "emb0"))
def train_sq_loss_grad(spark, sf):
    return state(spark, sf)[4]


@pair("train_grad_accumulate", f"{_CTES} SELECT v, {_SUMS} FROM (SELECT * FROM g2 UNION ALL SELECT * FROM g2) GROUP BY v", ("hop", "emb0"))
def train_grad_accumulate(spark, sf):
    g = state(spark, sf)[4]
    return training.accumulate(g.union(g))


@pair("train_bwd_update", f"{_CTES} SELECT v, {_through(weights(1)[1])} FROM g2", ("hop", "emb0"))
def train_bwd_update(spark, sf):
    return training.backward_update(state(spark, sf)[4], 1)[0]


@pair("train_bwd_message", f"{_CTES} SELECT e.src AS v, {_SUMS} FROM hop e JOIN g2 ON e.dst = g2.v GROUP BY e.src", ("hop", "emb0"))
def train_bwd_message(spark, sf):
    _, e, _, _, g = state(spark, sf)
    return training.backward_message(e, g)


@pair("train_grad_2layer", f"{_CTES} SELECT v, {_GS} FROM g0", ("hop", "emb0"))
def train_grad_2layer(spark, sf):
    _, e, _, _, g = state(spark, sf)
    return training.backward_layer(training.backward_layer(g, e, 1), e, 0)


@pair("train_input_update", f"{_CTES} SELECT v, {', '.join(f'CAST(floor(x{i} - g{i} / 1024.0) AS BIGINT) AS x{i}' for i in N)} FROM g0 JOIN emb0 USING (v)", ("hop", "emb0"))
def train_input_update(spark, sf):
    v = graph(spark, sf, "emb0")
    return train_grad_2layer(spark, sf).join(v, "v").selectExpr("v", *[f"CAST(floor(x{i} - g{i} / 1024.0D) AS BIGINT) AS x{i}" for i in N])


_LONG = ", ".join(f"[{', '.join(f'{c}{i}' for i in N)}] AS {c}s" for c in "gx")
_CELLS = f"SELECT p, i, j, CAST(sum(gs[i + 1] * xs[j + 1]) AS BIGINT) AS g FROM (SELECT f1.v % {{}} AS p, {_LONG} FROM f1 JOIN g2 USING (v)), (SELECT CAST(unnest(range({DIMS})) AS INTEGER) AS i), (SELECT CAST(unnest(range({DIMS})) AS INTEGER) AS j) GROUP BY p, i, j"


@pair("train_sgd_step", f"{_CTES} SELECT i, j, CAST(floor(1024.0 * ((7 * i + 3 * j + 4) % 5 - 2) - g / 1048576.0) AS BIGINT) AS value FROM ({_CELLS.format(1)})", ("hop", "emb0"))
def train_sgd_step(spark, sf):
    _, _, f1, _, g = state(spark, sf)
    return training.weight_gradient(f1, g).selectExpr("i", "j", "CAST(floor(1024.0D * ((7 * i + 3 * j + 4) % 5 - 2) - g / 1048576.0D) AS BIGINT) AS value")


@pair("train_model_average", f"{_CTES} SELECT i, j, CAST(floor(avg(CAST(g AS DOUBLE)) + 0.5) AS BIGINT) AS value FROM ({_CELLS.format(4)}) GROUP BY i, j", ("hop", "emb0"))
def train_model_average(spark, sf):
    """Four parts each sum their own vertices' gradients; the model is their unweighted mean."""
    _, _, f1, _, g = state(spark, sf)
    parts = None
    for p in range(4):
        own = training.weight_gradient(f1.where(f"v % 4 = {p}"), g).select(F.lit(p).alias("part"), "i", "j", F.col("g").cast("double").alias("value"))
        parts = own if parts is None else parts.union(own)
    return training.average(parts).select("i", "j", F.floor(F.col("value") + 0.5).cast("long").alias("value"))


@pair("train_softmax_loss")
def train_softmax_loss(spark, sf):
    """Cross entropy of a softmax over all components, by label."""
    v = graph(spark, sf, "emb0")
    z = [F.exp(F.col(f"x{i}") / 1024.0) for i in N]
    p = F.element_at(F.array(*z), F.col("label") % DIMS + 1) / sum(z[1:], z[0])
    return v.groupBy("label").agg(F.avg(-F.log(p)).alias("loss"), F.count("*").alias("n"))


@pair("train_optimisers")
def train_optimisers(spark, sf):
    """Three optimisers over the same gradient for three steps."""
    rows = sorted((r["i"], r["j"], float(r["g"])) for r in training.weight_gradient(*(lambda s: (s[2], s[4]))(state(spark, sf))).collect())
    g = np.array([r[2] for r in rows]) / 2.0**40
    out = []
    for kind in ("sgd", "adam", "adamax"):
        o, p = training.Optimiser(kind), np.zeros(len(g))
        for _ in range(3):
            p = o.step(p, g)
        out += [(kind, i, j, float(x)) for (i, j, _), x in zip(rows, p)]
    return spark.createDataFrame(out, "optimiser string, i int, j int, value double")


_DAYS = "SELECT dst % 4 AS part, CAST(floor(us / 86400000000) AS BIGINT) AS day, count(*) AS n FROM hop JOIN emb0 ON dst = v GROUP BY 1, 2"


@pair("train_vote", f"WITH d AS ({_DAYS}), m AS (SELECT part, CAST(sum(n) AS BIGINT) AS s, count(*) AS days FROM d GROUP BY part) SELECT day, CAST(sum(CASE WHEN n * days > s THEN 1 ELSE 0 END) AS INTEGER) AS votes, sum(CASE WHEN n * days > s THEN 1 ELSE 0 END) * 2 > 4 AS start FROM d JOIN m USING (part) GROUP BY day", ("hop", "emb0"))
def train_vote(spark, sf):
    """Four parts vote by day: a part asks when more edges reach its labelled vertices than on its mean day."""
    e, v = graph(spark, sf, "hop"), graph(spark, sf, "emb0").select("v")
    d = e.join(v, F.col("dst") == F.col("v")).groupBy(F.pmod("dst", F.lit(4)).alias("part"), F.floor(F.col("us") / 86_400_000_000).alias("day")).agg(F.count("*").alias("n"))
    mean = d.groupBy("part").agg(F.sum("n").alias("s"), F.count("*").alias("days"))
    votes = d.join(mean, "part").groupBy("day").agg(F.count_if(F.col("n") * F.col("days") > F.col("s")).cast("int").alias("votes"))
    return votes.select("day", "votes", training.should_start(F.col("votes"), 4).alias("start"))


portable("train_trigger_size", "SELECT v % 4 AS part, count(*) AS labelled, count(*) >= 30 AS asks FROM emb0 GROUP BY v % 4", ("emb0",))
portable("train_trigger_metric", "SELECT p, acc, acc < 0.2 AS asks FROM (SELECT v % 4 AS p, CAST(sum(CASE WHEN CASE WHEN x0 >= x1 THEN 0 ELSE 1 END = label % 2 THEN 1 ELSE 0 END) AS DOUBLE) / count(*) AS acc FROM emb0 GROUP BY v % 4)", ("emb0",))


@pair("train_batch_plan", "SELECT CAST(e AS INTEGER) AS epoch, a AS first_row, least(n, a + 50) AS end_row FROM (SELECT count(*) AS n FROM emb0), (SELECT unnest([0, 1]) AS e), LATERAL (SELECT unnest(range(0, n, 50)) AS a)", ("emb0",))
def train_batch_plan(spark, sf):
    return spark.createDataFrame(training.plan_batches(graph(spark, sf, "emb0").count(), 50, 2), "epoch int, first_row long, end_row long")


portable("rebuild_messages", "SELECT dst, count(DISTINCT (src * 31 + dst * 17 + seq * 7) % 16) AS rebuilt, count(*) AS in_degree FROM hop GROUP BY dst", ("hop",))


@pair("rebuild_equals_full", full_sql(layers=2), ("hop", "emb0"))
def rebuild_equals_full(spark, sf):
    """One pre-summed reduce per part and destination, then the update, layer by layer."""
    from deltamp.operators import aggregators as agg
    from deltamp.operators.partition import random_arithmetic

    v, e = hop_and_features(spark, sf)
    e = random_arithmetic(e)
    h = v.select("v", *agg.X)
    for layer in range(2):
        m = e.join(h, F.col("src") == F.col("v"))
        local = m.groupBy("lpart", "dst").agg(*[F.expr(f"sum({x}) AS {y}") for x, y in zip(agg.X, agg.S)], F.count("*").alias("n"))
        h = infer.update_rows(h, agg.merge(local.drop("lpart")), layer)
    return h


@pair("train_grad_link", f"{_CTES} SELECT e.src AS v, CAST(sum(2 * (a.x0 + b.x0 - e.w)) AS BIGINT) AS g FROM hop e JOIN f1 a ON e.src = a.v JOIN f1 b ON e.dst = b.v GROUP BY e.src", ("hop", "emb0"))
def train_grad_link(spark, sf):
    """An edge task reads both ends; the source's share of its gradient."""
    _, e, f1, _, _ = state(spark, sf)
    j = e.join(f1.select(F.col("v").alias("src"), F.col("x0").alias("a")), "src").join(f1.select(F.col("v").alias("dst"), F.col("x0").alias("b")), "dst")
    return j.groupBy(F.col("src").alias("v")).agg(F.sum(2 * (F.col("a") + F.col("b") - F.col("w"))).alias("g"))


@pair("train_stale_gap", f"WITH f1 AS {_linear(0, 'emb0')}, p1 AS {_linear(0, 'emb0').replace('FROM hop e', 'FROM (SELECT * FROM hop WHERE seq % 2 = 0) e')} SELECT count(*) AS differing FROM f1 JOIN p1 USING (v) WHERE f1.x0 <> p1.x0", ("hop", "emb0"))
def train_stale_gap(spark, sf):
    """Vertices whose forward state differs when half the edges weren't there: a pass across a change is stale."""
    v, e = hop_and_features(spark, sf)
    a, b = training.forward_linear(v, e, 0), training.forward_linear(v, e.where("seq % 2 = 0"), 0).withColumnRenamed("x0", "y0")
    return a.join(b, "v").where("x0 <> y0").agg(F.count("*").alias("differing"))


_ALL = ", ".join(f"x{i}" for i in N)


@pair("metric_confusion", f"SELECT label AS truth, CAST((list_position([{_ALL}], list_max([{_ALL}])) - 1) % 10 AS INTEGER) AS class, count(*) AS n FROM emb0 GROUP BY 1, 2", ("emb0",))
def metric_confusion(spark, sf):
    guess = f"CAST((array_position(array({_ALL}), array_max(array({_ALL}))) - 1) % 10 AS INT)"
    return graph(spark, sf, "emb0").selectExpr("label AS truth", f"{guess} AS class").groupBy("truth", "class").agg(F.count("*").alias("n"))


@pair("train_accuracy_stream")
def train_accuracy_stream(spark, sf):
    """Running accuracy of a fixed head at the output, by event time day."""
    e, v = graph(spark, sf, "hop"), graph(spark, sf, "emb0")
    hit = (F.when(F.col("x0") >= F.col("x1"), 0).otherwise(1) == F.col("label") % 2).cast("int")
    return e.join(v, F.col("dst") == F.col("v")).groupBy(F.floor(F.col("us") / 86_400_000_000).alias("day")).agg(F.avg(hit).alias("accuracy"))
