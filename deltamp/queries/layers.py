"""Graphs, models, aggregators and incremental inference."""

from __future__ import annotations

from pyspark.sql import functions as F

from deltamp.functions.grid import DIMS, mean_sql, update_sql
from deltamp.operators import aggregators as agg
from deltamp.operators import infer
from deltamp.operators.store import cascade
from deltamp.registry import graph, pair, portable

N = range(DIMS)
for _g in ("hop", "topic", "copurchase", "trade", "fk", "reply", "link"):
    portable(f"g_{_g}_edges", f"SELECT * FROM {_g}", (_g,), ())
portable("g_feature_updates", "SELECT * FROM feat", ("feat",))
portable("g_trade_deletes", "SELECT eid, us, src, dst FROM trade WHERE op = 'del'", ("trade",))
_SNAP = "SELECT eid, src, dst FROM (SELECT eid, src, dst, max_by(op, us * 64 + seq % 64) AS op FROM trade GROUP BY eid, src, dst) WHERE op <> 'del'"


@pair("g_snapshot", _SNAP, ("trade",))
def g_snapshot(spark, sf):
    return infer.snapshot(graph(spark, sf, "trade"))


portable("g_vertex_stream", "SELECT dst AS v, count(*) AS neighbours, min(seq) AS first_seq FROM topic GROUP BY dst", ("topic",))
portable("g_subgraph_events", "SELECT src AS v, min(seq) AS seq, count(*) AS edges, count(DISTINCT dst) AS vertices FROM copurchase GROUP BY src", ("copurchase",))
portable("split_route_counts", "SELECT 'edge' AS kind, l AS layer, count(*) AS n FROM hop, (SELECT 1 AS l UNION ALL SELECT 2) GROUP BY l UNION ALL SELECT 'feature', 1, count(*) FROM feat UNION ALL SELECT 'label', 3, count(*) FROM emb0", ("hop", "feat", "emb0"))
portable("halo_replica_rows", "SELECT halo, sum(CASE WHEN halo = 1 THEN 0 ELSE parts - 1 END) AS rows_sent FROM (SELECT v, v % 2 AS halo, count(DISTINCT p) AS parts FROM (SELECT src AS v, (src * 31 + dst * 17 + seq * 7) % 16 AS p FROM topic UNION ALL SELECT dst, (src * 31 + dst * 17 + seq * 7) % 16 FROM topic) GROUP BY v) GROUP BY halo".replace("sum(CASE", "CAST(sum(CASE").replace("END) AS", "END) AS BIGINT) AS"), ("topic",))
_DEG = "SELECT v, CAST(sum(o) AS BIGINT) AS out_degree, CAST(sum(i) AS BIGINT) AS in_degree FROM (SELECT src AS v, 1 AS o, 0 AS i FROM topic UNION ALL SELECT dst, 0, 1 FROM topic) GROUP BY v"
portable("deg_in_out", _DEG, ("topic",))
portable("deg_avg", f"SELECT CAST(floor(avg(out_degree) * 1e6 + 0.5) AS BIGINT) AS avg_out, max(out_degree) AS max_out, max(in_degree) AS max_in, count(*) AS n FROM ({_DEG})", ("topic",))
portable("deg_skew_topk", f"SELECT v, in_degree FROM ({_DEG}) ORDER BY in_degree DESC, v LIMIT 20", ("topic",))


def layer_cte(name: str, source: str, edges: str, layer: int) -> str:
    """A layer over vertices (v, x*) as CTEs name_a and name."""
    sums = ", ".join(f"sum(h.x{i}) AS s{i}" for i in N)
    means = ", ".join(f"{mean_sql(f's{i}', 'n')} AS m{i}" for i in N)
    read = ", ".join(f"coalesce(m{i}, 0) AS m{i}" for i in N)
    return f"{name}_a AS (SELECT dst, {means} FROM (SELECT e.dst, {sums}, count(*) AS n FROM {edges} e JOIN {source} h ON e.src = h.v GROUP BY e.dst)), {name} AS (SELECT v, {', '.join(f'{u} AS x{i}' for i, u in zip(N, update_sql(layer)))} FROM (SELECT v, {', '.join(f'x{i}' for i in N)}, {read} FROM {source} LEFT JOIN {name}_a ON v = dst))"


def full_sql(edges: str = "hop", layers: int = 2, source: str = "emb0") -> str:
    ctes = []
    for k in range(layers):
        ctes.append(layer_cte(f"h{k + 1}", source, edges, k))
        source = f"h{k + 1}"
    return f"WITH {', '.join(ctes)} SELECT v, {', '.join(f'x{i}' for i in N)} FROM {source}"


def hop_and_features(spark, sf):
    e = graph(spark, sf, "hop").withColumn("eid", F.col("seq").cast("string"))
    return infer.settle(graph(spark, sf, "emb0")), infer.settle(e)


for _k in (1, 2):

    @pair(f"inf_sage{_k}", full_sql(layers=_k), ("hop", "emb0"))
    def _inf(spark, sf, _k=_k):
        return infer.full(graph(spark, sf, "emb0"), graph(spark, sf, "hop"), _k)


def batches_of(edges, parts: int):
    """Edges cut into so many batches of equal event time, as (added, no deletion)."""
    lo, hi = edges.agg(F.min("us"), F.max("us")).first()
    width = max(1, -(-(hi - lo + 1) // parts))
    k = F.floor((F.col("us") - lo) / width)
    return [(edges.where(k == i), edges.where("false")) for i in range(parts)]


@pair("delta_cascade2_state", full_sql(layers=2), ("hop", "emb0"))
def delta_cascade2_state(spark, sf):
    v, e = hop_and_features(spark, sf)
    return cascade(v, batches_of(e, 3), 2).outputs()


@pair("delta_layer1_state", f"WITH {layer_cte('h1', 'emb0', 'hop', 0)} SELECT e.dst, {', '.join(f'CAST(sum(x{i}) AS BIGINT) AS s{i}' for i in N)}, count(*) AS n FROM hop e JOIN emb0 ON src = v GROUP BY e.dst", ("hop", "emb0"))
def delta_layer1_state(spark, sf):
    v, e = hop_and_features(spark, sf)
    return cascade(v, batches_of(e, 3), 1).aggregates(1)


@pair("delta_edge_add", full_sql(layers=1), ("hop", "emb0"))
def delta_edge_add(spark, sf):
    v, e = hop_and_features(spark, sf)
    return cascade(v, batches_of(e, 2), 1).outputs()


_KEPT = "(SELECT * FROM hop WHERE etype <> 'error')"


@pair("delta_edge_delete", full_sql(_KEPT, 2), ("hop", "emb0"))
def delta_edge_delete(spark, sf):
    v, e = hop_and_features(spark, sf)
    return cascade(v, [(e, None), (None, e.where("etype = 'error'"))], 2).outputs()


@pair("delta_order_invariance", full_sql(layers=2), ("hop", "emb0"))
def delta_order_invariance(spark, sf):
    v, e = hop_and_features(spark, sf)
    return cascade(v, batches_of(e, 3)[::-1], 2).outputs()


@pair("delta_edge_update", f"SELECT e.dst, {', '.join(f'CAST(sum(x{i} * 2) AS BIGINT) AS s{i}' for i in N)}, count(*) AS n FROM hop e JOIN emb0 ON src = v GROUP BY e.dst", ("hop", "emb0"))
def delta_edge_update(spark, sf):
    """An edge feature changes from 1 to 2: each message is swapped on its own edge."""
    v, e = hop_and_features(spark, sf)
    old = infer.messages(e, v)
    new = old.selectExpr("dst", *[f"{x} * 2 AS {x}" for x in agg.X])
    return agg.merge(agg.swap(new, old), agg.merge(agg.absorb(old)))


def packed(v):
    return v.selectExpr("v", f"array({', '.join(agg.X)}) AS x")


_FEATS = f"(SELECT v, x0 + 1 AS x0, {', '.join(agg.X[1:])} FROM emb0)"
_FEW = "(SELECT * FROM emb0 WHERE label >= 3)"


@pair("delta_feature_update", f"WITH up AS {_FEATS}, {layer_cte('h1', 'up', 'hop', 0)}, {layer_cte('h2', 'h1', 'hop', 1)} SELECT v, {', '.join(agg.X)} FROM h2", ("hop", "emb0"))
def delta_feature_update(spark, sf):
    """Every feature moves after the edges came: swaps run through both layers."""
    v, e = hop_and_features(spark, sf)
    store = cascade(v, [(e, None)], 2)
    store.apply(2, features=v.selectExpr("v", f"array(x0 + 1, {', '.join(agg.X[1:])}) AS x"))
    return store.outputs()


@pair("delta_feature_add", full_sql(layers=2), ("hop", "emb0"))
def delta_feature_add(spark, sf):
    """The features of three labels arrive after the edges: their messages are absorbed once ready."""
    v, e = hop_and_features(spark, sf)
    store = cascade(v.where("label >= 3"), [(e, None)], 2)
    store.apply(2, features=packed(v.where("label < 3")))
    return store.outputs()


@pair("delta_feature_delete", f"WITH few AS {_FEW}, {layer_cte('h1', 'few', 'hop', 0)}, {layer_cte('h2', 'h1', 'hop', 1)} SELECT v, {', '.join(agg.X)} FROM h2", ("hop", "emb0"))
def delta_feature_delete(spark, sf):
    """Three labels lose their features: their messages are retracted in both layers, their edges stay."""
    v, e = hop_and_features(spark, sf)
    store = cascade(v, [(e, None)], 2)
    store.apply(2, features=v.where("label < 3").selectExpr("v", "CAST(NULL AS ARRAY<BIGINT>) AS x"))
    return store.outputs()


@pair("delta_vertex_delete", f"WITH few AS {_FEW}, left_ AS (SELECT h.* FROM hop h JOIN few a ON src = a.v JOIN few b ON dst = b.v), {layer_cte('h1', 'few', 'left_', 0)}, {layer_cte('h2', 'h1', 'left_', 1)} SELECT v, {', '.join(agg.X)} FROM h2", ("hop", "emb0"))
def delta_vertex_delete(spark, sf):
    """Three labels' vertices go with all their edges, in one batch."""
    v, e = hop_and_features(spark, sf)
    store = cascade(v, [(e, None)], 2)
    gone = v.where("label < 3").select("v")
    edges = e.alias("e").join(gone.alias("a"), F.expr("e.src = a.v"), "left").join(gone.alias("b"), F.expr("e.dst = b.v"), "left").where("a.v IS NOT NULL OR b.v IS NOT NULL").select("e.*")
    store.apply(2, deleted=edges, features=gone.selectExpr("v", "CAST(NULL AS ARRAY<BIGINT>) AS x"))
    return store.outputs()


portable("ready_counts", f"SELECT CASE WHEN v IS NULL THEN 0 ELSE 1 END AS ready, count(*) AS edges FROM hop LEFT JOIN {_FEW} ON src = v GROUP BY CASE WHEN v IS NULL THEN 0 ELSE 1 END", ("hop", "emb0"))
_T = "(SELECT max(us) AS t FROM hop WHERE seq <= (SELECT max(seq) / 2 FROM hop))"


@pair("asof_embeddings", full_sql(f"(SELECT * FROM hop WHERE us <= {_T.replace('SELECT max(us) AS t', 'SELECT max(us)')})", 2), ("hop", "emb0"))
def asof_embeddings(spark, sf):
    v, e = hop_and_features(spark, sf)
    half = e.agg(F.max("seq")).first()[0] / 2
    return infer.full(v, e.where(F.col("seq") <= half), 2)


for _h, _sql in ((1, "SELECT DISTINCT dst AS v FROM hop WHERE src = 0 UNION SELECT 0"), (2, "SELECT v FROM (SELECT b.dst AS v FROM hop a JOIN hop b ON b.src = a.dst WHERE a.src = 0 UNION SELECT dst FROM hop WHERE src = 0 UNION SELECT 0)")):

    @pair(f"influenced_set_{_h}hop", _sql.replace("SELECT 0", "SELECT CAST(0 AS BIGINT)"), ("hop",))
    def _influenced(spark, sf, _h=_h):
        return infer.influenced(graph(spark, sf, "hop"), spark.range(1).select(F.col("id").alias("v")), _h)


@pair("worked_example", "SELECT CAST(layer AS INTEGER) AS layer, v FROM (VALUES (1, 0), (2, 0), (2, 1), (2, 2)) t(layer, v)".replace("layer, v FROM", "layer, CAST(v AS BIGINT) AS v FROM"))
def worked_example(spark, sf):
    """a=0 sends to b=1 and c=2; then d=3 sends to a. Layer one changes a, layer two a, b and c."""
    level = {0: 9, 1: 2, 2: 3, 3: 90}
    v = spark.createDataFrame([(k, *[n + (7 * i + 3 * k) % 11 for i in N]) for k, n in level.items()], f"v long, {', '.join(f'{x} long' for x in agg.X)}")
    e = spark.createDataFrame([(0, 1), (0, 2)], "src long, dst long")
    d = spark.createDataFrame([(3, 0)], "src long, dst long")
    store = cascade(v, [(e, None), (d, None)], 2)
    return store.changed(1).select(F.lit(1).alias("layer"), "v").union(store.changed(2).select(F.lit(2), "v"))


# Models beyond the mean: one-layer readings over grid features.


@pair("inf_gcn1", f"SELECT dst AS v, {', '.join(f'CAST(sum(x{i}) AS BIGINT) AS y{i}' for i in N)} FROM hop JOIN emb0 ON src = v GROUP BY dst", ("hop", "emb0"))
def inf_gcn1(spark, sf):
    """The plain sum of messages."""
    v, e = hop_and_features(spark, sf)
    return infer.messages(e, v).groupBy(F.col("dst").alias("v")).agg(*[F.expr(f"sum(x{i}) AS y{i}") for i in N])


_SYM = f"SELECT e.dst AS v, {', '.join(f'CAST(sum(CAST(floor(x{i} / sqrt(CAST(o.d AS DOUBLE) * i.d) * 1024 + 0.5) AS BIGINT)) AS BIGINT) AS y{i}' for i in N)} FROM {{}} e JOIN emb0 ON e.src = v JOIN (SELECT src, count(*) AS d FROM {{}} GROUP BY src) o ON o.src = e.src JOIN (SELECT dst, count(*) AS d FROM {{}} GROUP BY dst) i ON i.dst = e.dst GROUP BY e.dst"


def _symmetric(edges, v, sign=1):
    """Messages divided by the root of both ends' degrees, on the grid, so that sums are exact."""
    out, into = edges.groupBy("src").agg(F.count("*").alias("od")), edges.groupBy("dst").agg(F.count("*").alias("id"))
    j = edges.join(out, "src").join(into, "dst").join(v, F.expr("src = v"))
    return j.selectExpr("src", "dst", "od", "id", *[f"{sign} * CAST(floor({x} / sqrt(CAST(od AS DOUBLE) * id) * 1024D + 0.5D) AS BIGINT) AS {x}" for x in agg.X])


@pair("inf_gcn_sym", _SYM.format("hop", "hop", "hop"), ("hop", "emb0"))
def inf_gcn_sym(spark, sf):
    v, e = hop_and_features(spark, sf)
    return _symmetric(e, v).groupBy(F.col("dst").alias("v")).agg(*[F.expr(f"sum(x{i}) AS y{i}") for i in N])


@pair("delta_gcn_sym", _SYM.format("hop", "hop", "hop"), ("hop", "emb0"))
def delta_gcn_sym(spark, sf):
    """An edge changes its ends' degrees, so a batch also swaps the other messages of its sources and destinations."""
    v, e = hop_and_features(spark, sf)
    early, late = e.where("etype <> 'error'"), e.where("etype = 'error'")
    state = infer.settle(_symmetric(early, v).groupBy("dst").agg(*[F.expr(f"sum({x}) AS {x}") for x in agg.X]))
    moved = e.join(late.select("src").distinct(), "src", "left_semi").select("seq").union(e.join(late.select("dst").distinct(), "dst", "left_semi").select("seq")).distinct()

    def again(edges, sign):
        degrees = edges.groupBy("src").agg(F.count("*").alias("od")), edges.groupBy("dst").agg(F.count("*").alias("id"))
        j = edges.join(moved, "seq", "left_semi").join(degrees[0], "src").join(degrees[1], "dst").join(v, F.expr("src = v"))
        return j.selectExpr("dst", *[f"{sign} * CAST(floor({x} / sqrt(CAST(od AS DOUBLE) * id) * 1024D + 0.5D) AS BIGINT) AS {x}" for x in agg.X])

    deltas = again(early, -1).unionByName(again(e, 1)).unionByName(state)
    return deltas.groupBy(F.col("dst").alias("v")).agg(*[F.expr(f"sum(x{i}) AS y{i}") for i in N])


portable("inf_edge_weighted", "SELECT dst AS v, CAST(sum(x0 * w) AS BIGINT) AS y0, CAST(sum(x1 * w) AS BIGINT) AS y1, CAST(sum(w) AS BIGINT) AS w FROM hop JOIN emb0 ON src = v GROUP BY dst", ("hop", "emb0"))
portable("inf_typed_fk", "SELECT dst AS v, CAST(sum(src % 1000 * CASE etype WHEN 'order-part' THEN 2 WHEN 'supplier-part' THEN 3 WHEN 'customer-order' THEN 5 ELSE 7 END) AS BIGINT) AS y, count(*) AS n FROM fk GROUP BY dst", ("fk",))
_JUMPS = {"concat": [f"{t}.x{i} AS {t}{i}" for t in "ab" for i in N], "max": [f"greatest(a.x{i}, b.x{i}) AS y{i}" for i in N]}
for _m, _e in _JUMPS.items():

    @pair(f"inf_jk_{_m}", f"WITH {layer_cte('h1', 'emb0', 'hop', 0)}, {layer_cte('h2', 'h1', 'hop', 1)} SELECT a.v, {', '.join(_e)} FROM h1 a JOIN h2 b ON a.v = b.v", ("hop", "emb0"))
    def _jump(spark, sf, _e=_e):
        v, e = hop_and_features(spark, sf)
        one = infer.settle(infer.full(v, e, 1))
        two = infer.update_rows(one, agg.merge(agg.absorb(infer.messages(e, one))), 1)
        return one.alias("a").join(two.alias("b"), F.expr("a.v = b.v")).selectExpr("a.v AS v", *_e)


_ALL = ", ".join(agg.X)
_DOT = lambda a, b: " + ".join(f"{a}x{i} * {b}x{i}" for i in N)


@pair("head_node_argmax", f"SELECT v, CAST(list_position([{_ALL}], list_max([{_ALL}])) - 1 AS INTEGER) AS class FROM emb0", ("emb0",))
def head_node_argmax(spark, sf):
    return graph(spark, sf, "emb0").selectExpr("v", f"CAST(array_position(array({_ALL}), array_max(array({_ALL}))) - 1 AS INT) AS class")


@pair("head_link_dot", f"SELECT seq, CAST({_DOT('a.', 'b.')} AS BIGINT) AS score FROM hop JOIN emb0 a ON src = a.v JOIN emb0 b ON dst = b.v", ("hop", "emb0"))
def head_link_dot(spark, sf):
    """The score of every edge from whole embeddings of its ends."""
    e, v = graph(spark, sf, "hop").select("seq", "src", "dst"), graph(spark, sf, "emb0").selectExpr("v", f"array({_ALL}) AS x")
    j = e.join(v.selectExpr("v AS src", "x AS a"), "src").join(v.selectExpr("v AS dst", "x AS b"), "dst")
    return j.selectExpr("seq", "aggregate(zip_with(a, b, (p, q) -> p * q), 0L, (t, y) -> t + y) AS score")


@pair("head_topk_similar", f"SELECT a.v, CAST(floor(CAST({_DOT('a.', 'q.')} AS DOUBLE) / sqrt(CAST({_DOT('a.', 'a.')} AS DOUBLE)) / sqrt(CAST({_DOT('q.', 'q.')} AS DOUBLE)) * 1e6 + 0.5) AS BIGINT) AS cosine FROM emb0 a, (SELECT * FROM emb0 ORDER BY v LIMIT 1) q WHERE a.v <> q.v ORDER BY cosine DESC, v LIMIT 10", ("emb0",))
def head_topk_similar(spark, sf):
    """The ten vertices with the greatest cosine to a query, which is the first vertex."""
    v = graph(spark, sf, "emb0").selectExpr("v", f"array({_ALL}) AS x")
    q = v.orderBy("v").first()
    dot = lambda a, b: f"CAST(aggregate(zip_with({a}, {b}, (p, r) -> p * r), 0L, (t, y) -> t + y) AS DOUBLE)"
    scored = v.where(F.col("v") != q["v"]).withColumn("q", F.array(*[F.lit(y).cast("long") for y in q["x"]]))
    return scored.selectExpr("v", f"CAST(floor({dot('x', 'q')} / sqrt({dot('x', 'x')}) / sqrt({dot('q', 'q')}) * 1e6D + 0.5D) AS BIGINT) AS cosine").orderBy(F.col("cosine").desc(), "v").limit(10)


@pair("head_graph_pool", f"SELECT label, {', '.join(f'CAST(sum(x{i}) AS BIGINT) AS s{i}' for i in N)}, {', '.join(f'max(x{i}) AS m{i}' for i in N)}, count(*) AS n FROM emb0 GROUP BY label", ("emb0",))
def head_graph_pool(spark, sf):
    """Sum and maximum readouts of the graph of each label."""
    return graph(spark, sf, "emb0").groupBy("label").agg(*[F.expr(f"sum(x{i}) AS s{i}") for i in N], *[F.expr(f"max(x{i}) AS m{i}") for i in N], F.count("*").alias("n"))


def _gat(spark, sf):
    """One head: scores read both ends, weights are softmax over in-edges."""
    v, e = hop_and_features(spark, sf)
    f = v.select("v", *[(F.col(x) / 1024.0).alias(x) for x in agg.X])
    a, b = f.alias("a"), f.alias("b")
    j = e.join(a, F.expr("src = a.v")).join(b, F.expr("dst = b.v"))
    s = j.select("dst", F.exp(F.expr("0.5 * a.x0 - 0.25 * b.x1")).alias("w"), F.col("a.x0").alias("m"))
    return s.groupBy("dst").agg(F.sum(F.col("w") * F.col("m")).alias("num"), F.sum("w").alias("den")).select(F.col("dst").alias("v"), (F.col("num") / F.col("den")).alias("y"))


pair("inf_gat1")(_gat)


@pair("delta_gat_state")
def delta_gat_state(spark, sf):
    """The same by deltas: edges come in three batches, and a third of the vertices has other features until the last."""
    v, e = hop_and_features(spark, sf)
    early = v.selectExpr("v", *[f"CASE WHEN label < 3 THEN {x} + {512 * (k + 1)} ELSE {x} END AS {x}" for k, x in enumerate(agg.X)])
    added = batches_of(e, 3)
    state = infer.attention_cascade([(v if k == 2 else early, *b) for k, b in enumerate(added)])
    return state.select(F.col("dst").alias("v"), (F.col("num").cast("double") / F.col("den").cast("double")).alias("y"))


@pair("inf_memory_decay")
def inf_memory_decay(spark, sf):
    """A vertex memory that halves with every event of the vertex and takes the event's value in."""
    f = graph(spark, sf, "feat").groupBy("vid").agg(F.array_sort(F.collect_list(F.struct("seq", "val_new"))).alias("a"))
    return f.select("vid", F.aggregate("a", F.lit(0.0), lambda h, p: h / 2 + p["val_new"] / 1024.0).alias("memory"))


# Aggregators on the purchase graph with returns: messages are the source's local id modulo 1000.
_LIVE = f"({_SNAP})"


def _signed(spark, sf):
    t = graph(spark, sf, "trade")
    m = lambda op: t.where(f"op = '{op}'").select("dst", (F.col("src") % 1000).alias("x0"), *[F.lit(0).cast("long").alias(x) for x in agg.X[1:]])
    return agg.absorb(m("add")).unionByName(agg.retract(m("del")))


for _name, _sql, _pick in (
    ("agg_sum_incremental", "CAST(sum(src % 1000) AS BIGINT) AS s", "s0 AS s"),
    ("agg_count_incremental", "count(*) AS n", "n"),
    ("agg_mean_incremental", "CAST(floor(sum(CAST(src % 1000 AS DOUBLE)) / count(*) + 0.5) AS BIGINT) AS m", "CAST(floor(CAST(s0 AS DOUBLE) / n + 0.5) AS BIGINT) AS m"),
):

    @pair(_name, f"SELECT dst, {_sql} FROM {_LIVE} GROUP BY dst", ("trade",))
    def _incremental(spark, sf, _pick=_pick):
        return agg.merge(_signed(spark, sf)).where("n > 0").selectExpr("dst", _pick)


for _kind in ("min", "max"):

    @pair(f"agg_{_kind}_retract", f"SELECT dst, {_kind}(src % 1000) AS value, count(*) AS n FROM {_LIVE} GROUP BY dst", ("trade",))
    def _extremum(spark, sf, _kind=_kind):
        t = graph(spark, sf, "trade").select("dst", (F.col("src") % 1000).alias("value"), F.when(F.col("op") == "add", 1).otherwise(-1).cast("long").alias("mult"))
        return agg.extremum(t, _kind)


@pair("agg_concat", "SELECT dst, string_agg(CAST(w AS VARCHAR), ',' ORDER BY seq) AS messages FROM hop GROUP BY dst", ("hop",))
def agg_concat(spark, sf):
    return agg.concat(graph(spark, sf, "hop").select("dst", "seq", F.col("w").alias("value")))


@pair("agg_recurrent_linear", "SELECT dst, list_reduce(list_prepend(CAST(0 AS BIGINT), list(w ORDER BY seq)), lambda h, m: ((2 * h + 3 * m) % 1000003 + 1000003) % 1000003) AS h FROM hop GROUP BY dst", ("hop",))
def agg_recurrent_linear(spark, sf):
    return agg.recurrent_linear(graph(spark, sf, "hop").select("dst", "seq", F.col("w").alias("value")))


@pair("agg_recurrent_gated")
def agg_recurrent_gated(spark, sf):
    """A gated cell, where a swap is only approximate: state after messages, and after pushing the last one's negation."""
    a = graph(spark, sf, "hop").groupBy("dst").agg(F.array_sort(F.collect_list(F.struct("seq", "w"))).alias("a"))
    cell = lambda h, x: F.tanh(0.5 * h + x / 102400.0)
    h = F.aggregate("a", F.lit(0.0), lambda h, p: cell(h, p["w"]))
    before = F.aggregate(F.slice("a", 1, F.greatest(F.size("a") - 1, F.lit(0))), F.lit(0.0), lambda h, p: cell(h, p["w"]))
    undone = cell(h, -F.element_at("a", -1)["w"])
    return a.select("dst", h.alias("h"), F.abs(undone - before).alias("deviation"))


@pair("agg_distinct_hll")
def agg_distinct_hll(spark, sf):
    return agg.distinct_sketch(graph(spark, sf, "topic"))


_ZERO = "SELECT CAST(0 AS BIGINT) AS differences"


@pair("agg_law_inverse", _ZERO)
def agg_law_inverse(spark, sf):
    """Absorbing and retracting the same messages leaves every state at zero."""
    v, e = hop_and_features(spark, sf)
    m = infer.messages(e, v)
    return agg.merge(agg.absorb(m).unionByName(agg.retract(m))).where(" OR ".join(f"{x} <> 0" for x in (*agg.S, "n"))).agg(F.count("*").alias("differences"))


@pair("agg_law_merge", _ZERO)
def agg_law_merge(spark, sf):
    """Merging the states of two halves equals the state of all."""
    v, e = hop_and_features(spark, sf)
    half = lambda k: agg.merge(agg.absorb(infer.messages(e.where(f"seq % 2 = {k}"), v)))
    whole = agg.merge(agg.absorb(infer.messages(e, v)))
    both = agg.merge(half(0), half(1))
    return both.exceptAll(whole).union(whole.exceptAll(both)).agg(F.count("*").alias("differences"))


@pair("agg_law_commute", _ZERO)
def agg_law_commute(spark, sf):
    """Deletions before additions give the state that additions before deletions give."""
    d = _signed(spark, sf)
    one, two = agg.merge(d.where("n > 0"), agg.merge(d.where("n < 0"))), agg.merge(d.where("n < 0"), agg.merge(d.where("n > 0")))
    return one.exceptAll(two).union(two.exceptAll(one)).agg(F.count("*").alias("differences"))
