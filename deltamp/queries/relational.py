"""The relational surface a user of the methods needs: sources, sinks, joins, aggregates, windows, scalars, SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from deltamp.plans.shared import scratch
from deltamp.registry import graph, pair, portable, table

EV = ("events",)


def same(name, body, tables=(), graphs=(), spark=None):
    portable(name, body, tuple(graphs), tuple(tables), spark)


# Sources and sinks: a round trip through each format.
def _round_trip(fmt):
    def run(spark, sf):
        path = f"{scratch(spark)}/{fmt}"
        rows = table(spark, sf, "events").select("event_id", "user_id", "event_type", "value")
        writer = rows.write.format(fmt).option("header", True)
        writer.save(path)
        return spark.read.format(fmt).schema(rows.schema).option("header", True).load(path)

    return run


for _f in ("json", "csv", "orc"):
    pair(f"src_{_f}_roundtrip", "SELECT event_id, user_id, event_type, value FROM events")(_round_trip(_f))
same("src_parquet_pruned", "SELECT user_id, count(*) AS n FROM events WHERE event_type = 'click' GROUP BY user_id", EV)


@pair("src_python_ds", "SELECT seq, src, dst FROM hop", ("hop",))
def src_python_ds(spark, sf):
    """The hop graph's edges, written and read again through the Python data source."""
    from deltamp.sources.python_source import GraphEdges

    spark.dataSource.register(GraphEdges)
    path = f"{scratch(spark)}/edges"
    graph(spark, sf, "hop").select("seq", "src", "dst").write.format("graph_edges").mode("append").save(path)
    return spark.read.format("graph_edges").load(path)


@pair("snk_partitioned", "SELECT event_type, count(*) AS n, CAST(sum(event_id) AS BIGINT) AS ids FROM events GROUP BY event_type")
def snk_partitioned(spark, sf):
    path = f"{scratch(spark)}/by_type"
    table(spark, sf, "events").select("event_id", "event_type").write.partitionBy("event_type").parquet(path)
    return spark.read.parquet(path).groupBy("event_type").agg(F.count("*").alias("n"), F.sum("event_id").alias("ids"))


@pair("snk_idempotent", "SELECT count(*) AS n, CAST(sum(event_id) AS BIGINT) AS ids FROM events")
def snk_idempotent(spark, sf):
    """A batch written twice under its id is there once."""
    path = f"{scratch(spark)}/batches"
    for batch in (0, 1, 1):
        table(spark, sf, "events").select("event_id").where(f"event_id % 2 = {batch}").write.mode("overwrite").parquet(f"{path}/batch={batch}")
    return spark.read.parquet(path).agg(F.count("*").alias("n"), F.sum("event_id").alias("ids"))


@pair("snk_bucketed", "SELECT user_id, count(*) AS n FROM events GROUP BY user_id")
def snk_bucketed(spark, sf):
    """Equal keys share a file, so the aggregate needs no shuffle when it reads the layout back by bucket."""
    path = f"{scratch(spark)}/bucketed"
    table(spark, sf, "events").select("user_id", F.pmod(F.hash("user_id"), F.lit(8)).alias("bucket")).repartition(8, "bucket").write.partitionBy("bucket").parquet(path)
    return spark.read.parquet(path).groupBy("user_id").agg(F.count("*").alias("n"))


# Projections and filters.
same("proj_vector_explode", "SELECT v, 0 AS dim, x0 AS val FROM emb0 UNION ALL SELECT v, 1, x1 FROM emb0", graphs=("emb0",))
same("proj_vector_pivot", "SELECT v, max(CASE WHEN dim = 0 THEN val END) AS a, max(CASE WHEN dim = 1 THEN val END) AS b FROM (SELECT v, 0 AS dim, x0 AS val FROM emb0 UNION ALL SELECT v, 1, x1 FROM emb0) GROUP BY v", graphs=("emb0",))
pair("proj_struct_pack", "SELECT v, x0 + x1 AS s FROM emb0", ("emb0",))(lambda spark, sf: graph(spark, sf, "emb0").select("v", F.struct("x0", "x1").alias("p")).select("v", (F.col("p.x0") + F.col("p.x1")).alias("s")))
same("flt_time_range", "SELECT seq, src FROM hop WHERE us >= (SELECT min(us) FROM hop) + 86400000000 AND us < (SELECT min(us) FROM hop) + 172800000000", graphs=("hop",))
same("flt_null_safe_changed", "SELECT count(*) AS changed FROM feat WHERE val_old IS DISTINCT FROM val_new", graphs=("feat",))
pair("flt_array_exists", "SELECT vec_id FROM embeddings WHERE len(list_filter(embedding, lambda x: x > 0.35)) > 0")(lambda spark, sf: table(spark, sf, "embeddings").where(F.exists("embedding", lambda x: x > F.lit(0.35))).select("vec_id"))
same("flt_regex_href", "SELECT src, count(*) AS n FROM link WHERE dst LIKE '/t%' GROUP BY src", graphs=("link",))
# Joins.
_J = {"join_broadcast_weights": "BROADCAST(b)", "join_shuffle_hash": "SHUFFLE_HASH(b)", "join_sort_merge": "MERGE(b)"}
for _n, _h in _J.items():
    _body = "SELECT {} a.seq, b.label FROM hop a JOIN emb0 b ON a.src = b.v"
    same(_n, _body.format(""), graphs=("hop", "emb0"), spark=_body.format(f"/*+ {_h} */"))
same("join_inner_edge_feature", "SELECT seq, x0 FROM hop JOIN emb0 ON src = v", graphs=("hop", "emb0"))
same("join_left_features", "SELECT seq, x0 FROM hop LEFT JOIN (SELECT * FROM emb0 WHERE v % 2 = 0) ON src = v", graphs=("hop", "emb0"))
same("join_full_state_merge", "SELECT coalesce(a.v, b.v) AS v, coalesce(a.n, 0) + coalesce(b.n, 0) AS n FROM (SELECT src AS v, count(*) AS n FROM hop WHERE seq % 3 = 0 GROUP BY src) a FULL OUTER JOIN (SELECT dst AS v, count(*) AS n FROM hop WHERE seq % 3 = 1 GROUP BY dst) b ON a.v = b.v", graphs=("hop",))
same("join_nested_loop", "SELECT r_name, n_name FROM region, nation WHERE r_regionkey < n_regionkey", ("region", "nation"))
same("join_semi_ready", "SELECT seq FROM hop LEFT SEMI JOIN (SELECT v FROM emb0 WHERE v % 3 = 0) f ON src = f.v".replace("LEFT SEMI JOIN", "SEMI JOIN"), graphs=("hop", "emb0"), spark="SELECT seq FROM hop LEFT SEMI JOIN (SELECT v FROM emb0 WHERE v % 3 = 0) f ON src = f.v")
same("join_anti_pending", "SELECT seq FROM hop ANTI JOIN (SELECT v FROM emb0 WHERE v % 3 = 0) f ON src = f.v", graphs=("hop", "emb0"), spark="SELECT seq FROM hop LEFT ANTI JOIN (SELECT v FROM emb0 WHERE v % 3 = 0) f ON src = f.v")
same("join_time_prefix", "SELECT a.seq, count(*) AS before FROM hop a JOIN hop b ON a.dst = b.dst AND b.seq <= a.seq GROUP BY a.seq", graphs=("hop",))
_GAP = 3_600_000_000


@pair("join_interval_bucketed", f"SELECT a.seq AS a, b.seq AS b FROM hop a JOIN hop b ON a.dst = b.src AND b.us >= a.us AND b.us < a.us + {_GAP}", ("hop",))
def join_interval_bucketed(spark, sf):
    """A range join as an equi-join: each left row meets the right rows of its own bucket and the next."""
    e = graph(spark, sf, "hop").withColumn("b", F.floor(F.col("us") / _GAP))
    left = e.select("seq", "us", F.col("dst").alias("k"), F.explode(F.array("b", F.col("b") + 1)).alias("b")).alias("l")
    return left.join(e.select("seq", "us", F.col("src").alias("k"), "b").alias("r"), ["k", "b"]).where(f"r.us >= l.us AND r.us < l.us + {_GAP}").select(F.col("l.seq").alias("a"), F.col("r.seq").alias("b"))


@pair("join_asof_feature", "SELECT h.seq, f.val_new AS val FROM hop h ASOF LEFT JOIN feat f ON h.src = f.vid AND h.seq >= f.seq", ("hop", "feat"))
def join_asof_feature(spark, sf):
    """Union and one ordered pass per vertex: the latest value no later than the edge."""
    from pyspark.sql import Window

    e = graph(spark, sf, "hop").select(F.col("src").alias("v"), "seq", F.lit(None).cast("long").alias("val"), F.lit(1).alias("edge"))
    f = graph(spark, sf, "feat").select(F.col("vid").alias("v"), "seq", F.col("val_new").alias("val"), F.lit(0).alias("edge"))
    w = Window.partitionBy("v").orderBy("seq", "edge").rowsBetween(Window.unboundedPreceding, 0)
    return e.unionByName(f).withColumn("val", F.last("val", ignorenulls=True).over(w)).where("edge = 1").select("seq", "val")


same("join_copurchase", "SELECT src, count(*) AS n FROM copurchase GROUP BY src", graphs=("copurchase",))
same("path_two_hop", "SELECT a.src, b.dst, count(*) AS paths FROM reply a JOIN reply b ON a.dst = b.src GROUP BY a.src, b.dst", graphs=("reply",))
_D = "(SELECT DISTINCT src, dst FROM hop WHERE etype = 'purchase')"
same("common_neighbours", f"SELECT a.src AS x, b.src AS y, count(*) AS n FROM {_D} a JOIN {_D} b ON a.dst = b.dst AND a.src < b.src GROUP BY a.src, b.src", graphs=("hop",))
same("triangle_count", f"SELECT count(*) AS triangles FROM {_D} a JOIN {_D} b ON a.dst = b.src JOIN {_D} c ON b.dst = c.src AND c.dst = a.src", graphs=("hop",))
same("join_lateral_topk", "SELECT v, dst, n FROM emb0, LATERAL (SELECT dst, count(*) AS n FROM hop WHERE src = v GROUP BY dst ORDER BY n DESC, dst LIMIT 2) t", graphs=("emb0", "hop"), spark="SELECT v, dst, n FROM (SELECT src AS v, dst, n, row_number() OVER (PARTITION BY src ORDER BY n DESC, dst) AS r FROM (SELECT src, dst, count(*) AS n FROM hop GROUP BY src, dst)) JOIN emb0 USING (v) WHERE r <= 2")
# Aggregation.
same("agg_basic", "SELECT event_type, count(*) AS n, min(event_id) AS lo, max(event_id) AS hi, CAST(sum(user_id) AS BIGINT) AS s FROM events GROUP BY event_type", EV)
same("agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type", EV)
pair("agg_approx_distinct")(lambda spark, sf: table(spark, sf, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users")))
same("agg_max_by", "SELECT user_id, max_by(event_type, event_id) AS last_type, min_by(event_type, event_id) AS first_type FROM events GROUP BY user_id", EV)
pair("agg_collect_sorted", "SELECT user_id, string_agg(DISTINCT event_type, ',' ORDER BY event_type) AS types FROM events GROUP BY user_id")(lambda spark, sf: table(spark, sf, "events").groupBy("user_id").agg(F.array_join(F.array_sort(F.collect_set("event_type")), ",").alias("types")))
same("agg_bit_or_parts", "SELECT dst, bit_or(CAST(power(2, src % 16) AS BIGINT)) AS mask FROM hop GROUP BY dst", graphs=("hop",))
same("agg_stddev_latency", "SELECT CAST(floor(stddev_pop(CAST(w AS DOUBLE)) * 1000 + 0.5) AS BIGINT) AS sd FROM hop", graphs=("hop",))
same("agg_percentile", "SELECT etype, CAST(floor(median(w) * 10 + 0.5) AS BIGINT) AS med FROM hop GROUP BY etype", graphs=("hop",))
same("agg_filter_clause", "SELECT dst, count(*) FILTER (WHERE etype = 'click') AS clicks, count(*) AS n FROM hop GROUP BY dst", graphs=("hop",))
for _n, _g in (("agg_grouping_sets", "GROUPING SETS ((etype, p), (etype), ())"), ("agg_rollup", "ROLLUP (etype, p)"), ("agg_cube", "CUBE (etype, p)")):
    same(_n, f"SELECT etype, p, count(*) AS n FROM (SELECT etype, dst % 4 AS p FROM hop) GROUP BY {_g}", graphs=("hop",))
pair("agg_pivot_policy", "SELECT dst % 10 AS k, count(*) FILTER (WHERE etype = 'click') AS click, count(*) FILTER (WHERE etype = 'view') AS view FROM hop GROUP BY dst % 10", ("hop",))(lambda spark, sf: graph(spark, sf, "hop").groupBy((F.col("dst") % 10).alias("k")).pivot("etype", ["click", "view"]).agg(F.count("seq")).fillna(0))
pair("agg_unpivot_measures", "SELECT v, 'x0' AS name, x0 AS value FROM emb0 UNION ALL SELECT v, 'x1', x1 FROM emb0", ("emb0",))(lambda spark, sf: graph(spark, sf, "emb0").unpivot("v", ["x0", "x1"], "name", "value"))
# Windows, order, sets.
_W = "OVER (PARTITION BY dst ORDER BY seq)"
for _n, _e in {"row_number": f"row_number() {_W}", "rank": "rank() OVER (PARTITION BY dst ORDER BY w)", "ntile": f"CAST(ntile(4) {_W} AS INTEGER)", "lag_gap": f"us - lag(us) {_W}", "running_degree": f"count(*) {_W}", "range_rate": "count(*) OVER (PARTITION BY dst ORDER BY us RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW)", "first_last": "first_value(w) OVER (PARTITION BY dst ORDER BY seq)"}.items():
    same(f"wf_{_n}", f"SELECT seq, CAST({_e} AS BIGINT) AS x FROM hop", graphs=("hop",))
same("sort_topk_degree", "SELECT dst, count(*) AS n FROM hop GROUP BY dst ORDER BY n DESC, dst LIMIT 10", graphs=("hop",))
same("sort_limit_offset", "SELECT seq FROM hop ORDER BY seq LIMIT 10 OFFSET 5", graphs=("hop",))
same("topk_per_group", "SELECT etype, seq FROM (SELECT etype, seq, row_number() OVER (PARTITION BY etype ORDER BY w DESC, seq) AS r FROM hop) WHERE r <= 3", graphs=("hop",))
same("set_union_events", "SELECT src AS v FROM hop UNION SELECT dst FROM hop", graphs=("hop",))
same("set_intersect_edges", "SELECT src, dst FROM hop INTERSECT SELECT dst, src FROM hop", graphs=("hop",))
same("set_except_live", "SELECT eid FROM trade WHERE op = 'add' EXCEPT SELECT eid FROM trade WHERE op = 'del'", graphs=("trade",))
same("set_except_all", "SELECT dst FROM hop EXCEPT ALL SELECT src FROM hop", graphs=("hop",))
# Scalars.
pair("vec_dot", "SELECT vec_id, CAST(floor(list_dot_product(CAST(embedding AS DOUBLE[]), CAST(embedding AS DOUBLE[])) * 1e4 + 0.5) AS BIGINT) AS d FROM embeddings")(lambda spark, sf: table(spark, sf, "embeddings").select("vec_id", F.floor(F.aggregate(F.transform("embedding", lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x) * 1e4 + 0.5).cast("long").alias("d")))
same("vec_axpy", "SELECT v, 3 * x0 + x1 AS y0, 3 * x2 + x3 AS y1 FROM emb0", graphs=("emb0",))
same("vec_norm", "SELECT v, CAST(floor(sqrt(CAST(x0 * x0 + x1 * x1 + x2 * x2 + x3 * x3 AS DOUBLE)) + 0.5) AS BIGINT) AS n FROM emb0", graphs=("emb0",))
same("vec_cosine", "SELECT seq, CAST(floor((a.x0 * b.x0 + a.x1 * b.x1) / (sqrt(CAST(a.x0 * a.x0 + a.x1 * a.x1 AS DOUBLE)) * sqrt(CAST(b.x0 * b.x0 + b.x1 * b.x1 AS DOUBLE)) + 1) * 1e4) AS BIGINT) AS c FROM hop JOIN emb0 a ON src = a.v JOIN emb0 b ON dst = b.v", graphs=("hop", "emb0"))
same("vec_relu", "SELECT v, greatest(x0, 0) AS y0, greatest(x1, 0) AS y1 FROM emb0", graphs=("emb0",))
same("vec_softmax", "SELECT v, CAST(floor(exp(x0 / 1024.0) / (exp(x0 / 1024.0) + exp(x1 / 1024.0)) * 1e4) AS BIGINT) AS p0 FROM emb0", graphs=("emb0",), spark="SELECT v, CAST(floor(exp(x0 / 1024.0D) / (exp(x0 / 1024.0D) + exp(x1 / 1024.0D)) * 1e4) AS BIGINT) AS p0 FROM emb0")  # a plain 1024.0 makes decimals of six places
same("vec_matvec", "SELECT v, 2 * x0 - x1 AS y0, x2 + 5 * x3 AS y1 FROM emb0", graphs=("emb0",))
pair("arr_sort_flatten", "SELECT user_id, string_agg(CAST(event_id AS VARCHAR), '-' ORDER BY event_id) AS ids FROM events GROUP BY user_id")(lambda spark, sf: table(spark, sf, "events").groupBy("user_id").agg(F.array_join(F.array_sort(F.flatten(F.collect_list(F.array("event_id")))).cast("array<string>"), "-").alias("ids")))
pair("arr_slice", "SELECT vec_id, CAST(floor(embedding[2] * 1024 + 0.5) AS BIGINT) AS second FROM embeddings")(lambda spark, sf: table(spark, sf, "embeddings").select("vec_id", F.floor(F.slice("embedding", 2, 1)[0].cast("double") * 1024 + 0.5).cast("long").alias("second")))


def _multiset(spark, sf):
    half = lambda k: graph(spark, sf, "hop").where(f"seq % 2 = {k}").groupBy("dst", "etype").count().groupBy("dst").agg(F.map_from_entries(F.collect_list(F.struct("etype", "count"))).alias(f"m{k}"))
    none = F.create_map().cast("map<string,bigint>")
    both = half(0).join(half(1), "dst", "full")
    return both.select("dst", F.map_zip_with(F.coalesce("m0", none), F.coalesce("m1", none), lambda k, a, b: F.coalesce(a, F.lit(0)) + F.coalesce(b, F.lit(0))).alias("m"))


pair("map_multiset_merge", "SELECT dst, etype, count(*) AS n FROM hop GROUP BY dst, etype", ("hop",))(lambda spark, sf: _multiset(spark, sf).select("dst", F.explode("m").alias("etype", "n")))
pair("map_filter_zero", "SELECT dst, count(*) AS kinds FROM (SELECT dst, etype FROM hop GROUP BY dst, etype HAVING count(*) > 2) GROUP BY dst", ("hop",))(lambda spark, sf: _multiset(spark, sf).select("dst", F.size(F.map_filter("m", lambda k, n: n > 2)).cast("long").alias("kinds")).where("kinds > 0"))
pair("json_props_k", "SELECT event_id, CAST(props->>'$.k' AS BIGINT) AS k FROM events")(lambda spark, sf: table(spark, sf, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k")))
same("str_href_extract", "SELECT src, dst FROM link", graphs=("link",))
pair("url_host", "SELECT page_id, regexp_extract(url, '://([^/?#]+)', 1) AS host FROM pages")(lambda spark, sf: table(spark, sf, "pages").select("page_id", F.expr("parse_url(url, 'HOST')").alias("host")))
same("time_bucket", "SELECT CAST(floor(us / 3600000000) AS BIGINT) AS hour, count(*) AS n FROM hop GROUP BY CAST(floor(us / 3600000000) AS BIGINT)", graphs=("hop",))
same("time_gap", "SELECT seq, us - lag(us) OVER (PARTITION BY src ORDER BY seq) AS gap FROM hop", graphs=("hop",))
same("time_trunc", "SELECT CAST(date_trunc('day', ts) AS DATE) AS day, count(*) AS n FROM events GROUP BY CAST(date_trunc('day', ts) AS DATE)", EV)
same("math_grid_quantise", "SELECT event_id, CAST(floor(CAST(value AS DOUBLE) * 1024 + 0.5) AS BIGINT) AS q FROM events", EV)
same("math_pmod_div", "SELECT event_id, event_id % 7 AS m, CAST(floor(event_id / 7) AS BIGINT) AS d FROM events", EV)
same("math_bitmask_count", "SELECT dst, CAST(bit_count(bit_or(CAST(power(2, src % 16) AS BIGINT))) AS INTEGER) AS parts FROM hop GROUP BY dst", graphs=("hop",))


# User functions.
@pair("udf_matvec_arrow")
def udf_matvec_arrow(spark, sf):
    """A layer's product in numpy over Arrow batches."""
    import numpy as np
    import pyarrow as pa

    w = np.arange(64 * 8).reshape(64, 8) % 5 - 2.0

    def run(batches):
        for b in batches:
            y = np.stack(b.column(1).to_numpy(zero_copy_only=False)) @ w if b.num_rows else np.zeros((0, 8))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(list(y), pa.list_(pa.float64()))], names=["vec_id", "y"])

    return table(spark, sf, "embeddings").select("vec_id", F.col("embedding").cast("array<double>")).mapInArrow(run, "vec_id long, y array<double>")


@pair("udf_grouped_grad")
def udf_grouped_grad(spark, sf):
    """Per label: the mean vector, a grouped gradient kernel."""
    import numpy as np
    import pandas as pd

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"label": [int(pdf["label"].iloc[0])], "g": [np.stack(pdf["embedding"]).mean(axis=0).astype(float).tolist()]})

    return table(spark, sf, "embeddings").groupBy("label").applyInPandas(run, "label int, g array<double>")


@pair("udaf_vector_sum")
def udaf_vector_sum(spark, sf):
    e = table(spark, sf, "embeddings").select("label", F.posexplode("embedding").alias("i", "x"))
    return e.groupBy("label", "i").agg(F.sum(F.col("x").cast("double")).alias("s"))


@pair("udtf_khop", "SELECT v, k AS hop, CASE k WHEN 1 THEN n WHEN 2 THEN n * n ELSE n * n * n END AS budget FROM (SELECT src AS v, count(*) AS n FROM hop GROUP BY src), (SELECT CAST(unnest([1, 2, 3]) AS INTEGER) AS k)", ("hop",))
def udtf_khop(spark, sf):
    """How many vertices a walk may reach within so many hops, if all had the out-degree of its start."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="hop int, budget long")
    class Fan:
        def eval(self, degree: int, hops: int):
            n = 1
            for k in range(hops):
                n *= degree
                yield k + 1, n

    spark.udtf.register("fan", Fan)
    graph(spark, sf, "hop").groupBy(F.col("src").alias("v")).agg(F.count("*").alias("n")).createOrReplaceTempView("degrees")
    return spark.sql("SELECT v, hop, budget FROM degrees, LATERAL fan(n, 3)")




@pair("sql_function_grid", "SELECT l_returnflag, CAST(floor(l_discount * 1024 + 0.5) AS BIGINT) AS q, count(*) AS n FROM lineitem GROUP BY 1, 2")
def sql_function_grid(spark, sf):
    """The grid as a SQL function, over the discounts of all order lines."""
    table(spark, sf, "lineitem").createOrReplaceTempView("lineitem")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION on_grid(x DOUBLE) RETURNS BIGINT RETURN CAST(floor(x * 1024 + 0.5D) AS BIGINT)")
    return spark.sql("SELECT l_returnflag, on_grid(l_discount) AS q, count(*) AS n FROM lineitem GROUP BY 1, 2")


same("sql_khop_recursive", "WITH RECURSIVE k AS (SELECT src AS root, dst AS v, 1 AS depth FROM reply UNION ALL SELECT k.root, r.dst, k.depth + 1 FROM k JOIN reply r ON r.src = k.v WHERE k.depth < 3) SELECT root, v, depth FROM k", graphs=("reply",))
same("sql_correlated_degree", "SELECT v, (SELECT count(*) FROM hop WHERE dst = v) AS n FROM emb0", graphs=("emb0", "hop"))
same("sql_exists_in_edge", "SELECT v FROM emb0 WHERE EXISTS (SELECT 1 FROM hop WHERE src = v AND etype = 'error') AND v IN (SELECT dst FROM hop)", graphs=("emb0", "hop"))
same("sql_scalar_subquery", "SELECT seq FROM hop WHERE w > (SELECT avg(CAST(w AS DOUBLE)) FROM hop)", graphs=("hop",))


@pair("sql_param", "SELECT count(*) AS n FROM hop WHERE etype = 'click'", ("hop",))
def sql_param(spark, sf):
    graph(spark, sf, "hop").createOrReplaceTempView("hop")
    return spark.sql("SELECT count(*) AS n FROM hop WHERE etype = :kind", args={"kind": "click"})


# A few star-schema queries, for regression.
_M = lambda x: f"CAST(floor(sum({x}) / 100 + 0.5) AS BIGINT)"
same("tpch_q1_like", f"SELECT l_returnflag, l_linestatus, count(*) AS n, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS q FROM lineitem GROUP BY l_returnflag, l_linestatus", ("lineitem",))
same("tpch_q3_like", "SELECT o_orderkey, count(*) AS n FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON l_orderkey = o_orderkey WHERE c_mktsegment = 'BUILDING' GROUP BY o_orderkey ORDER BY n DESC, o_orderkey LIMIT 10", ("customer", "orders", "lineitem"))
same("tpch_q5_like", "SELECT n_name, count(*) AS n FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON l_orderkey = o_orderkey JOIN supplier ON l_suppkey = s_suppkey AND s_nationkey = c_nationkey JOIN nation ON n_nationkey = s_nationkey GROUP BY n_name", ("customer", "orders", "lineitem", "supplier", "nation"))
same("tpch_q10_like", "SELECT c_custkey, count(*) AS returned FROM customer JOIN orders ON c_custkey = o_custkey JOIN lineitem ON l_orderkey = o_orderkey WHERE l_returnflag = 'R' GROUP BY c_custkey", ("customer", "orders", "lineitem"))
same("tpch_q18_like", "SELECT o_orderkey, CAST(sum(CAST(l_quantity AS BIGINT)) AS BIGINT) AS q FROM orders JOIN lineitem ON l_orderkey = o_orderkey GROUP BY o_orderkey HAVING sum(CAST(l_quantity AS BIGINT)) > 200", ("orders", "lineitem"))
