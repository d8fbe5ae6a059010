"""Graphs derived from the given tables, as DataFrames, and the CTEs DuckDB builds them with.

Edges: seq (total order), us (event time in microseconds), src, dst, etype, w. Vertex ids are disjoint
by type: type code * 2**40 + local id. The two vertex views emb0 and users hold grid features.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from deltamp.functions.grid import DIMS, SCALE, quantise

Tables = Callable[[str], DataFrame]
SHIFT = 2**40
CODES = {"user": 0, "topic": 1, "part": 2, "customer": 3, "order": 4, "supplier": 5, "nation": 6, "region": 7, "turn": 8, "host": 9}
DAY = 86_400_000_000


def vid(kind: str, local: Column) -> Column:
    return (F.lit(CODES[kind] * SHIFT) + local.cast("long")).cast("long")


def micros(ts: str) -> Column:
    """Microseconds since 1970 of a timestamp without time zone, whatever the session's zone."""
    return F.expr(f"timestampdiff(MICROSECOND, TIMESTAMP_NTZ '1970-01-01 00:00:00', cast({ts} as timestamp_ntz))")


def lag_in_buckets(rows: DataFrame, order: str, value: str, bucket: Column) -> DataFrame:
    """value of the row before in a global order, without a one-partition window.

    Rows are cut into buckets that follow the order; lag runs inside each, and a small table of each
    bucket's last value (one row a bucket) fills every bucket's first row.
    """
    cut = rows.withColumn("_b", bucket)
    inner = cut.withColumn("_p", F.lag(value).over(Window.partitionBy("_b").orderBy(order)))
    last = cut.groupBy("_b").agg(F.max_by(value, order).alias("_v"))
    carry = last.select("_b", F.lag("_v").over(Window.orderBy("_b")).alias("_c"))
    return inner.join(carry, "_b").withColumn("previous", F.coalesce("_p", "_c")).drop("_p", "_c", "_b")


def hop(t: Tables) -> DataFrame:
    e = t("events").select("event_id", micros("ts").alias("us"), "user_id", "event_type", "value")
    e = lag_in_buckets(e, "event_id", "user_id", F.floor(F.col("us") / (DAY // 4)))
    return e.where("previous <> user_id").select(F.col("event_id").alias("seq"), "us", F.col("previous").alias("src"), F.col("user_id").alias("dst"), F.col("event_type").alias("etype"), quantise(F.col("value")).alias("w"))


def topic(t: Tables) -> DataFrame:
    e = t("events").select("event_id", micros("ts").alias("us"), "user_id", "event_type", "value", F.get_json_object("props", "$.k").cast("long").alias("k"))
    there = e.select((F.col("event_id") * 2).alias("seq"), "us", F.col("user_id").alias("src"), vid("topic", F.col("k")).alias("dst"), F.col("event_type").alias("etype"), quantise(F.col("value")).alias("w"))
    back = e.select((F.col("event_id") * 2 + 1).alias("seq"), "us", vid("topic", F.col("k")).alias("src"), F.col("user_id").alias("dst"), F.col("event_type").alias("etype"), quantise(F.col("value")).alias("w"))
    return there.unionByName(back)


def copurchase(t: Tables) -> DataFrame:
    o = t("orders").select("o_orderkey", micros("o_orderdate").alias("us"))
    li = t("lineitem").select("l_orderkey", "l_linenumber", "l_partkey")
    a, b = li.alias("a"), li.alias("b")
    j = a.join(b, (F.col("a.l_orderkey") == F.col("b.l_orderkey")) & (F.col("a.l_linenumber") < F.col("b.l_linenumber")) & (F.col("a.l_partkey") != F.col("b.l_partkey")))
    j = j.join(o, F.col("a.l_orderkey") == o["o_orderkey"])
    seq = F.col("a.l_orderkey") * 64 + F.col("a.l_linenumber") * 8 + F.col("b.l_linenumber")
    return j.select(seq.cast("long").alias("seq"), "us", vid("part", F.col("a.l_partkey")).alias("src"), vid("part", F.col("b.l_partkey")).alias("dst"), F.lit("bought").alias("etype"), F.lit(1024).cast("long").alias("w"))


def trade(t: Tables) -> DataFrame:
    """Purchases, and deletions of the returned ones at their ship date (never before the order's). op: add or del."""
    j = t("lineitem").join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    n = F.row_number().over(Window.partitionBy("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey").orderBy("l_shipdate", "l_extendedprice", "l_quantity"))
    base = j.select("*", micros("o_orderdate").alias("ous"), F.greatest(micros("o_orderdate"), micros("l_shipdate")).alias("sus"), F.concat_ws("-", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", n).alias("eid"))
    ends = lambda op, us, seq: base.select("eid", us.alias("us"), seq.alias("seq"), vid("customer", F.col("o_custkey")).alias("src"), vid("part", F.col("l_partkey")).alias("dst"), F.col("l_returnflag").alias("etype"), F.lit(op).alias("op"))
    adds = ends("add", F.col("ous"), (F.col("l_orderkey") * 16 + F.col("l_linenumber") * 2).cast("long"))
    dels = ends("del", F.col("sus"), (F.col("l_orderkey") * 16 + F.col("l_linenumber") * 2 + 1).cast("long")).where("etype = 'R'")
    return adds.unionByName(dels)


def fk(t: Tables) -> DataFrame:
    def edge(df: DataFrame, a: str, ka: str, b: str, kb: str) -> DataFrame:
        return df.select(vid(a, F.col(ka)).alias("src"), vid(b, F.col(kb)).alias("dst"), F.lit(f"{a}-{b}").alias("etype"))

    parts = [
        edge(t("nation"), "region", "n_regionkey", "nation", "n_nationkey"), edge(t("customer"), "nation", "c_nationkey", "customer", "c_custkey"),
        edge(t("supplier"), "nation", "s_nationkey", "supplier", "s_suppkey"), edge(t("orders"), "customer", "o_custkey", "order", "o_orderkey"),
        edge(t("lineitem"), "order", "l_orderkey", "part", "l_partkey"), edge(t("lineitem"), "supplier", "l_suppkey", "part", "l_partkey"),
    ]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def reply(t: Tables) -> DataFrame:
    c = t("conversations").select("conv_id", "turn")
    key = lambda turn: vid("turn", F.col("conv_id") * 1000 + turn)
    n = F.lead("turn").over(Window.partitionBy("conv_id").orderBy("turn"))
    return c.withColumn("n", n).where("n is not null").select((F.col("conv_id") * 1000 + F.col("turn")).alias("seq"), key(F.col("turn")).alias("src"), key(F.col("n")).alias("dst"))


def link(t: Tables) -> DataFrame:
    """Page host to the target of each absolute or rooted href of the page."""
    p = t("pages").select("page_id", F.regexp_extract("url", r"://([^/?#]+)", 1).alias("src"), F.posexplode(F.regexp_extract_all("html", F.lit(r'href="([^"]+)"'), F.lit(1))).alias("pos", "dst"))
    return p.select((F.col("page_id") * 1000 + F.col("pos")).alias("seq"), "src", "dst")


def feat(t: Tables) -> DataFrame:
    """Feature updates: each event sets its user's scalar; the old value rides along."""
    w = Window.partitionBy("user_id").orderBy("event_id")
    return t("events").select(F.col("event_id").alias("seq"), micros("ts").alias("us"), F.col("user_id").alias("vid"), F.lag(quantise(F.col("value"))).over(w).alias("val_old"), quantise(F.col("value")).alias("val_new"))


def emb0(t: Tables) -> DataFrame:
    """Grid features of the users that occur in events."""
    users = t("events").select(F.col("user_id").alias("v")).distinct()
    return users.join(features(t), "v")


def features(t: Tables) -> DataFrame:
    """(v, label, x*): whole embeddings on the grid."""
    parts = [f"CAST(floor(CAST(embedding[{i}] AS DOUBLE) * {SCALE}D + 0.5D) AS BIGINT) AS x{i}" for i in range(DIMS)]
    return t("embeddings").selectExpr("vec_id AS v", "CAST(label AS INT) AS label", *parts)


def _spread(t: Tables, table: str, key: str, kind: str) -> DataFrame:
    n = t("embeddings").count()
    rows = t(table).select(vid(kind, F.col(key)).alias("p"), F.pmod(key, F.lit(n)).alias("v"))
    return rows.join(features(t), "v").drop("v").withColumnRenamed("p", "v").select("v", "label", *[f"x{i}" for i in range(DIMS)])


def goods(t: Tables) -> DataFrame:
    """Features of all parts: the embedding numbered by the key modulo the number of embeddings."""
    return _spread(t, "part", "p_partkey", "part")


def buyers(t: Tables) -> DataFrame:
    """Features of all customers, as those of parts."""
    return _spread(t, "customer", "c_custkey", "customer")


def hop_batches(t: Tables) -> DataFrame:
    """hop with b, the number of an edge's batch of 2000."""
    from deltamp.operators.window import fixed_count

    return fixed_count(hop(t), 2000).withColumnRenamed("due", "b")


BUILDERS: dict[str, Callable[[Tables], DataFrame]] = {f.__name__: f for f in (hop, topic, copurchase, trade, fk, reply, link, feat, emb0, goods, buyers, hop_batches)}

_Q = lambda x: f"CAST(floor(CAST({x} AS DOUBLE) * 1024 + 0.5) AS BIGINT)"
_V = lambda k, x: f"CAST({CODES[k] * SHIFT} + {x} AS BIGINT)"
_FK = [("nation", "region", "n_regionkey", "nation", "n_nationkey"), ("customer", "nation", "c_nationkey", "customer", "c_custkey"), ("supplier", "nation", "s_nationkey", "supplier", "s_suppkey"), ("orders", "customer", "o_custkey", "order", "o_orderkey"), ("lineitem", "order", "l_orderkey", "part", "l_partkey"), ("lineitem", "supplier", "l_suppkey", "part", "l_partkey")]
_TRADE = "SELECT {us} AS us, CAST(l_orderkey * 16 + l_linenumber * 2 + {k} AS BIGINT) AS seq, " + f"{_V('customer', 'o_custkey')} AS src, {_V('part', 'l_partkey')} AS dst, l_returnflag AS etype, '{{op}}' AS op, " + "l_orderkey || '-' || l_linenumber || '-' || l_partkey || '-' || l_suppkey || '-' || row_number() OVER (PARTITION BY l_orderkey, l_linenumber, l_partkey, l_suppkey ORDER BY l_shipdate, l_extendedprice, l_quantity) AS eid FROM lineitem JOIN orders ON l_orderkey = o_orderkey"
GRAPH_SQL = {
    "hop": f"SELECT event_id AS seq, epoch_us(ts) AS us, p AS src, user_id AS dst, event_type AS etype, {_Q('value')} AS w FROM (SELECT *, lag(user_id) OVER (ORDER BY event_id) AS p FROM events) WHERE p <> user_id",
    "topic": f"SELECT event_id * 2 AS seq, epoch_us(ts) AS us, user_id AS src, {_V('topic', chr(40) + 'props->>' + chr(39) + '$.k' + chr(39) + ')::BIGINT')} AS dst, event_type AS etype, {_Q('value')} AS w FROM events UNION ALL SELECT event_id * 2 + 1, epoch_us(ts), {_V('topic', chr(40) + 'props->>' + chr(39) + '$.k' + chr(39) + ')::BIGINT')}, user_id, event_type, {_Q('value')} FROM events",
    "copurchase": f"SELECT CAST(a.l_orderkey * 64 + a.l_linenumber * 8 + b.l_linenumber AS BIGINT) AS seq, epoch_us(o_orderdate) AS us, {_V('part', 'a.l_partkey')} AS src, {_V('part', 'b.l_partkey')} AS dst, 'bought' AS etype, CAST(1024 AS BIGINT) AS w FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_linenumber < b.l_linenumber AND a.l_partkey <> b.l_partkey JOIN orders ON o_orderkey = a.l_orderkey",
    "trade": f"{_TRADE.format(us='epoch_us(o_orderdate)', k=0, op='add')} UNION ALL SELECT * FROM ({_TRADE.format(us='greatest(epoch_us(o_orderdate), epoch_us(l_shipdate))', k=1, op='del')}) WHERE etype = 'R'",
    "fk": " UNION ALL ".join(f"SELECT {_V(a, ka)} AS src, {_V(b, kb)} AS dst, '{a}-{b}' AS etype FROM {t}" for t, a, ka, b, kb in _FK),
    "reply": f"SELECT conv_id * 1000 + turn AS seq, {_V('turn', 'conv_id * 1000 + turn')} AS src, {_V('turn', 'conv_id * 1000 + n')} AS dst FROM (SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS n FROM conversations) WHERE n IS NOT NULL",
    "link": "SELECT page_id * 1000 + i - 1 AS seq, src, h[i] AS dst FROM (SELECT page_id, src, h, unnest(range(1, len(h) + 1)) AS i FROM (SELECT page_id, regexp_extract(url, '://([^/?#]+)', 1) AS src, regexp_extract_all(html, 'href=\"([^\"]+)\"', 1) AS h FROM pages))",
    "feat": f"SELECT event_id AS seq, epoch_us(ts) AS us, user_id AS vid, lag({_Q('value')}) OVER (PARTITION BY user_id ORDER BY event_id) AS val_old, {_Q('value')} AS val_new FROM events",
    **{n: f"SELECT {_V(k, c)} AS v, CAST(label AS INTEGER) AS label, {', '.join(f'{_Q(f"embedding[{i + 1}]")} AS x{i}' for i in range(DIMS))} FROM {t} JOIN embeddings ON vec_id = {c} % (SELECT count(*) FROM embeddings)" for n, t, k, c in (("goods", "part", "part", "p_partkey"), ("buyers", "customer", "customer", "c_custkey"))},
    "emb0": f"SELECT vec_id AS v, CAST(label AS INTEGER) AS label, {', '.join(f'{_Q(f"embedding[{i + 1}]")} AS x{i}' for i in range(DIMS))} FROM embeddings WHERE vec_id IN (SELECT user_id FROM events)",
}
GRAPH_SQL["hop_batches"] = f"SELECT *, CAST(floor((row_number() OVER (ORDER BY seq) - 1) / 2000) AS BIGINT) AS b FROM ({GRAPH_SQL['hop']})"
