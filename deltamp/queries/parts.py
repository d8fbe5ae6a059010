"""Partitioners, masters, placement and their measures."""

from __future__ import annotations

from pyspark.sql import functions as F

from deltamp.operators import partition as part
from deltamp.registry import graph, pair, portable

P = 16
_L = f"CAST((src * 31 + dst * 17 + seq * 7) % {P} AS INTEGER)"
PLACED = f"(SELECT seq, us, src, dst, {_L} AS lpart FROM topic)"
ENDS = f"(SELECT src AS v, lpart, seq FROM {PLACED} UNION ALL SELECT dst, lpart, seq FROM {PLACED})"


def placed(spark, sf):
    return part.random_arithmetic(graph(spark, sf, "topic"), P)


@pair("part_random_arith", f"SELECT seq, {_L} AS lpart FROM topic", ("topic",))
def part_random_arith(spark, sf):
    return placed(spark, sf).select("seq", "lpart")


def _links(spark, sf):
    """The link graph with ids for its strings."""
    e = graph(spark, sf, "link")
    key = lambda c: F.xxhash64(c) % (2**40)
    return e.select("seq", key("src").alias("src"), key("dst").alias("dst"))


def _hop(spark, sf):
    return graph(spark, sf, "hop").select("seq", "src", "dst")


@pair("part_hdrf")
def part_hdrf(spark, sf):
    return part.hdrf(_hop(spark, sf), P, chunk=20_000)


@pair("part_cluster")
def part_cluster(spark, sf):
    return part.cluster_affinity(_links(spark, sf), P)


@pair("part_multilevel")
def part_multilevel(spark, sf):
    return part.multilevel(_links(spark, sf), P)


@pair("part_vertex_greedy")
def part_vertex_greedy(spark, sf):
    return part.vertex_greedy(_links(spark, sf), P)


@pair("part_conflict_free_rounds")
def part_conflict_free_rounds(spark, sf):
    return part.lockstep_rounds(_hop(spark, sf))


portable("part_first_round", "SELECT e.seq FROM hop e JOIN (SELECT v, min(seq) AS low FROM (SELECT src AS v, seq FROM hop UNION ALL SELECT dst, seq FROM hop) GROUP BY v) a ON a.v = e.src JOIN (SELECT v, min(seq) AS low FROM (SELECT src AS v, seq FROM hop UNION ALL SELECT dst, seq FROM hop) GROUP BY v) b ON b.v = e.dst WHERE e.seq = a.low AND e.seq = b.low", ("hop",))
_HOME = f"(SELECT v, min_by(lpart, seq * {P} + lpart) AS home FROM {ENDS} GROUP BY v)"


@pair("part_masters", f"SELECT v, home AS lpart FROM {_HOME}", ("topic",))
def part_masters(spark, sf):
    return part.masters(placed(spark, sf)).where("is_master").select("v", "lpart")


@pair("part_replicas", f"SELECT e.v, count(DISTINCT e.lpart) - 1 AS replicas FROM {ENDS} e GROUP BY e.v", ("topic",))
def part_replicas(spark, sf):
    return part.masters(placed(spark, sf)).groupBy("v").agg((F.count("*") - 1).alias("replicas"))


_SIZES = f"(SELECT lpart, count(*) AS edges FROM {PLACED} GROUP BY lpart)"
_PAR = f"(SELECT lpart AS l, edges, p FROM {_SIZES}, (SELECT unnest([4, 5, 16]) AS p))"


def _sizes(spark, sf):
    """The logical parts that the graph's edges lie in, with their edges."""
    return placed(spark, sf).groupBy("lpart").agg(F.count("*").alias("edges"))


def _grid(spark, sf):
    return _sizes(spark, sf).select("lpart", "edges", F.explode(F.array(F.lit(4), F.lit(5), F.lit(16))).alias("par"))


@pair("place_physical", f"SELECT l AS lpart, CAST(p AS INTEGER) AS par, CAST(floor(l % 16 * p / 16.0) AS INTEGER) AS ppart, edges FROM {_PAR}", ("topic",))
def place_physical(spark, sf):
    return _grid(spark, sf).select("lpart", "par", F.floor(F.pmod("lpart", F.lit(16)) * F.col("par") / 16).cast("int").alias("ppart"), "edges")


@pair("place_coverage", f"SELECT par, count(*) AS used, min(n) AS least, max(n) AS most, min(e) AS least_edges, max(e) AS most_edges FROM (SELECT CAST(p AS INTEGER) AS par, floor(l * p / 16.0) AS pp, count(*) AS n, CAST(sum(edges) AS BIGINT) AS e FROM {_PAR} GROUP BY 1, 2) GROUP BY par", ("topic",))
def place_coverage(spark, sf):
    """Physical parts that get edges, and the logical parts and edges that one of them gets."""
    counts = place_physical(spark, sf).groupBy("par", "ppart").agg(F.count("*").alias("n"), F.sum("edges").alias("e"))
    return counts.groupBy("par").agg(F.count("*").alias("used"), F.min("n").alias("least"), F.max("n").alias("most"), F.min("e").alias("least_edges"), F.max("e").alias("most_edges"))


@pair("place_hashed_idle")
def place_hashed_idle(spark, sf):
    """Operators that get no edge when part ids are hashed, and the edges of the fullest."""
    at = F.floor(F.pmod(F.hash("lpart"), F.lit(16)) * F.col("par") / 16)
    used = _grid(spark, sf).groupBy("par", at.alias("ppart")).agg(F.sum("edges").alias("e")).groupBy("par").agg(F.count("*").alias("used"), F.max("e").alias("most_edges"))
    return used.select("par", "used", (F.col("par") - F.col("used")).alias("idle"), "most_edges")


@pair("place_moves", f"SELECT lpart, CAST(floor(lpart * 4 / 16.0) AS INTEGER) AS old_part, CAST(floor(lpart * 5 / 16.0) AS INTEGER) AS new_part, edges FROM {_SIZES} WHERE floor(lpart * 4 / 16.0) <> floor(lpart * 5 / 16.0)", ("topic",))
def place_moves(spark, sf):
    """Logical parts that move from four operators to five, with the edges that move along."""
    return _sizes(spark, sf).select("lpart", part.physical(F.col("lpart"), 4, 16).alias("old_part"), part.physical(F.col("lpart"), 5, 16).alias("new_part"), "edges").where("old_part <> new_part")


_LAMBDA = "SELECT CAST(g AS INTEGER) AS growth, CAST(i AS INTEGER) AS layer, CAST(least(2 * power(g, i - 1), 64) AS INTEGER) AS operators, 2 * power(g, i - 1) > 64 AS capped FROM (SELECT unnest(range(1, 9)) AS g), (SELECT unnest(range(1, 4)) AS i)"


@pair("explosion_parallelism", f"SELECT growth, layer, operators, capped, count(*) AS used, max(n) AS most FROM (SELECT growth, layer, operators, capped, dst % operators AS q, count(*) AS n FROM hop, ({_LAMBDA}) GROUP BY growth, layer, operators, capped, dst % operators) GROUP BY growth, layer, operators, capped", ("hop",))
def explosion_parallelism(spark, sf):
    """Operators of each layer by growth, how many of them the graph's destinations reach, and the edges of the fullest."""
    rows = [(g, *r) for g in range(1, 9) for r in part.layer_parallelism(2, g, 3, 64)]
    names = ("growth", "layer", "operators", "capped")
    plans = F.array(*[F.struct(*[F.lit(x).alias(k) for k, x in zip(names, r)]) for r in rows])
    loads = graph(spark, sf, "hop").groupBy("dst").agg(F.count("*").alias("m")).select("dst", "m", F.explode(plans).alias("p")).select("dst", "m", "p.*")
    loads = loads.groupBy(*names, F.pmod("dst", "operators").alias("q")).agg(F.sum("m").alias("n"))
    return loads.groupBy(*names).agg(F.count("*").alias("used"), F.max("n").alias("most"))


portable("explosion_load", "SELECT layer, ppart, count(*) AS units FROM (SELECT 1 AS layer, dst % 2 AS ppart FROM topic UNION ALL SELECT 2, dst % 6 FROM topic) GROUP BY layer, ppart", ("topic",))


@pair("sync_messages", f"SELECT home, count(*) AS messages FROM (SELECT DISTINCT v, lpart FROM {ENDS}) e JOIN {_HOME} h USING (v) WHERE lpart <> home GROUP BY home", ("topic",))
def sync_messages(spark, sf):
    """A changed master feature goes to the parts with a replica only."""
    m = part.masters(placed(spark, sf))
    home = m.where("is_master").select("v", F.col("lpart").alias("home"))
    return m.where("NOT is_master").join(home, "v").groupBy("home").agg(F.count("*").alias("messages"))


@pair("selective_vs_full_broadcast", f"SELECT CAST(sum(n - 1) AS BIGINT) AS selective, CAST(sum({P - 1}) AS BIGINT) AS everywhere FROM (SELECT v, count(DISTINCT lpart) AS n FROM {ENDS} GROUP BY v)", ("topic",))
def selective_vs_full_broadcast(spark, sf):
    m = part.masters(placed(spark, sf)).groupBy("v").agg(F.count("*").alias("n"))
    return m.agg(F.sum(F.col("n") - 1).alias("selective"), F.sum(F.lit(P - 1)).cast("long").alias("everywhere"))


@pair("replication_factor", f"SELECT CAST(floor(avg(CAST(n AS DOUBLE)) * 1e6 + 0.5) AS BIGINT) AS factor FROM (SELECT v, count(DISTINCT lpart) AS n FROM {ENDS} GROUP BY v)", ("topic",))
def replication_factor(spark, sf):
    m = part.masters(placed(spark, sf)).groupBy("v").agg(F.count("*").alias("n"))
    return m.agg(F.floor(F.avg("n") * 1e6 + 0.5).cast("long").alias("factor"))


@pair("edge_cut", f"SELECT count(*) AS cut FROM topic JOIN {_HOME} a ON src = a.v JOIN {_HOME} b ON dst = b.v WHERE a.home <> b.home", ("topic",))
def edge_cut(spark, sf):
    e = placed(spark, sf)
    home = part.masters(e).where("is_master")
    a, b = home.select(F.col("v").alias("src"), F.col("lpart").alias("pa")), home.select(F.col("v").alias("dst"), F.col("lpart").alias("pb"))
    return e.join(a, "src").join(b, "dst").where("pa <> pb").agg(F.count("*").alias("cut"))


portable("part_balance", f"SELECT CAST(floor(max(n) / avg(n) * 1e6 + 0.5) AS BIGINT) AS balance, max(n) AS most, min(n) AS least FROM (SELECT lpart, count(*) AS n FROM {PLACED} GROUP BY lpart)", ("topic",))


def quality(edges):
    """(factor, balance) of a placement, in millionths."""
    ends = edges.select(F.col("src").alias("v"), "lpart").union(edges.select("dst", "lpart"))
    f = ends.groupBy("v").agg(F.countDistinct("lpart").alias("n")).agg(F.floor(F.avg("n") * 1e6 + 0.5).cast("long").alias("factor"))
    b = edges.groupBy("lpart").agg(F.count("*").alias("n")).agg(F.floor(F.max("n") / F.avg("n") * 1e6 + 0.5).cast("long").alias("balance"))
    return f.crossJoin(b)  # one row each


@pair("wl_w6_greedy")
def wl_w6_greedy(spark, sf):
    """Partitioners side by side on the link graph: replication and balance."""
    e = _links(spark, sf)
    made = {"random": part.random_hash(e, P), "greedy": part.hdrf(e, P, chunk=100_000), "cluster": part.cluster_affinity(e, P), "multilevel": part.multilevel(e, P)}
    out = None
    for name, m in made.items():
        row = quality(m).select(F.lit(name).alias("partitioner"), "factor", "balance")
        out = row if out is None else out.union(row)
    return out
