"""Streaming vertex-cut partitioning, masters and replicas, and the placement of logical parts.

Greedy algorithms read edges in seq order in chunks. A chunk's edges meet the state at its start
(degrees and the parts that hold each endpoint, by joins), workers score their share in order with local
updates, and the chunk's results merge by sums and unions. One worker and one chunk is the sequential
algorithm; quality falls with staleness, which is the chunk.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from deltamp.durable import settle


def random_arithmetic(edges: DataFrame, parts: int = 16) -> DataFrame:
    return edges.withColumn("lpart", F.pmod(F.col("src") * 31 + F.col("dst") * 17 + F.col("seq") * 7, F.lit(parts)).cast("int"))


def random_hash(edges: DataFrame, parts: int = 16, seed: int = 0) -> DataFrame:
    return edges.withColumn("lpart", F.pmod(F.xxhash64(F.lit(seed), "seq"), F.lit(parts)).cast("int"))


def _score(mask_a: int, mask_b: int, share_a: float, load: list[int], balance: float, eps: float, cap: float = math.inf) -> int:
    """The part with the most: endpoints it already holds, the rarer one weighing more, plus room."""
    low, high = min(load), max(load)
    best, pick = -math.inf, 0
    for p, n in enumerate(load):
        if n >= cap and low < cap:
            continue
        s = balance * (high - n) / (eps + high - low)
        if mask_a >> p & 1:
            s += 2 - share_a
        if mask_b >> p & 1:
            s += 1 + share_a
        if s > best:
            best, pick = s, p
    return pick


def hdrf_sequential(rows: list[tuple], parts: int = 16, balance: float = 2.0, eps: float = 1.0) -> list[int]:
    """Parts of (src, dst) rows in order, degrees and load counted as they come."""
    degree: dict = {}
    masks: dict = {}
    load = [0] * parts
    out = []
    for a, b in rows:
        degree[a], degree[b] = degree.get(a, 0) + 1, degree.get(b, 0) + 1
        p = _score(masks.get(a, 0), masks.get(b, 0), degree[a] / (degree[a] + degree[b]), load, balance, eps)
        load[p] += 1
        masks[a], masks[b] = masks.get(a, 0) | 1 << p, masks.get(b, 0) | 1 << p
        out.append(p)
    return out


ROUND = 1 << 19  # edges that one worker takes in a round; a round costs the driver some jobs


def hdrf(edges: DataFrame, parts: int = 16, balance: float = 2.0, eps: float = 1.0, chunk: int = 1 << 20, workers: int = 1) -> DataFrame:
    """(seq, src, dst, lpart). edges: seq, src, dst (longs). parts up to 62, as masks are longs.

    One worker has no staleness, so its chunks can be joined into rounds of ROUND edges without changing a part.
    """
    from deltamp.operators.window import global_rank

    if workers == 1:
        chunk *= max(1, ROUND // chunk)

    ranked = settle(global_rank(edges.select("seq", "src", "dst"), "seq"))
    total = ranked.count()
    spark = edges.sparkSession
    state = spark.createDataFrame([], "v long, degree long, mask long")
    load = [0] * parts
    done = None
    for at in range(0, max(1, total), chunk):
        part = ranked.where((F.col("rank") >= at) & (F.col("rank") < at + chunk))
        a, b = state.select(F.col("v").alias("src"), F.col("degree").alias("da"), F.col("mask").alias("ma")), state.select(F.col("v").alias("dst"), F.col("degree").alias("db"), F.col("mask").alias("mb"))
        met = part.join(a, "src", "left").join(b, "dst", "left").select("seq", "src", "dst", "da", "ma", "db", "mb", F.floor((F.col("rank") - at) * workers / chunk).cast("int").alias("worker"))
        base = tuple(load)

        def score(pdf: pd.DataFrame) -> pd.DataFrame:
            pdf = pdf.sort_values("seq")
            degree: dict = {}
            masks: dict = {}
            load, out = list(base), []
            clean = lambda x: 0 if x != x or x is None else int(x)
            for r in pdf.itertuples(index=False):
                for v, d, m in ((r.src, r.da, r.ma), (r.dst, r.db, r.mb)):
                    if v not in degree:
                        degree[v], masks[v] = clean(d), clean(m)
                degree[r.src] += 1
                degree[r.dst] += 1
                p = _score(masks[r.src], masks[r.dst], degree[r.src] / (degree[r.src] + degree[r.dst]), load, balance, eps)
                load[p] += 1
                masks[r.src] |= 1 << p
                masks[r.dst] |= 1 << p
                out.append(p)
            return pd.DataFrame({"seq": pdf["seq"], "src": pdf["src"], "dst": pdf["dst"], "lpart": out})

        placed = settle(met.groupBy("worker").applyInPandas(score, "seq long, src long, dst long, lpart int"))
        for r in placed.groupBy("lpart").count().collect():
            load[r["lpart"]] += r["count"]
        ends = placed.select(F.col("src").alias("v"), "lpart").union(placed.select(F.col("dst"), "lpart"))
        news = ends.groupBy("v").agg(F.count("*").alias("degree"), F.bit_or(F.expr("shiftleft(1L, lpart)")).alias("mask"))
        state = settle(state.union(news).groupBy("v").agg(F.sum("degree").alias("degree"), F.bit_or("mask").alias("mask")))
        done = placed if done is None else done.union(placed)
    return done


def cluster_affinity(edges: DataFrame, parts: int = 16, rounds: int = 3, slack: float = 1.1) -> DataFrame:
    """Our own reading of a clustering vertex-cut: capped label spreading, clusters packed onto parts, edges
    follow the endpoint of lower degree."""
    both = settle(edges.select(F.col("src").alias("a"), F.col("dst").alias("b")).union(edges.select("dst", "src")))
    labels = settle(both.select(F.col("a").alias("v")).distinct().withColumn("label", F.col("v")))
    for _ in range(rounds):
        votes = both.join(labels, both["b"] == labels["v"]).groupBy("a", "label").count()
        best = votes.groupBy("a").agg(F.max_by("label", F.struct("count", F.xxhash64("label"))).alias("label"))
        labels = settle(best.select(F.col("a").alias("v"), "label"))
    degree = both.groupBy(F.col("a").alias("v")).agg(F.count("*").alias("d"))
    size = labels.join(degree, "v").groupBy("label").agg(F.sum("d").alias("d"))
    total = size.agg(F.sum("d")).first()[0] or 0
    cap = slack * total / parts
    # Clusters over the cap are cut into several; each piece goes to the part of its hash.
    piece = size.select("label", F.greatest(F.lit(1), F.ceil(F.col("d") / cap)).cast("int").alias("pieces"))
    home = labels.join(piece, "label").join(degree, "v").select("v", "d", F.pmod(F.xxhash64("label", F.pmod(F.xxhash64("v"), F.col("pieces"))), F.lit(parts)).cast("int").alias("lpart"))
    h1, h2 = home.select(F.col("v").alias("src"), F.col("d").alias("d1"), F.col("lpart").alias("p1")), home.select(F.col("v").alias("dst"), F.col("d").alias("d2"), F.col("lpart").alias("p2"))
    return edges.join(h1, "src").join(h2, "dst").select("seq", "src", "dst", F.when(F.col("d1") <= F.col("d2"), F.col("p1")).otherwise(F.col("p2")).alias("lpart"))


def multilevel(edges: DataFrame, parts: int = 16, levels: int = 4, imbalance: float = 1.05, most_coarse: int = 200_000) -> DataFrame:
    """Offline: coarsen by heavy matching, pack the coarse graph greedily, project back; edges follow src."""
    weights = edges.where("src <> dst").select(F.least("src", "dst").alias("a"), F.greatest("src", "dst").alias("b")).groupBy("a", "b").agg(F.count("*").alias("w"))
    weights = settle(weights)
    home = settle(edges.select(F.col("src").alias("v")).union(edges.select("dst")).groupBy("v").agg(F.count("*").alias("d")).withColumn("c", F.col("v")))
    for _ in range(levels):
        both = weights.union(weights.select("b", "a", "w"))
        pick = both.groupBy("a").agg(F.max_by("b", F.struct("w", F.xxhash64("a", "b").bitwiseXOR(F.xxhash64("b", "a")))).alias("b"))
        p, q = pick.alias("p"), pick.alias("q")
        pairs = p.join(q, (F.col("p.a") == F.col("q.b")) & (F.col("p.b") == F.col("q.a")) & (F.col("p.a") < F.col("p.b"))).select(F.col("p.a").alias("into"), F.col("p.b").alias("c"))
        home = settle(home.join(pairs, "c", "left").select("v", "d", F.coalesce("into", "c").alias("c")))
        x, y = pairs.select(F.col("c").alias("a"), F.col("into").alias("ia")), pairs.select(F.col("c").alias("b"), F.col("into").alias("ib"))
        moved = weights.join(x, "a", "left").join(y, "b", "left").select(F.coalesce("ia", "a").alias("a"), F.coalesce("ib", "b").alias("b"), "w").where("a <> b")
        weights = settle(moved.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b"), "w").groupBy("a", "b").agg(F.sum("w").alias("w")))
    sizes = home.groupBy("c").agg(F.sum("d").alias("d")).limit(most_coarse + 1).collect()
    if len(sizes) > most_coarse:
        raise ValueError("coarse graph too large for the driver: raise levels")
    near: dict = {}
    for r in weights.collect() if len(sizes) <= most_coarse else []:
        near.setdefault(r["a"], []).append((r["b"], r["w"]))
        near.setdefault(r["b"], []).append((r["a"], r["w"]))
    cap = imbalance * sum(r["d"] for r in sizes) / parts
    load, part_of = [0.0] * parts, {}
    for r in sorted(sizes, key=lambda r: (-r["d"], r["c"])):
        pull = [0.0] * parts
        for other, w in near.get(r["c"], []):
            if other in part_of:
                pull[part_of[other]] += w
        p = max(range(parts), key=lambda k: (load[k] + r["d"] <= cap, pull[k] * max(0.0, 1 - load[k] / cap), -load[k]))
        part_of[r["c"]] = p
        load[p] += r["d"]
    coarse = edges.sparkSession.createDataFrame(list(part_of.items()), "c long, lpart int")
    placed = home.join(coarse, "c").select(F.col("v").alias("src"), "lpart")
    return edges.join(placed, "src").select("seq", "src", "dst", "lpart")


def vertex_greedy(edges: DataFrame, parts: int = 16) -> DataFrame:
    """Vertices in id order join the part with most placed neighbours, less a size penalty: (v, lpart)."""
    rows = edges.select("src", "dst").distinct().orderBy("src", "dst")

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        near: dict = {}
        for b in batches:
            for s, d in zip(b["src"], b["dst"]):
                near.setdefault(int(s), set()).add(int(d))
                near.setdefault(int(d), set()).add(int(s))
        cap = max(1.0, 1.05 * len(near) / parts)
        load, home = [0] * parts, {}
        for v in sorted(near):
            pull = [0] * parts
            for u in near[v]:
                if u in home:
                    pull[home[u]] += 1
            home[v] = max(range(parts), key=lambda k: ((1 + pull[k]) * (1 - load[k] / cap), -k))
            load[home[v]] += 1
        yield pd.DataFrame({"v": list(home), "lpart": list(home.values())})

    return rows.coalesce(1).mapInPandas(run, "v long, lpart int")


def masters(placed: DataFrame) -> DataFrame:
    """(v, lpart, is_master): the part of a vertex' first edge is its master, other parts hold replicas."""
    ends = placed.select(F.col("src").alias("v"), "lpart", "seq").union(placed.select("dst", "lpart", "seq"))
    first = ends.groupBy("v", "lpart").agg(F.min("seq").alias("seq"))
    home = ends.groupBy("v").agg(F.min_by("lpart", F.struct("seq", "lpart")).alias("home"))
    return first.join(home, "v").select("v", "lpart", (F.col("lpart") == F.col("home")).alias("is_master"))


def physical(lpart: Column, parallelism: int, most: int) -> Column:
    """Logical to physical part: key group by modulo, then proportional division. Every operator gets work."""
    return F.floor(F.pmod(lpart, F.lit(most)) * parallelism / most).cast("int")


def layer_parallelism(p: int, growth: int, layers: int, cap: int) -> list[tuple[int, int, bool]]:
    """(layer, operators, was it capped) under the explosion factor."""
    return [(i + 1, min(p * growth**i, cap), p * growth**i > cap) for i in range(layers)]


def lockstep_rounds(edges: DataFrame, chunk: int = 1 << 20) -> DataFrame:
    """(seq, round): an edge goes when it is the first left at both its endpoints; seq is unique.

    That is one round after the later of the edges before it at either endpoint. Edges are read in seq order,
    a chunk at a time, with the next free round of each endpoint joined in, so every edge gets its round
    however many there are.
    """
    from deltamp.operators.window import global_rank

    ranked = settle(global_rank(edges.select("seq", "src", "dst"), "seq"))
    total = ranked.count()
    state = edges.sparkSession.createDataFrame([], "v long, free long")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("seq")
        free: dict = {}
        out = []
        for r in pdf.itertuples(index=False):
            k = max(free.get(r.src, r.fa), free.get(r.dst, r.fb))
            free[r.src] = free[r.dst] = k + 1
            out.append(k)
        return pd.DataFrame({"seq": pdf["seq"], "src": pdf["src"], "dst": pdf["dst"], "round": out})

    done = None
    for at in range(0, max(1, total), chunk):
        part = ranked.where((F.col("rank") >= at) & (F.col("rank") < at + chunk))
        a, b = state.select(F.col("v").alias("src"), F.col("free").alias("fa")), state.select(F.col("v").alias("dst"), F.col("free").alias("fb"))
        met = part.join(a, "src", "left").join(b, "dst", "left").select("seq", "src", "dst", F.coalesce("fa", F.lit(0)).alias("fa"), F.coalesce("fb", F.lit(0)).alias("fb"), F.lit(0).alias("worker"))
        placed = settle(met.groupBy("worker").applyInPandas(run, "seq long, src long, dst long, round int"))
        ends = placed.select(F.col("src").alias("v"), (F.col("round") + 1).cast("long").alias("free")).union(placed.select("dst", (F.col("round") + 1).cast("long")))
        state = settle(state.union(ends).groupBy("v").agg(F.max("free").alias("free")))
        done = placed if done is None else done.union(placed)
    return done.select("seq", "src", "dst", "round")
