"""When delayed work falls due. Times are event-time microseconds.

Each function takes rows (key, us, seq) and returns them with due, the time at which the key's pending
work is evicted; rows of one key with one due collapse into one output.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from deltamp.sources.graphs import DAY

HOUR = DAY // 24
# The most rows of a broadcast: batches with their closing times, cells of a sketch over all its days.
BATCHES, CELLS = 1 << 18, 1 << 21


def per_event(rows: DataFrame) -> DataFrame:
    return rows.withColumn("due", F.col("us"))


def tumbling(rows: DataFrame, width: int) -> DataFrame:
    """Windows aligned to the epoch: due at the window's end."""
    return rows.withColumn("due", ((F.floor(F.col("us") / width) + 1) * width).cast("long"))


def tumbling_per_key(rows: DataFrame, width: int) -> DataFrame:
    """A key's window opens at its first pending arrival. The fold needs one key's times only."""
    times = rows.groupBy("key").agg(F.array_sort(F.collect_set("us")).alias("t"))
    start = F.struct(F.lit(-(2**62)).cast("long").alias("due"), F.array().cast("array<bigint>").alias("all"))
    step = lambda acc, u: F.when(u >= acc["due"], F.struct((u + width).alias("due"), F.concat(acc["all"], F.array(u)).alias("all"))).otherwise(acc)
    opened = times.select("key", F.explode(F.aggregate("t", start, step)["all"]).alias("open"))
    dues = Window.partitionBy("key").orderBy("us", F.col("is_open").desc()).rowsBetween(Window.unboundedPreceding, 0)
    both = rows.withColumn("is_open", F.lit(0)).unionByName(opened.select("key", F.col("open").alias("us"), F.lit(None).cast("long").alias("seq"), F.lit(1).alias("is_open")))
    return both.withColumn("due", F.last(F.when(F.col("is_open") == 1, F.col("us") + width), ignorenulls=True).over(dues)).where("is_open = 0").drop("is_open")


def sliding(rows: DataFrame, width: int, step: int) -> DataFrame:
    """A row is in width / step windows."""
    first = F.floor(F.col("us") / step).cast("long")
    return rows.withColumn("due", F.explode(F.transform(F.sequence(F.lit(0), F.lit(width // step - 1)), lambda k: (first - k) * step + width)))


def session(rows: DataFrame, gap: int, most: int | None = None) -> DataFrame:
    """Every arrival postpones; due is the last arrival plus gap. most caps a session's length by cutting it on a grid from its first arrival."""
    w = Window.partitionBy("key").orderBy("us", "seq")
    opened = rows.withColumn("_new", F.when(F.col("us") - F.lag("us").over(w) > gap, 1).otherwise(0))
    numbered = opened.withColumn("_s", F.sum("_new").over(w))
    if most:
        first = F.min("us").over(Window.partitionBy("key", "_s"))
        numbered = numbered.withColumn("_c", F.floor((F.col("us") - first) / most))
    else:
        numbered = numbered.withColumn("_c", F.lit(0))
    return numbered.withColumn("due", F.max("us").over(Window.partitionBy("key", "_s", "_c")) + gap).drop("_new", "_s", "_c")


def _averages(daily: DataFrame, *key: str) -> DataFrame:
    """(key.., day, average) of (key.., day, n): half the day's count and half the average before, one fold a key."""
    series = daily.groupBy(*key).agg(F.array_sort(F.collect_list(F.struct("day", F.col("n").cast("double").alias("n")))).alias("a"))
    start = F.struct(F.lit(-1.0).alias("f"), F.array().cast("array<struct<day:bigint,f:double>>").alias("all"))

    def step(acc, d):
        f = F.when(acc["f"] < 0, d["n"]).otherwise((acc["f"] + d["n"]) / 2)
        return F.struct(f.alias("f"), F.concat(acc["all"], F.array(F.struct(d["day"].alias("day"), f.alias("f")))).alias("all"))

    return series.select(*key, F.explode(F.aggregate("a", start, step)["all"]).alias("d")).select(*key, "d.day", F.col("d.f").alias("average"))


def adaptive_gaps(rows: DataFrame, k: int = 2, least: int = HOUR, most: int = 2 * DAY, sketch: CountMin | None = None) -> DataFrame:
    """(key, day, freq, gap): counts per day, averaged half and half over days, and the gap k days / frequency, clamped.

    With a sketch, the counts averaged are those of its cells, so storage is days times cells and not keys; a key
    reads the least of its cells' averages, which is never below its own where its cells are busy on its days only.
    """
    day = F.floor(F.col("us") / DAY).cast("long").alias("day")
    if sketch is None:
        series = _averages(rows.groupBy("key", day).agg(F.count("*").alias("n")), "key")
    else:
        seen = rows.groupBy("key", day).agg(F.count("*").alias("n"))
        cells = _averages(sketch.cells(seen, "key").groupBy("depth", "bucket", "day").agg(F.sum("n").alias("n")), "depth", "bucket")
        series = sketch.least(seen.select("key", "day"), cells, "average")
    gap = F.least(F.lit(most), F.greatest(F.lit(least), F.floor(k * F.lit(DAY).cast("double") / F.col("average")).cast("long")))
    return series.select("key", "day", F.floor(F.col("average") * 1e6 + 0.5).cast("long").alias("freq"), gap.alias("gap"))


def adaptive(rows: DataFrame, **options) -> DataFrame:
    """Sessions whose gap is the key's gap of the day before the arrival's (the least gap where there is none)."""
    days = F.map_from_entries(F.collect_list(F.struct((F.col("day") + 1).alias("day"), "gap")))
    gaps = adaptive_gaps(rows, **options).groupBy("key").agg(days.alias("_gaps"))  # by key, as the windows: rows move once
    gap = F.coalesce(F.col("_gaps")[F.floor(F.col("us") / DAY).cast("long")], F.lit(options.get("least", HOUR)))
    told = rows.join(gaps.hint("merge"), "key", "left").withColumn("gap", gap).drop("_gaps")
    w = Window.partitionBy("key").orderBy("us", "seq")
    numbered = told.withColumn("_new", F.when(F.col("us") > F.lag(F.col("us") + F.col("gap")).over(w), 1).otherwise(0)).withColumn("_s", F.sum("_new").over(w))
    last = F.max(F.struct("us", "gap")).over(Window.partitionBy("key", "_s"))
    return numbered.withColumn("due", last["us"] + last["gap"]).drop("_new", "_s", "gap")


def _piece(value: Column, cuts: list[int], first: int = 0) -> Column:
    """How many cuts are at or below the value, by halving."""
    if not cuts:
        return F.lit(first)
    m = len(cuts) // 2
    return F.when(value < cuts[m], _piece(value, cuts[:m], first)).otherwise(_piece(value, cuts[m + 1 :], first + m + 1))


def global_rank(rows: DataFrame, order: str, parts: int | None = None) -> DataFrame:
    """rank (from 0) in a total order without a one-partition window: ranges between quantiles, their sizes, local ranks.

    A row's range follows from its value alone, so sizes and ranks agree though the rows aren't stored for it.
    """
    parts = parts or max(16, rows.sparkSession.sparkContext.defaultParallelism, int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions")))
    cuts = rows.agg(F.percentile_approx(order, [k / parts for k in range(1, parts)])).first()[0] if parts > 1 else None
    cut = rows.withColumn("_p", F.when(F.col(order).isNull(), 0).otherwise(_piece(F.col(order), sorted(set(cuts or [])))))
    sizes = cut.groupBy("_p").agg(F.count("*").alias("_n"))
    before = sizes.select("_p", F.coalesce(F.sum("_n").over(Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("_b"))
    local = F.row_number().over(Window.partitionBy("_p").orderBy(order))
    return cut.withColumn("_l", local).join(F.broadcast(before), "_p").withColumn("rank", (F.col("_b") + F.col("_l") - 1).cast("long")).drop("_p", "_l", "_b")  # parts rows


def fixed_count(rows: DataFrame, size: int) -> DataFrame:
    """Batches of so many rows in seq order; due is the batch's number."""
    return global_rank(rows, "seq").withColumn("due", F.floor(F.col("rank") / size).cast("long")).drop("rank")


def count_closes(edges: DataFrame, size: int) -> DataFrame:
    """(batch, close): the time of the last edge of each batch of so many edges; one row a batch."""
    return fixed_count(edges, size).groupBy(F.col("due").alias("batch")).agg(F.max("us").alias("close"))


def by_count(edges: DataFrame, size: int):
    """The policy that holds edges back until their batch of so many is complete. Its rows are those of edges."""

    def policy(rows: DataFrame) -> DataFrame:
        ranked = fixed_count(rows, size).withColumnRenamed("due", "batch")
        closes = ranked.groupBy("batch").agg(F.max("us").alias("close"))
        if rows.count() <= size * BATCHES:
            closes = F.broadcast(closes)
        return ranked.join(closes, "batch").withColumn("due", F.col("close")).drop("batch", "close")

    return policy


def outputs(due: DataFrame) -> DataFrame:
    """The outputs that remain: per key and due, how many rows it stands for and the last row's time."""
    return due.groupBy("key", "due").agg(F.count("*").alias("n"), F.max("us").alias("last_us"))


def coalesced(due: DataFrame, grid: int) -> DataFrame:
    """Timers moved up to the next point of a grid."""
    return due.withColumn("due", (F.ceil(F.col("due") / grid) * grid).cast("long"))


def gather_partials(edges: DataFrame, parts: int, width: int) -> DataFrame:
    """One partial aggregate per part, destination and window, with its count."""
    lpart = F.pmod(F.col("src") * 31 + F.col("dst") * 17 + F.col("seq") * 7, F.lit(parts)).cast("int")
    due = ((F.floor(F.col("us") / width) + 1) * width).cast("long")
    return edges.groupBy(lpart.alias("lpart"), "dst", due.alias("due")).agg(F.count("*").alias("n"), F.countDistinct("src").alias("sources"))


class CountMin:
    """A count-min sketch as a table (depth, bucket, weight): mergeable by sum, and it decays by a factor."""

    def __init__(self, depth: int = 4, width: int = 4096):
        self.depth, self.width = depth, width

    def cells(self, rows: DataFrame, key: str) -> DataFrame:
        cells = F.array(*[F.struct(F.lit(d).alias("depth"), F.pmod(F.xxhash64(F.lit(d), F.col(key)), F.lit(self.width)).cast("int").alias("bucket")) for d in range(self.depth)])
        return rows.withColumn("_c", F.explode(cells)).select("*", "_c.depth", "_c.bucket").drop("_c")

    def update(self, rows: DataFrame, key: str = "key") -> DataFrame:
        return self.cells(rows.select(key), key).groupBy("depth", "bucket").agg(F.count("*").cast("double").alias("weight"))

    def estimate(self, sketch: DataFrame, keys: DataFrame, key: str = "key") -> DataFrame:
        """depth * width rows at most: a bounded broadcast."""
        return self.cells(keys.select(key).distinct(), key).join(F.broadcast(sketch), ["depth", "bucket"], "left").groupBy(key).agg(F.min(F.coalesce("weight", F.lit(0.0))).alias("estimate"))

    def least(self, seen: DataFrame, cells: DataFrame, value: str) -> DataFrame:
        """seen (key, day) with the least value of the key's cells (depth, bucket, day, value), one row of all cells a day: keys aren't multiplied."""
        n = self.depth * self.width
        blank = cells.select("day").distinct().select("day", F.explode(F.sequence(F.lit(0), F.lit(n - 1))).alias("c"), F.lit(None).cast("double").alias(value))
        filled = cells.select("day", (F.col("depth") * self.width + F.col("bucket")).alias("c"), value).unionByName(blank).groupBy("day", "c").agg(F.max(value).alias(value))
        days = filled.groupBy("day").agg(F.transform(F.array_sort(F.collect_list(F.struct("c", value))), lambda x: x[value]).alias("_m"))
        if cells.select("day").distinct().count() * n <= CELLS:
            days = F.broadcast(days)
        mine = [F.col("_m")[F.pmod(F.xxhash64(F.lit(d), "key"), F.lit(self.width)).cast("int") + d * self.width] for d in range(self.depth)]
        return seen.join(days, "day").select("key", "day", (F.least(*mine) if len(mine) > 1 else mine[0]).alias(value))

    def average(self, old: DataFrame, new: DataFrame, alpha: float = 0.5) -> DataFrame:
        scaled = old.withColumn("weight", F.col("weight") * (1 - alpha)).unionByName(new.withColumn("weight", F.col("weight") * alpha))
        return scaled.groupBy("depth", "bucket").agg(F.sum("weight").alias("weight"))


def reference_sessions(times: list[int], gap: int) -> list[int]:
    """Due times of one key by direct simulation, for tests."""
    out: list[int] = []
    for t in sorted(times):
        if out and t <= out[-1]:
            out[-1] = t + gap
        else:
            out.append(t + gap)
    return out


