"""Quality rules: fixed text measures and a hashed n-gram likelihood ratio, in DataFrame expressions only.

Words and word pairs are hashed into buckets, whose number grows with the text (one for every BUCKET_BYTES of it,
between LEAST_BUCKETS and MOST_BUCKETS, a power of two). One pass counts the buckets over all documents (the raw
corpus) and over the trusted ones (all that are labelled good). A document's score is the mean over its words and
pairs of log(p_trusted / p_raw) in thousandths, both counts on the trusted corpus' scale with PRIOR added; at or
above LEAST_SCORE it is kept, with no chance involved. The weights are one array of integers, a literal of
MOST_BUCKETS entries at most, made by one aggregation and read by the driver as one row.

No text moves but those that may be trusted: the trusted ids make a bitmap of BITS_EACH bits an id (MOST_BITS at
most), a literal too; texts whose id hits a set bit are joined with the ids, which settles it. Where the bitmap is
full, or the id types differ, more texts move and the result is the same. Counts are combined in two tasks a core, or
one for TASK_BYTES of text if that is more, so that what they shuffle follows the buckets and stays small beside it.

Defined results: null text has no words and fails the base rule; a text without words scores 0;
without trusted rows (or an empty table) all weights are 0; null ids and repeated rows are judged like
any other row; columns of the input other than the two named pass through judge() unchanged, the verdicts
being named verdict_column(): _q, with more underscores in front where the input has such a column.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from deltamp.llm.common import WORD_CLASS

LEAST_BUCKETS, MOST_BUCKETS, BUCKET_BYTES = 1 << 15, 1 << 20, 4096
BITS_EACH, MOST_BITS, TASK_BYTES = 32, 1 << 24, 1 << 28
PRIOR = 20
LEAST_SCORE = -100.0
_BREAKS = r"[\x20\x09-\x0D]+"


def _upto(n: Column, make) -> Column:
    """make(i) for i from 0 to n - 1."""
    return F.when(n > 0, F.transform(F.sequence(F.lit(0), n - 1), make)).otherwise(F.array().cast("array<bigint>"))


def word_hashes(text: Column) -> Column:
    return F.transform(F.regexp_extract_all(F.coalesce(text.cast("string"), F.lit("")), F.lit(WORD_CLASS), F.lit(0)), lambda w: F.xxhash64(w))


def verdict_column(docs: DataFrame) -> str:
    """The name of the verdicts' struct: _q, or the first longer one that the input doesn't use."""
    name = "_q"
    while name in docs.columns or name == "_row":
        name = "_" + name
    return name


def text_bytes(docs: DataFrame, text_col: str = "text") -> int:
    return docs.agg(F.sum(F.octet_length(F.col(text_col).cast("string")))).first()[0] or 0


def buckets_for(docs: DataFrame, text_col: str = "text") -> int:
    return _buckets(text_bytes(docs, text_col))


def _buckets(size: int) -> int:
    return min(MOST_BUCKETS, max(LEAST_BUCKETS, 1 << (size // BUCKET_BYTES).bit_length()))


def features(hashes: str, buckets: int) -> Column:
    """Buckets of the words and of the pairs of neighbours."""
    h = F.col(hashes)
    pairs = _upto(F.size(h) - 1, lambda i: F.xxhash64(F.get(h, i), F.get(h, i + 1)))
    return F.transform(F.concat(h, pairs), lambda x: F.shiftrightunsigned(x, 64 - (buckets.bit_length() - 1)).cast("int"))


def _literal(values: list[int], kind: str) -> Column:
    """An array that folds to one literal."""
    return F.split(F.lit(",".join(map(str, values))), ",").cast(f"array<{kind}>")


def may_be_in(ids: DataFrame, key: Column) -> Column:
    """False only for keys that the distinct ids (one column, of the key's type) don't hold."""
    rows = ids.count()
    bits = min(MOST_BITS, 1 << max(10, (BITS_EACH * rows).bit_length()))
    slot = lambda x: F.shiftrightunsigned(F.xxhash64(x), 64 - (bits.bit_length() - 1))
    at = slot(F.col(ids.columns[0]))
    words = ids.select(at.alias("s")).groupBy(F.shiftright("s", 6).alias("w")).agg(F.expr("bit_or(shiftleft(1L, CAST(s & 63 AS INT)))").alias("m"))
    packed = words.agg(F.array_join(F.collect_list(F.concat_ws(":", "w", "m")), ",")).first()[0]
    held = [0] * (bits // 64)
    for cell in packed.split(",") if packed else []:
        w, m = cell.split(":")
        held[int(w)] = int(m)
    s = slot(key)
    mask = F.get(_literal(held, "bigint"), F.shiftright(s, 6).cast("int"))
    return F.getbit(mask, s.bitwiseAND(F.lit(63)).cast("int")) == 1


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", buckets: int | None = None) -> list[int]:
    """The weights, in thousandths of a nat, by bucket."""
    size = text_bytes(docs, text_col)
    buckets = buckets or _buckets(size)
    good = labels.where((F.col("quality") == 1) & (F.coalesce(F.col("toxic"), F.lit(0)) == 0)).select(F.col(id_col).alias("good_id")).distinct()
    texts = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    kind = texts.schema["id"].dataType
    same = kind == good.schema["good_id"].dataType and (isinstance(kind, T.IntegralType) or kind == T.StringType())
    likely = texts.where(may_be_in(good, F.col("id"))) if same else texts
    trusted = likely.join(good.hint("shuffle_hash"), texts["id"] == good["good_id"], "left_semi")  # the ids grow with the corpus: no broadcast
    tasks = max(2 * docs.sparkSession.sparkContext.defaultParallelism, size // TASK_BYTES)

    def told(rows: DataFrame, raw: int, good: int) -> DataFrame:
        hashed = rows.select(word_hashes(F.col("text")).alias("h")).coalesce(tasks)
        return hashed.select(F.lit(raw).alias("r"), F.lit(good).alias("t"), F.explode_outer(features("h", buckets)).alias("f")).where("f is not null")

    counted = told(texts, 1, 0).unionByName(told(trusted, 0, 1))
    rows = counted.groupBy("f").agg(F.sum("r").alias("raw"), F.sum("t").alias("good"))
    totals = F.struct(F.sum("raw").alias("n"), F.sum("good").alias("t"), F.collect_list(F.struct("f", "raw", "good")).alias("cells"))
    # Counts on the trusted corpus' scale, each with PRIOR more: a bucket of little evidence weighs little.
    share = F.col("s.t") / F.col("s.n")
    weight = lambda c: F.round(1000 * (F.log(c["good"] + PRIOR) - F.log(c["raw"] * share + PRIOR))).cast("int")
    cells = F.transform("s.cells", lambda c: F.concat_ws(":", c["f"], weight(c)))
    packed = rows.agg(totals.alias("s")).select(F.when(F.col("s.t") > 0, F.array_join(cells, ","))).first()[0]  # one row
    out = [0] * buckets
    for cell in packed.split(",") if packed else []:
        f, w = cell.split(":")
        out[int(f)] = int(w)
    return out


def measure(docs: DataFrame, weights: list[int], text_col: str = "text") -> DataFrame:
    """All columns of docs, and a struct column verdict_column(docs) with the measures, the score and the verdicts."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    table = _literal(weights, "int")
    own = F.struct(*[F.col(c) for c in docs.columns]).alias("_row")
    h = F.col("h")
    a = docs.select(
        own, word_hashes(F.col(text_col)).alias("h"),
        F.length(F.regexp_replace(text, _BREAKS, "")).cast("long").alias("word_chars"),
        F.length(F.regexp_replace(text, r"[^#*$%&|<>]+", "")).cast("long").alias("n_symbols"),
        F.filter(F.split(text, "\n"), lambda x: x.rlike(r"[^\x20\x09-\x0D]")).alias("lines"),
    )
    b = a.select(
        "_row", "word_chars", "n_symbols", F.size("h").cast("long").alias("n_words"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        features("h", len(weights)).alias("f"),
        _upto(F.size(h) - 4, lambda i: F.xxhash64(*[F.get(h, i + k) for k in range(5)])).alias("w"),
    )
    w, s, p = F.col("w"), F.col("s"), F.col("p")
    nothing = F.array().cast("array<struct<h:bigint,i:int>>")
    keyed = F.transform(w, lambda x, i: F.struct(x.alias("h"), i.cast("int").alias("i")))
    c = b.select(
        "_row", "word_chars", "n_symbols", "n_words", "n_dup_lines", F.size("f").alias("n_f"),
        F.aggregate("f", F.lit(0).cast("long"), lambda acc, x: acc + F.get(table, x)).alias("total"),
        F.when(F.size(F.array_distinct(w)) < F.size(w), F.array_sort(keyed)).otherwise(nothing).alias("s"),
    )
    same = lambda i, j: F.coalesce(F.get(s, i)["h"] == F.get(s, j)["h"], F.lit(False))
    again = _upto(F.size(s), lambda i: F.when(same(i, i - 1) | same(i, i + 1), F.get(s, i)["i"].cast("bigint")))
    d = c.withColumn("p", F.array_sort(F.filter(again, lambda x: x.isNotNull())))
    step = lambda i: F.least(F.lit(5).cast("bigint"), F.coalesce(F.get(p, i + 1) - F.get(p, i), F.lit(5).cast("bigint")))
    e = d.withColumn("n_repeat_words", F.aggregate(_upto(F.size(p), step), F.lit(0).cast("long"), lambda acc, x: acc + x))
    score = F.when(F.col("n_f") > 0, F.col("total") / F.col("n_f")).otherwise(0.0)
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    names = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
    judged = e.select("_row", *names, score.alias("score"), failed.alias("base_failed"))
    verdict = ~F.col("base_failed") & (F.col("score") >= LEAST_SCORE)
    # Through a generator, or a filter on the verdict would be pushed down and each array with it, many times over.
    verdicts = F.array(F.struct(*names, "score", "base_failed", verdict.alias("kept")))
    return judged.select("_row.*", F.explode_outer(verdicts).alias(verdict_column(docs)))


def judge(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    return measure(docs, fit(docs, labels, id_col, text_col), text_col)
