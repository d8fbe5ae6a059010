"""The corpus pipeline: five stages over the documents table, each written as Parquet and read again.

quality rules drop documents they reject; near-dedup (exact five-word Jaccard of 0.8 or more) keeps the smallest id of each group, rows that share an id or
have none included;
documents that hold a benchmark item go; personal data are replaced by marks; the rest are encoded.
"""

from __future__ import annotations

import uuid

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamp.llm import copies, leaks, pieces, pii, quality
from deltamp.llm.common import shared_folder, table

# Rows and bytes of an Arrow batch. A batch of texts lies in the JVM and in its worker, for each core.
BATCH_ROWS, BATCH_BYTES = 1000, 4 << 20
COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def _small_batches(spark: SparkSession) -> None:
    """For the session, as stages run after they return; smaller values that are set already stay."""
    for key, most in (("maxRecordsPerBatch", BATCH_ROWS), ("maxBytesPerBatch", BATCH_BYTES)):
        now = spark._jvm.org.apache.spark.network.util.JavaUtils.byteStringAsBytes(spark.conf.get(f"spark.sql.execution.arrow.{key}"))
        if not 0 < now <= most:
            spark.conf.set(f"spark.sql.execution.arrow.{key}", str(most))


def _free_shuffles(spark: SparkSession) -> None:
    """For the session: an execution's shuffle files go when it ends, not when the driver happens to collect garbage.

    A stage runs dozens of executions, and what they shuffled lies in the checkpoint folder by then.
    """
    spark.conf.set("spark.sql.classic.shuffleDependency.fileCleanup.enabled", "true")


def keep_good(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    _free_shuffles(spark)
    judged = quality.judge(docs.select(*COLUMNS), table(spark, sf_dir, "labels"))
    return judged.where("_q.kept").select(*COLUMNS)


def keep_one_of_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of texts whose five-word shingles are 0.8 similar or more."""
    _free_shuffles(spark)
    _small_batches(spark)
    return copies.keep_one_each(docs.select(*COLUMNS))


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    _free_shuffles(spark)
    _small_batches(spark)
    return leaks.keep_clean(docs.select(*COLUMNS), table(spark, sf_dir, "benchmark"))


def hide_personal(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    _small_batches(spark)
    out = pii.redact(docs.select(*COLUMNS))
    return out.withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    _small_batches(spark)
    return pieces.encode(docs, str(public_tokenizers.path("piece_bpe_32k.model")))


STAGES = [("quality_rules", keep_good), ("simhash_dedup", keep_one_of_group), ("decontamination", drop_leaks), ("personal_data", hide_personal), ("encoding", encode)]
ORACLE_SQL = None  # the stages' models and tokenizer have no SQL form; tests hold them against brute force


def _remove(spark: SparkSession, path: str) -> None:
    jvm = spark.sparkContext._jvm
    target = jvm.org.apache.hadoop.fs.Path(path)
    target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; between them Parquet in the shared checkpoint folder.

    A stage's input is removed once its output is written; the last stage's stays, as the result reads it.
    """
    root = f"{shared_folder(spark)}/pipeline-{uuid.uuid4().hex}"
    docs, before = table(spark, sf_dir, "documents"), None
    for k, (name, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        if k == len(STAGES) - 1:
            return out
        path = f"{root}/{k}-{name}"
        out.write.parquet(path)
        if before:
            _remove(spark, before)
        docs, before = spark.read.parquet(path), path
    return docs
