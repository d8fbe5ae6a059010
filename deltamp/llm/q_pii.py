"""Query op1: personal data in the documents table."""

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamp.llm.common import table
from deltamp.llm.pii import scan


def op1_pii_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = scan(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_email", "n_ip", "n_card", "n_phone", F.sha2(F.col("base").cast("binary"), 256).alias("base_sha256"), "spans")


QUERIES = {"op1_pii_spans": op1_pii_spans}
ORACLES: dict[str, str] = {}
