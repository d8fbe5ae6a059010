"""Query op6: remove word runs that documents repeat."""

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamp.llm.common import table
from deltamp.llm.passages import repeated_runs


def op6_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = repeated_runs(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


QUERIES = {"op6_substring_dedup": op6_substring_dedup}
ORACLES: dict[str, str] = {}
