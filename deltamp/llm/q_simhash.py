"""Query op2: near-duplicate groups of the documents table."""

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from deltamp.llm.common import table
from deltamp.llm.simhash import near_duplicates


def op2_simhash_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = near_duplicates(table(spark, sf_dir, "documents"))
    digits = F.lpad(F.lower(F.hex("fp")), 16, "0")
    return found.select("doc_id", digits.alias("fingerprint"), "component_id")


QUERIES = {"op2_simhash_groups": op2_simhash_groups}
ORACLES: dict[str, str] = {}
