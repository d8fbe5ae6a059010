"""Query op9: licence notices in the documents table."""

from pyspark.sql import DataFrame, SparkSession

from deltamp.llm.common import table
from deltamp.llm.licenses import scan


def op9_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents"))


QUERIES = {"op9_license_scan": op9_license_scan}
ORACLES: dict[str, str] = {}
