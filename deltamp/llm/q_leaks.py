"""Query op8: benchmark items that documents hold."""

from pyspark.sql import DataFrame, SparkSession

from deltamp.llm.common import table
from deltamp.llm.leaks import matches


def op8_benchmark_leaks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return matches(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


QUERIES = {"op8_benchmark_leaks": op8_benchmark_leaks}
ORACLES: dict[str, str] = {}
