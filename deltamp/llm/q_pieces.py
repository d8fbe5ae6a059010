"""Query op4: piece ids of the documents table."""

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from deltamp.llm.common import table
from deltamp.llm.pieces import encode

MODEL = "piece_bpe_32k.model"


def op4_piece_encoding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode(table(spark, sf_dir, "documents"), str(public_tokenizers.path(MODEL)))


QUERIES = {"op4_piece_encoding": op4_piece_encoding}
ORACLES: dict[str, str] = {}
