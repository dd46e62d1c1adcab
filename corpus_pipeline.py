"""A corpus pipeline: identified languages, one of each near copy, no benchmark text, no secrets, packed sequences."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from vecforest.llm.common import staged, table
from vecforest.llm.decontamination import drop_contaminated
from vecforest.llm.jaccard import keep_one_of_each
from vecforest.llm.language import keep_known_languages
from vecforest.llm.packing import pack_stage
from vecforest.llm.secrets import mask_secrets

#: Each stage takes (spark, docs, sf_dir); what it returns is written as Parquet and read again as the next one's docs.
STAGES = [
    ("language", keep_known_languages),
    ("near_copies", keep_one_of_each),
    ("decontamination", drop_contaminated),
    ("secrets", mask_secrets),
    ("packing", pack_stage),
]

#: Tokens and packing have no SQL; the tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Applies the stages to documents. Empty documents give no pieces; null texts go with the first stage."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = staged(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
