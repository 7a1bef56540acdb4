"""A corpus pipeline over ``documents``: quality classifier, line dedup, SimHash near-dedup, benchmark decontamination, mixing.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame that is written
as Parquet and reread as the next one's docs.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from caregraph.llm import decontaminate, line_dedup, mixing, quality, simhash
from caregraph.llm.common import saved

STAGES = [
    ("quality_classifier", quality.stage),
    ("line_dedup", line_dedup.stage),
    ("simhash_near_dedup", simhash.stage),
    ("benchmark_decontamination", decontaminate.stage),
    ("temperature_mixing", mixing.stage),
]
#: Rules fitted by boosting, edit joins, components and alignments have no SQL form; tests/llm/test_pipeline.py and test_text_operators.py hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages in order; the last one's rows."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES[:-1]:
        docs = saved(stage(spark, docs, sf_dir))
    return STAGES[-1][1](spark, docs, sf_dir)
