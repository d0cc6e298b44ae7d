"""The training-data pipeline: toxicity filter, line dedup, near duplicates, secret masking, packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from proxembed.llm.common import store
from proxembed.llm.line_dedup import line_dedup_stage
from proxembed.llm.packing import packing_stage
from proxembed.llm.parity_join import near_duplicate_stage
from proxembed.llm.secret_scan import secret_stage
from proxembed.llm.toxicity import toxicity_stage

STAGES = [
    ("toxicity", toxicity_stage),
    ("line dedup", line_dedup_stage),
    ("n-gram Jaccard join", near_duplicate_stage),
    ("secret scans", secret_stage),
    ("best-fit packing", packing_stage),
]

#: The stages hold a fitted model, a graph closure and a tokenizer, which SQL can't express; tests/llm hold them against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (name, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = store(docs, name.replace(" ", "-"))
    return docs
