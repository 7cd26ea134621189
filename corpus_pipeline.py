"""The corpus pipeline: quality classifier, line dedup, SimHash near-dedup, decontamination, source mixing."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from loadshard.llm.common import shared_dir
from loadshard.llm.latentdecon import decontaminated
from loadshard.llm.linededup import lines_deduped
from loadshard.llm.mixing import mixed
from loadshard.llm.neighbours import quality_kept
from loadshard.llm.simhash import near_deduped

STAGES = [
    ("quality classifier", quality_kept),
    ("line dedup", lines_deduped),
    ("simhash near-dedup", near_deduped),
    ("benchmark decontamination", decontaminated),
    ("source mixing", mixed),
]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Applies STAGES to documents; each result is written as Parquet and read again as the next one's input."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    root = f"{shared_dir(spark).rstrip('/')}/pipeline-{uuid.uuid4().hex}"
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{root}/{k}")
        docs = spark.read.parquet(f"{root}/{k}")
    return docs
