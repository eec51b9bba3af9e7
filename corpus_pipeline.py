"""The corpus pipeline: language ID, line dedup, n-gram Jaccard join, decontamination, mixing.

Each stage is a function of (spark, docs, sf_dir) that works on all rows of its predecessor's Parquet.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from fedgrid.checkpoints import delete, folder
from fedgrid.llm import decontamination, jaccard_join, language_id, line_dedup, mixing

STAGES = [
    ("language_id", language_id.stage),
    ("line_dedup", line_dedup.stage),
    ("jaccard_join", jaccard_join.stage),
    ("decontamination", decontamination.stage),
    ("mixing", mixing.stage),
]

#: The first and the last stage are fitted models, which SQL doesn't express.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written to the shared folder before the next one reads it.

    A stage's table goes when the next one is written; the last one's is the result.
    """
    docs, before = spark.read.parquet(f"{sf_dir}/documents.parquet"), None
    place = f"{folder(spark)}/pipeline-{uuid.uuid4().hex}"
    for name, step in STAGES:
        step(spark, docs, sf_dir).write.parquet(f"{place}/{name}")
        docs = spark.read.parquet(f"{place}/{name}")
        if before:
            delete(spark, before)
        before = f"{place}/{name}"
    return docs
