"""Sources and sinks: the given tables, other formats with explicit schemas, bucketed tables, released messages."""

from __future__ import annotations

import json

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = (
    "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations"
).split()


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, fmt: str, schema: str, **options) -> DataFrame:
    """csv, json, orc or parquet with an explicit schema; nothing is inferred."""
    return spark.read.format(fmt).schema(schema).options(**options).load(path)


def read_stream(spark: SparkSession, path: str, schema, fmt: str = "parquet", files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).format(fmt).load(path)


def save_bucketed(df: DataFrame, name: str, by: str = "id", buckets: int = 64) -> None:
    """Written once by id, so that joins of the parties' tables on it move nothing."""
    df.write.mode("overwrite").bucketBy(buckets, by).sortBy(by).saveAsTable(name)


def save_message(spark: SparkSession, path: str, party: int, centers: np.ndarray, sketch: np.ndarray | None) -> None:
    """What a party releases, and nothing else: one JSON row per cluster."""
    rows = [
        (party, a, json.dumps(c.tolist()), None if sketch is None else sketch[:, a].tolist()) for a, c in enumerate(centers)
    ]
    frame = spark.createDataFrame(rows, "party int, a int, center string, alpha array<int>")
    frame.coalesce(1).write.mode("append").partitionBy("party").json(path)


def load_messages(spark: SparkSession, path: str) -> list[tuple[np.ndarray, np.ndarray]]:
    """(centers, sketch) of each party, from its released rows."""
    rows = spark.read.schema("party int, a int, center string, alpha array<int>").json(path).orderBy("party", "a").collect()
    out = []
    for party in sorted({r["party"] for r in rows}):
        own = [r for r in rows if r["party"] == party]
        out.append((np.array([json.loads(r["center"]) for r in own]), np.array([r["alpha"] or [] for r in own]).T))
    return out


def first_records(df: DataFrame, keys: list[str], n: int) -> DataFrame:
    """The first n rows by key: a top-k, no global sort."""
    return df.orderBy(*keys).limit(n)


def props_k(df: DataFrame) -> DataFrame:
    return df.withColumn("props_k", F.get_json_object("props", "$.k").cast("double"))
