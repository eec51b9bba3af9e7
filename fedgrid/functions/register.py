"""The SQL surface: functions for sketches and grids, registered by name."""

from __future__ import annotations

import itertools

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from fedgrid.functions.estimators import cardinality
from fedgrid.operators.sketch import mix64


def register(spark: SparkSession) -> None:
    """geometric_hash(id, key, gamma), sketch_cardinality(alpha, gamma), sketch_union_agg(alpha), grid_cells(k, s)."""

    def geometric_hash(ids: pd.Series, keys: pd.Series, gamma: pd.Series) -> pd.Series:
        with np.errstate(over="ignore"):
            hashed = mix64(mix64(ids.to_numpy(np.int64).view(np.uint64)) ^ mix64(keys.to_numpy(np.int64).view(np.uint64)))
        u = (hashed.astype(float) + 1) / 2.0**64
        return pd.Series(np.maximum(np.ceil(-np.log(u) / np.log1p(gamma.to_numpy(float))), 1).astype(np.int32))

    def sketch_cardinality(alpha: pd.Series, gamma: pd.Series) -> pd.Series:
        return pd.Series([float(cardinality(np.array(a), g)) for a, g in zip(alpha, gamma, strict=True)])

    def union_agg(alpha: pd.Series) -> list[int]:
        return np.maximum.reduce([np.asarray(a) for a in alpha]).tolist()

    spark.udf.register("geometric_hash", F.pandas_udf(geometric_hash, "int"))
    spark.udf.register("sketch_cardinality", F.pandas_udf(sketch_cardinality, "double"))
    union_agg.__annotations__ = {"alpha": pd.Series, "return": list[int]}
    spark.udf.register("sketch_union_agg", F.pandas_udf(union_agg, "array<int>", F.PandasUDFType.GROUPED_AGG))

    @F.udtf(returnType="cell array<int>")
    class GridCells:
        def eval(self, k: int, s: int):
            for cell in itertools.product(range(k), repeat=s):
                yield (list(cell),)

    spark.udtf.register("grid_cells", GridCells)
