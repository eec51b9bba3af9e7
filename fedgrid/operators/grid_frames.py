"""The server's estimators on DataFrames, for grids above ``weights.MAX_CELLS``: cells are rows (a0 .. aS-1, w).

Party tables (k' rows each) are broadcast: their size is the number of local clusters. A refinement round is one
shuffle on the pair's two columns; lineage is cut every sweep by a checkpoint in the shared folder.
"""

from __future__ import annotations

import warnings
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fedgrid.checkpoints import checkpointed
from fedgrid.functions.estimators import bias
from fedgrid.operators.weights import complement_weights, consistent, leave_one_out, size_estimates


def cells(spark: SparkSession, sizes: list[int]) -> DataFrame:
    """All cells, by mixed-radix digits of a running number: no join."""
    total = int(np.prod([int(s) for s in sizes]))
    out, step = spark.range(total), total
    columns = {}
    for p, k in enumerate(sizes):
        step //= k
        columns[f"a{p}"] = (F.floor(F.col("id") / step) % k).cast("int")
    return out.select(*[c.alias(n) for n, c in columns.items()])


def _party(spark: SparkSession, p: int, values: list, schema: str) -> DataFrame:
    return F.broadcast(spark.createDataFrame([(a, v) for a, v in enumerate(values)], f"a{p} int, v{p} {schema}"))


def product_frame(spark: SparkSession, sizes: list[np.ndarray], n_hat: float) -> DataFrame:
    """The product start from single-party sizes."""
    out = cells(spark, [len(s) for s in sizes])
    for p, s in enumerate(sizes):
        out = out.join(_party(spark, p, [float(v) for v in s], "double"), f"a{p}")
    w = reduce(lambda x, y: x * y, [F.col(f"v{p}") / n_hat for p in range(len(sizes))], F.lit(float(n_hat)))
    return out.select(*[f"a{p}" for p in range(len(sizes))], w.alias("w"))


def complement_union_frame(spark: SparkSession, sketches: list[np.ndarray], n_hat: float, ghosts: int, gamma: float) -> DataFrame:
    """Raw weights of all cells: n_hat - (read-out of the union of complements - ghosts)."""
    out = cells(spark, [s.shape[1] for s in sketches])
    for p, s in enumerate(sketches):
        out = out.join(_party(spark, p, [[int(v) for v in c] for c in leave_one_out(s).T], "array<int>"), f"a{p}")
    union = reduce(lambda x, y: F.zip_with(x, y, lambda a, b: F.greatest(a, b)), [F.col(f"v{p}") for p in range(len(sketches))])
    total = F.aggregate(union, F.lit(0.0), lambda t, a: t + F.pow(F.lit(1.0 + gamma), -a.cast("double")))
    read = F.lit(len(sketches[0]) * bias(gamma)) / total
    return out.select(*[f"a{p}" for p in range(len(sketches))], (F.lit(float(n_hat + ghosts)) - read).alias("w"))


def simplex_frame(grid: DataFrame, total: float, rounds: int = 60) -> DataFrame:
    """Nearest nonnegative weights with the given sum: Newton steps on the threshold, one aggregate each, no sort."""
    theta = None
    for _ in range(rounds):
        live = F.lit(True) if theta is None else F.col("w") > theta
        s, n = grid.where(live).agg(F.sum("w"), F.count(F.lit(1))).first()
        new = (s - total) / n
        if theta is not None and new <= theta + 1e-12 * max(1.0, abs(theta)):
            break
        theta = new
    return grid.withColumn("w", F.greatest(F.col("w") - F.lit(float(theta)), F.lit(0.0)))


def refine_frame(
    grid: DataFrame, tables: dict[tuple[int, int], np.ndarray], n_hat: float, seed: int = 0, eta: float = 1.0,
    clip: bool = True, sweeps: int = 50, tol: float = 1e-4,
) -> DataFrame:
    """The additive fit to two-party tables, one pair a round in a drawn order, as in ``weights.refine``.

    Each sweep over the pairs is one checkpointed plan; it stops when a sweep moves no cell by more than tol * n_hat,
    and warns after ``sweeps`` of them.
    """
    spark, names = grid.sparkSession, grid.columns
    pairs = [sorted(tables)[i] for i in np.random.default_rng(seed).permutation(len(tables))]
    wanted = {}
    for l1, l2 in pairs:
        rows = [(int(i), int(j), float(tables[l1, l2][i, j])) for i, j in np.ndindex(tables[l1, l2].shape)]
        wanted[l1, l2] = spark.createDataFrame(rows, f"a{l1} int, a{l2} int, want double")
    for _ in range(sweeps):
        grid = grid.withColumn("__before", F.col("w"))
        for l1, l2 in pairs:
            group = Window.partitionBy(f"a{l1}", f"a{l2}")
            gap = (F.sum("w").over(group) - F.col("want")) / F.count(F.lit(1)).over(group)
            w = F.col("w") - F.lit(eta) * gap
            grid = grid.join(F.broadcast(wanted[l1, l2]), [f"a{l1}", f"a{l2}"])
            grid = grid.withColumn("w", F.greatest(w, F.lit(0.0)) if clip else w).select(*names, "__before")
        grid = checkpointed(grid)
        moved = grid.agg(F.max(F.abs(F.col("w") - F.col("__before")))).first()[0] or 0.0
        grid = grid.select(*names)
        if moved <= tol * max(n_hat, 1.0):
            return grid
    warnings.warn(f"the grid still moved by {moved:.4g} in sweep {sweeps}", stacklevel=2)
    return grid


def pairwise_refined_frame(
    spark: SparkSession, sketches: list[np.ndarray], n_hat: float, n_p: int, gamma: float, **how
) -> DataFrame:
    """The refined estimate as rows: tensors are two-party tables only."""
    pairs = [(a, b) for a in range(len(sketches)) for b in range(a + 1, len(sketches))]
    tables = {(a, b): consistent(complement_weights([sketches[a], sketches[b]], n_hat, n_p, gamma), n_hat) for a, b in pairs}
    sizes = [size_estimates(s, n_p, gamma).clip(min=0.0) for s in sketches]
    return simplex_frame(refine_frame(product_frame(spark, sizes, n_hat), tables, n_hat, **how), n_hat)


def complement_frame(spark: SparkSession, sketches: list[np.ndarray], n_hat: float, n_p: int, gamma: float) -> DataFrame:
    """The direct estimate as rows, made consistent."""
    ghosts = sum(s.shape[1] - 1 for s in sketches) * n_p
    return simplex_frame(checkpointed(complement_union_frame(spark, sketches, n_hat, ghosts, gamma)), n_hat)


def weighted_points(grid: DataFrame, centers: list[np.ndarray]) -> DataFrame:
    """(id, x, w): the cells' points, for a weighted Lloyd on the cluster; cells without weight are dropped."""
    out = grid.where("w > 0")
    for p, c in enumerate(centers):
        out = out.join(_party(grid.sparkSession, p, [[float(v) for v in row] for row in c], "array<double>"), f"a{p}")
    parts = [F.col(f"v{p}") for p in range(len(centers))]
    cell = F.xxhash64(*[f"a{p}" for p in range(len(centers))])
    return out.select(cell.alias("id"), F.concat(*parts).alias("x"), "w")


def pair_tables(wide: DataFrame, names: list[str]) -> DataFrame:
    """(names.., w): the exact two-party tables of users' labels in one grouping-sets aggregate over the full cells."""
    full = wide.groupBy(*names).agg(F.count(F.lit(1)).alias("n"))
    sets = [[F.col(a), F.col(b)] for i, a in enumerate(names) for b in names[i + 1 :]]
    return full.groupingSets(sets, *names).agg(F.sum("n").alias("w"))
