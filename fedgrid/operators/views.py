"""Party views: vertical splits of users' attributes, and the alignment of the parties' users."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fedgrid.operators.packed import Columns, Fold


@dataclass(frozen=True)
class PartyView:
    """One party's columns: ``frame`` has id and x (array of scaled attributes named by ``names``).

    ``columns`` are the same ones of packed points, in experiments that have these.
    """

    frame: DataFrame
    names: tuple[str, ...]
    columns: Columns | None = None


def view(df: DataFrame, id_col: str, names: list[str]) -> PartyView:
    """Only the id and the party's own columns are read (the scan is pruned to them)."""
    x = F.array(*[F.col(c).cast("double") for c in names])
    return PartyView(df.select(F.col(id_col).cast("bigint").alias("id"), x.alias("x")), tuple(names))


def build_views(df: DataFrame, id_col: str, groups: list[list[str]]) -> list[PartyView]:
    return [view(df, id_col, g) for g in groups]


def validate(v: PartyView) -> PartyView:
    """Raises on null ids, repeated ids, nulls or NaN; one shuffle on the id."""
    bad = F.col("x").isNull() | F.exists("x", lambda e: e.isNull() | F.isnan(e))
    users = v.frame.groupBy("id").agg(F.count(F.lit(1)).alias("n"), F.count_if(bad).alias("bad"))
    row = users.agg(
        F.coalesce(F.max(F.when(F.col("id").isNotNull(), F.col("n"))), F.lit(0)).alias("most"),
        F.coalesce(F.sum(F.when(F.col("id").isNull(), F.col("n"))), F.lit(0)).alias("nulls"),
        F.coalesce(F.sum("bad"), F.lit(0)).alias("bad"),
    ).first()
    if row["nulls"] or row["bad"]:
        raise ValueError(f"{row['nulls']} null ids and {row['bad']} rows with missing values")
    if row["most"] > 1:
        raise ValueError("an id occurs twice")
    return v


def random_split(names: list[str], parties: int, seed: int) -> list[list[str]]:
    """Columns dealt at random, as evenly as they go."""
    order = np.random.default_rng(seed).permutation(len(names))
    return [[names[i] for i in sorted(part)] for part in np.array_split(order, parties)]


def ratio_split(names: list[str], sizes: list[int], seed: int | None = None) -> list[list[str]]:
    """Columns dealt in the given numbers (3:5, 6:10 and so on), shuffled if a seed is given."""
    order = list(range(len(names))) if seed is None else list(np.random.default_rng(seed).permutation(len(names)))
    cuts = np.cumsum([0, *sizes])
    return [[names[i] for i in sorted(order[a:b])] for a, b in zip(cuts[:-1], cuts[1:], strict=True)]


class _MeansFold(Fold):
    def __init__(self):
        self.sums = 0.0

    def add(self, block) -> None:
        self.sums = self.sums + np.append(block.x.sum(axis=0), len(block))

    def state(self) -> np.ndarray | float:
        return self.sums


class _MomentsFold(Fold):
    """What ``correlations`` adds up, of points without gaps."""

    def __init__(self, means: np.ndarray):
        self.means, self.total = means, np.zeros((4, len(means), len(means)))

    def add(self, block) -> None:
        x = block.x - self.means
        has = np.ones_like(x)
        self.total += [has.T @ has, x.T @ has, (x * x).T @ has, x.T @ x]

    def state(self) -> np.ndarray:
        return self.total


def correlations(df: DataFrame | Columns, names: list[str]) -> dict[tuple[str, str], float]:
    """All pairwise correlations, each over the rows that have both values: a pass for the means, and one that adds
    up products of the distances from them."""
    if isinstance(df, Columns):
        *sums, n = df.points.ask(_MeansFold())
        sent = np.array(sums) / n
        return _correlated(df.points.ask(_MomentsFold(sent)), sent, list(names))
    values = df.select(*[F.col(c).cast("double").alias(c) for c in names])
    means = values.agg(*[F.avg(c).alias(c) for c in names]).first()
    sent, m = np.array([means[c] or 0.0 for c in names]), len(names)

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((4, m, m))
        for batch in batches:
            x = np.stack([c.to_numpy(zero_copy_only=False) for c in batch.columns], axis=1).astype(float) - sent
            has = np.stack([c.is_valid().to_numpy(zero_copy_only=False) for c in batch.columns], axis=1).astype(float)
            x[has == 0] = 0.0
            total += [has.T @ has, x.T @ has, (x * x).T @ has, x.T @ x]
        yield pa.RecordBatch.from_pydict({"c": pa.array(range(total.size), pa.int32()), "v": pa.array(total.ravel())})

    flat = np.zeros(4 * m * m)
    for r in values.mapInArrow(fold, "c int, v double").groupBy("c").agg(F.sum("v").alias("v")).collect():
        flat[r["c"]] = r["v"]
    return _correlated(flat.reshape(4, m, m), sent, names)


def _correlated(moments: np.ndarray, sent: np.ndarray, names: list[str]) -> dict[tuple[str, str], float]:
    n, s, q, p = moments
    with np.errstate(invalid="ignore", divide="ignore"):
        spread = q - s * s / n  # of the first one of a pair, over the rows that have both
        spread[spread <= n * (1e-13 * sent[:, None]) ** 2] = 0.0  # what is left of one value alone
        r = (p - s * s.T / n) / np.sqrt(spread * spread.T)
    # no rows or one value alone: no correlation
    return {(a, b): float(r[i, j]) if spread[i, j] > 0 and spread[j, i] > 0 else 0.0
            for i, a in enumerate(names) for j, b in enumerate(names) if i < j}


def correlation_split(df: DataFrame | Columns, names: list[str], parties: int) -> list[list[str]]:
    """Strongly correlated columns to different parties: greedy, least correlation inside a party, even sizes."""
    corr = correlations(df, names)
    strength = {n: sum(abs(v) for p, v in corr.items() if n in p) for n in names}
    groups: list[list[str]] = [[] for _ in range(parties)]
    most = -(-len(names) // parties)
    for n in sorted(names, key=lambda c: (-strength[c], c)):
        open_ = [g for g in groups if len(g) < most]

        def inside(g: list[str], n: str = n) -> float:
            return sum(abs(corr.get((n, o), corr.get((o, n), 0.0))) for o in g)

        min(open_, key=lambda g: (inside(g), len(g))).append(n)
    return groups


def align(views: list[PartyView], policy: str = "complete", default: float = 0.0) -> list[PartyView]:
    """Users in all parties (``complete``), all users with a public default (``impute``), or as they are (``own``)."""
    if policy == "own":
        return views
    ids = [v.frame.select("id") for v in views]
    if policy == "complete":
        common = reduce(lambda a, b: a.join(b, "id", "left_semi"), ids)
        return [PartyView(v.frame.join(common, "id", "left_semi"), v.names) for v in views]
    every = reduce(DataFrame.unionByName, ids).distinct()
    out = []
    for v in views:
        filled = F.coalesce("x", F.array(*[F.lit(float(default))] * len(v.names)))
        out.append(PartyView(every.join(v.frame, "id", "left").select("id", filled.alias("x")), v.names))
    return out


def unmatched(v: PartyView, other: PartyView) -> DataFrame:
    """(id) of the users that another party doesn't have."""
    return v.frame.select("id").join(other.frame.select("id"), "id", "left_anti")


def coverage(views: list[PartyView]) -> DataFrame:
    """(in_0.., users): how many users are in which parties."""
    frames = [v.frame.select("id").distinct().withColumn(f"p{k}", F.lit(True)) for k, v in enumerate(views)]
    both = reduce(lambda a, b: a.join(b, "id", "full_outer"), frames)
    flags = [F.coalesce(f"p{k}", F.lit(False)).alias(f"in_{k}") for k in range(len(views))]
    return both.groupBy(*flags).agg(F.count(F.lit(1)).alias("users"))


def joined(views: list[PartyView]) -> DataFrame:
    """id and the concatenated attributes of users in all parties: for evaluation only, outside the protocol."""
    frames = [v.frame.withColumnRenamed("x", f"x{k}") for k, v in enumerate(views)]
    wide = reduce(lambda a, b: a.join(b, "id"), frames)
    return wide.select("id", F.concat(*[f"x{k}" for k in range(len(views))]).alias("x"))
