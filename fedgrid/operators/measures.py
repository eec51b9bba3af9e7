"""Accuracy measures on DataFrames: V-measure, relative weight error, silhouette (squared distances)."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fedgrid.operators.kmeans import assign, cluster_sums
from fedgrid.operators.packed import Block, Columns, Fold, Labels, closest


def v_measure(pairs: DataFrame, truth: str = "y", found: str = "a") -> tuple[float, float, float]:
    """(homogeneity, completeness, their harmonic mean) of two labellings; one count table is collected."""
    return v_of_counts({(r[truth], r[found]): r["count"] for r in pairs.groupBy(truth, found).count().collect()})


def v_of_counts(rows: dict[tuple, float]) -> tuple[float, float, float]:
    """The same from the numbers of rows of each (truth, found)."""
    n = sum(rows.values())
    if not n:
        return 1.0, 1.0, 1.0
    ys, fs = {}, {}
    for (y, f), count in rows.items():
        ys[y] = ys.get(y, 0) + count
        fs[f] = fs.get(f, 0) + count

    def entropy(parts) -> float:
        return -sum(c / n * math.log(c / n) for c in parts)

    both = entropy(rows.values())
    hy, hf = entropy(ys.values()), entropy(fs.values())
    h = 1.0 if hy == 0 else 1 - (both - hf) / hy
    c = 1.0 if hf == 0 else 1 - (both - hy) / hf
    return h, c, 0.0 if h + c == 0 else 2 * h * c / (h + c)


@dataclass(frozen=True)
class Clustering:
    """What is measured: final centers over the columns ``order`` of the points, and each party's own centers over
    its columns (none for a central one)."""

    centers: np.ndarray
    order: tuple[int, ...]
    parties: tuple[tuple[tuple[int, ...], np.ndarray], ...] = ()


@dataclass
class Measured:
    loss: float
    pairs: dict[tuple[int, int], int]
    cells: np.ndarray | None


class CellsFold(Fold):
    """Numbers of users by their labels at all parties, as exact weights have them."""

    def __init__(self, labels: list[Labels]):
        self.labels, self.sizes = labels, tuple(len(own.centers) for own in labels)
        self.counts = np.zeros(int(np.prod(self.sizes)))

    def add(self, block: Block) -> None:
        cell = np.ravel_multi_index([own.of(block) for own in self.labels], self.sizes)
        self.counts += np.bincount(cell, minlength=len(self.counts))

    def state(self) -> np.ndarray:
        return self.counts


class _MeasureFold(Fold):
    """The sums of ``measure_all``: (run, what, y, a) to a number."""

    def __init__(self, runs: list[Clustering], truth: list[np.ndarray | None]):
        self.runs, self.truth = runs, truth
        self.total: dict[tuple[int, int, int, int], float] = {}

    def _count(self, r: int, what: int, y: np.ndarray, a: np.ndarray) -> None:
        first = y.min()
        wide = int(a.max()) + 1
        keys, n = np.unique((y - first) * wide + a, return_counts=True)
        for key, count in zip(keys.tolist(), n.tolist(), strict=True):
            at = r, what, key // wide + int(first), key % wide
            self.total[at] = self.total.get(at, 0) + count

    def add(self, block: Block) -> None:
        def near(places: tuple[int, ...], centers: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            return block.once(("near", places, centers.tobytes()), lambda: closest([block.columns[j] for j in places], centers))

        for r, (run, centers) in enumerate(zip(self.runs, self.truth, strict=True)):
            a, d = near(tuple(run.order), run.centers)
            self.total[r, 0, 0, 0] = self.total.get((r, 0, 0, 0), 0.0) + float(d.sum())
            self._count(r, 1, block.y if centers is None else near(tuple(range(len(block.columns))), centers)[0], a)
            if run.parties:
                cell = np.zeros(len(a), np.int64)
                for places, local in run.parties:
                    cell = cell * len(local) + near(tuple(places), local)[0]
                self._count(r, 2, np.zeros(len(a), np.int64), cell)

    def state(self) -> dict[tuple[int, int, int, int], float]:
        return self.total

    @staticmethod
    def both(a: dict, b: dict) -> dict:
        return {key: a.get(key, 0) + b.get(key, 0) for key in {**a, **b}}


def _measured_rows(df: DataFrame, runs: list[Clustering], truth: list[np.ndarray | None]) -> dict:
    sent = df.sparkSession.sparkContext.broadcast((runs, truth))

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = _MeasureFold(*sent.value)
        for batch in batches:
            if batch.num_rows:
                x = batch.column(0).flatten().to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1)
                own.add(Block(np.arange(len(x)), batch.column(1).fill_null(-1).to_numpy(), x))
        keys = np.array(list(own.total), np.int64).reshape(-1, 4)
        made = [pa.array(keys[:, j], pa.int32() if j < 2 else pa.int64()) for j in range(4)]
        yield pa.RecordBatch.from_arrays([*made, pa.array(list(own.total.values()), pa.float64())], names=["r", "what", "y", "a", "v"])

    rows = df.where(F.col("x").isNotNull()).select("x", F.col("y").cast("bigint"))
    made = rows.mapInArrow(fold, "r int, what int, y bigint, a bigint, v double")
    found = made.groupBy("r", "what", "y", "a").agg(F.sum("v").alias("v")).collect()
    sent.unpersist()
    return {(r["r"], r["what"], r["y"], r["a"]): r["v"] for r in found}


def measure_all(points: DataFrame | Columns, runs: list[Clustering], truth: list[np.ndarray | None]) -> list[Measured]:
    """Loss, label pairs and exact cell weights of many clusterings of the same points in one pass.

    A DataFrame has x and y; a point's true label is its nearest center of ``truth``, where one is given, else its y.
    """
    found = points.points.ask(_MeasureFold(runs, truth)) if isinstance(points, Columns) else _measured_rows(points, runs, truth)
    out = [Measured(0.0, {}, np.zeros([len(c) for _, c in run.parties]) if run.parties else None) for run in runs]
    for (r, what, y, a), v in found.items():
        own = out[r]
        if what == 0:
            own.loss = v
        elif what == 1:
            own.pairs[y, a] = int(v)
        else:
            own.cells.ravel()[a] = v
    for own in out:
        own.loss /= max(sum(own.pairs.values()), 1.0)
    return out


def relative_error(estimate: np.ndarray, exact: np.ndarray, n: float) -> float:
    """L1 distance of cell weights over the number of users."""
    return float(np.abs(estimate - exact).sum() / n)


class _MomentsFold(Fold):
    """Number of points, sums of their values and of their squares by nearest center: (k, m + 2)."""

    def __init__(self, labels: Labels):
        self.labels, self.total = labels, np.zeros((len(labels.centers), labels.centers.shape[1] + 2))

    def add(self, block: Block) -> None:
        a, x, k = self.labels.of(block), block.of(self.labels.seen.places), len(self.total)
        self.total[:, 0] += np.bincount(a, minlength=k)
        for j in range(x.shape[1]):
            self.total[:, 1 + j] += np.bincount(a, x[:, j], k)
        self.total[:, -1] += np.bincount(a, np.einsum("ij,ij->i", x, x), k)

    def state(self) -> np.ndarray:
        return self.total


class _SilhouetteFold(Fold):
    """Sum of the points' silhouettes, and their number, from the moments of all clusters."""

    def __init__(self, labels: Labels, moments: np.ndarray):
        self.labels, self.moments, self.total = labels, moments, np.zeros(2)

    def add(self, block: Block) -> None:
        a, x = self.labels.of(block), block.of(self.labels.seen.places)
        n, sums, q = self.moments[:, 0], self.moments[:, 1:-1], self.moments[:, -1]
        rows = np.arange(len(x))
        total = np.einsum("ij,ij->i", x, x)[:, None] * n - 2 * (x @ sums.T) + q
        inside = total[rows, a] / np.maximum(n - 1, 1)[a]
        total /= np.maximum(n, 1)
        total[:, n == 0] = np.inf
        total[rows, a] = np.inf
        outside = total.min(axis=1)
        most = np.maximum(inside, outside)
        none = (n[a] <= 1) | (most == 0)
        with np.errstate(invalid="ignore"):  # a single cluster has no silhouettes
            self.total += np.where(none, 0.0, (outside - inside) / np.where(none, 1.0, most)).sum(), len(x)

    def state(self) -> np.ndarray:
        return self.total


def silhouette(df: DataFrame | Columns, centers: np.ndarray) -> float:
    """Mean silhouette with squared distances, from cluster moments: two passes, no pair of points."""
    if isinstance(df, Columns):
        labels = Labels(df, np.asarray(centers, float))
        total, n = df.points.ask(_SilhouetteFold(labels, df.points.ask(_MomentsFold(labels))))
        return float(total / n)
    k, m = centers.shape
    labelled = assign(df, centers)
    sums = cluster_sums(df, [centers])[0]
    squares = labelled.groupBy("a").agg(F.sum(F.aggregate("x", F.lit(0.0), lambda s, v: s + v * v)).alias("q"))
    q = np.zeros(k)
    for r in squares.collect():
        q[r["a"]] = r["q"]
    n = sums[:, 0]
    own = F.aggregate("x", F.lit(0.0), lambda s, v: s + v * v)
    means = []
    for c in range(k):
        if n[c] == 0:
            means.append(F.lit(float("inf")))
            continue
        dot = F.lit(0.0)
        for j in range(m):
            dot = dot + F.get("x", F.lit(j)) * float(sums[c, 1 + j])
        total = own * float(n[c]) - 2 * dot + float(q[c])
        size = F.when(F.col("a") == c, F.lit(max(float(n[c]) - 1, 1.0))).otherwise(F.lit(float(n[c])))
        means.append(total / size)
    inside = F.coalesce(*[F.when(F.col("a") == c, v) for c, v in enumerate(means)])
    outside = F.least(*[F.when(F.col("a") == c, F.lit(float("inf"))).otherwise(v) for c, v in enumerate(means)], F.lit(float("inf")))
    alone = F.coalesce(*[F.when(F.col("a") == c, F.lit(bool(n[c] <= 1))) for c in range(k)])
    score = F.when(alone | (F.greatest(inside, outside) == 0), 0.0).otherwise(
        (outside - inside) / F.greatest(inside, outside)
    )
    return float(labelled.agg(F.avg(score)).first()[0])
