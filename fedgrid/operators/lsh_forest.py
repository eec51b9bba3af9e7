"""Private clustering by a locality-sensitive hash forest.

Points are coded by signs of seeded random projections. All code prefixes are counted in one aggregate; the
driver grows each tree from the root, splitting a part while its noisy count is above a threshold, and every
public prefix it looks at is charged, empty ones included. Leaves get noisy sums, and a plain weighted k-means
runs on the leaves' noisy means. Noise is Laplace over attributes bounded by ``radius`` (the vertical form), or
Gaussian with a bound on the whole point's L2 norm (the central form).
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fedgrid.operators.kmeans import weighted_kmeans
from fedgrid.operators.packed import Block, Columns, Fold
from fedgrid.privacy import gaussian_scale


def directions(m: int, bits: int, seed: int) -> np.ndarray:
    return np.random.default_rng(seed).standard_normal((bits, m))


def code(x: Column, planes: np.ndarray) -> Column:
    """The packed sign bits, first plane highest."""
    out = F.lit(0).cast("bigint")
    for k, plane in enumerate(planes.tolist()):
        dot = F.lit(0.0)
        for j, v in enumerate(plane):
            dot = dot + F.get(x, F.lit(j)) * F.lit(v)
        out = out + F.when(dot >= 0, 1 << (len(planes) - 1 - k)).otherwise(0)
    return out


def packed_signs(x: np.ndarray, planes: np.ndarray) -> np.ndarray:
    """The same bits of many points, added up in the same order."""
    out = np.zeros(len(x), np.int64)
    columns = np.ascontiguousarray(x.T)
    for plane in planes:
        dot = np.zeros(len(x))
        for v, own in zip(plane.tolist(), columns, strict=True):
            dot += own * v
        out = 2 * out + (dot >= 0)
    return out


def _cut(x: np.ndarray, weight_bound: float | None, radius: float | None) -> np.ndarray:
    """What bounds the part of one point: its norm, or its values."""
    if weight_bound:
        norm = np.sqrt((x * x).sum(axis=1))[:, None]
        far = norm > weight_bound
        return np.where(far, x * weight_bound / np.where(far, norm, 1.0), x)
    return x.clip(-radius, radius) if radius is not None else x


def _add(x: np.ndarray, trees: list[np.ndarray], tables: list[np.ndarray]) -> None:
    for planes, out in zip(trees, tables, strict=True):
        codes = packed_signs(x, planes)
        out[:, 0] += np.bincount(codes, minlength=len(out))
        for j in range(x.shape[1]):
            out[:, 1 + j] += np.bincount(codes, x[:, j], len(out))


class _LeavesFold(Fold):
    """``leaf_sums`` of some columns of packed points."""

    def __init__(self, places: tuple[int, ...], trees: list[np.ndarray], weight_bound: float | None, radius: float | None):
        self.places, self.trees, self.how = places, trees, (weight_bound, radius)
        self.tables = np.zeros((len(trees), 1 << len(trees[0]), len(places) + 1))

    def add(self, block: Block) -> None:
        _add(_cut(block.of(self.places), *self.how), self.trees, self.tables)

    def state(self) -> np.ndarray:
        return self.tables


def leaf_sums(
    df: DataFrame | Columns, trees: list[np.ndarray], weight_bound: float | None = None, radius: float | None = None
) -> list[np.ndarray]:
    """For each tree a (2^bits, m + 1) table of counts and sums by full code: one pass over the points.

    What one point can add is bounded here: its values by ``radius``, or its norm by ``weight_bound``.
    """
    if isinstance(df, Columns):
        return list(df.points.ask(_LeavesFold(df.places, trees, weight_bound, radius)))
    bits, m = trees[0].shape
    size = 1 << bits
    sent = df.sparkSession.sparkContext.broadcast(trees)

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = [np.zeros((size, m + 1)) for _ in sent.value]
        for batch in batches:
            x = batch.column(0).flatten().to_numpy(zero_copy_only=False).reshape(-1, m)
            _add(_cut(x, weight_bound, radius), sent.value, tables)
        flat = np.concatenate([t.ravel() for t in tables])
        at = np.flatnonzero(flat)
        yield pa.RecordBatch.from_pydict({"c": pa.array(at, pa.int64()), "v": pa.array(flat[at])})

    rows = df.where(F.col("x").isNotNull()).select("x")
    flat = np.zeros(len(trees) * size * (m + 1))
    for r in rows.mapInArrow(fold, "c bigint, v double").groupBy("c").agg(F.sum("v").alias("v")).collect():
        flat[r["c"]] = r["v"]  # trees * 2^bits * (m + 1) numbers at most
    sent.unpersist()
    return list(flat.reshape(len(trees), size, m + 1))


def prefix_table(leaves: np.ndarray, depth: int) -> np.ndarray:
    """Counts and sums of all code prefixes of ``depth`` bits."""
    return leaves.reshape(1 << depth, -1, leaves.shape[1]).sum(axis=1)


def fit(
    df: DataFrame | Columns, k: int, eps: float, rng: np.random.Generator, delta: float = 0.0, noise: str = "laplace",
    radius: float = 1.0, l2_bound: float | None = None, bits: int | None = None, trees: int = 1, seed: int = 0,
    ledger=None, party: int = 0, once: Callable = lambda key, make: make(),
) -> np.ndarray:
    """k private centers; half of ``eps`` counts parts, half sums leaves (both split over levels and trees).

    ``once`` may keep what is made before any noise, for runs on the same points (see ``pipeline.Shared``).

    ``gaussian`` is the central form: a public bound on the points' norm, and noise calibrated to (eps, delta).
    """
    m = len(df.places) if isinstance(df, Columns) else once(("m", id(df)), lambda: len(df.first()["x"]))
    bits = bits or max(4, math.ceil(math.log2(4 * k)) + 2)
    planes = [directions(m, bits, seed + 17 * t) for t in range(trees)]
    bound = l2_bound or math.sqrt(m) * radius
    how = {"weight_bound": bound} if noise == "gaussian" else {"radius": radius}
    leaves = once(("leaves", id(df), bits, trees, seed, *how.items()), lambda: leaf_sums(df, planes, **how))
    eps_level = eps / 2 / trees / (bits + 1)
    eps_sum = eps / 2 / trees
    sd = gaussian_scale(bound, eps_sum, delta / trees) if noise == "gaussian" else 0.0
    found: list[tuple[np.ndarray, float]] = []
    for full in leaves:
        levels = [prefix_table(full, d) for d in range(bits + 1)]
        parts = []
        stack = [(0, 0)]
        least = max(4.0 / eps_level, 2.0)
        while stack:
            depth, prefix = stack.pop()
            block = levels[depth][prefix]
            count = block[0] + rng.laplace(0, 1 / eps_level)
            if count > 2 * least and depth < bits:
                stack += [(depth + 1, 2 * prefix), (depth + 1, 2 * prefix + 1)]
            else:
                parts.append((block[1:], count))
        for sums, count in parts:
            if count < 1:
                continue
            if noise == "laplace":
                noisy = sums + rng.laplace(0, m * radius / eps_sum, m)
                found.append(((noisy / count).clip(-radius, radius), count))
            else:
                noisy = (sums + rng.normal(0, sd, m)) / count
                norm = np.linalg.norm(noisy)
                found.append((noisy * min(1.0, bound / max(norm, 1e-12)), count))
    if ledger is not None:
        ledger.charge(party, "local centers", eps, delta if noise == "gaussian" else 0.0)
    if not found:
        return rng.uniform(-radius, radius, (k, m))
    points, weights = np.array([p for p, _ in found]), np.array([w for _, w in found])
    if len(points) < k:
        points = np.vstack([points, rng.uniform(-radius, radius, (k - len(points), m))])
        weights = np.append(weights, np.ones(len(points) - len(weights)))
    return weighted_kmeans(points, weights, k, seed)
