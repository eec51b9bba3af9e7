"""Clustering on DataFrames of (id, x array<double>): assignment, Lloyd, seeding, noisy Lloyd, and its driver-side
twin for weighted grids of bounded size. Only k * (m + 2) numbers per round reach the driver.

Rounds send their centers by broadcast to one Arrow kernel: distances are a matrix product, each task adds up its own
clusters, and the plan (so its generated code) is the same in every round, whatever the centers.
"""

from __future__ import annotations

from collections.abc import Iterator
from contextlib import contextmanager
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark import RDD, Broadcast, StorageLevel
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fedgrid.functions.columns import nearest_center
from fedgrid.operators.packed import Block, Columns, Fold
from fedgrid.operators.sketch import mix64

Centers = np.ndarray

#: Numbers (a point's values, id and weight) up to which one task clusters all points: 128 MB, twice that as it reads them.
ONE_TASK = 1 << 24
#: Points that the kernel takes at a time, so that what it makes of them stays in a core's cache.
_PART = 2048
#: Tasks up to which their tables meet at the driver at once.
_COLLECTED = 256
#: Centers up to which a part's sums are a matrix product.
_DENSE = 64


def assign(df: DataFrame, centers: Centers) -> DataFrame:
    """``df`` with a (nearest center) and d (squared distance). Narrow; the centers are literals."""
    found = df.withColumn("__n", nearest_center(F.col("x"), np.asarray(centers, float).tolist()))
    return found.select(*df.columns, F.col("__n.a").alias("a"), F.col("__n.d").alias("d"))


def _points(column: pa.Array, m: int) -> np.ndarray:
    """A list column as rows of m numbers (rows of nulls were left out before)."""
    return column.flatten().to_numpy(zero_copy_only=False).reshape(-1, m)


def _nearest(x: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Index of and squared distance to the nearest center; ties go to the lowest index.

    The product form picks the center, within rounding; the distance is then taken by differences.
    """
    d = (c * c).sum(1)[:, None] - 2.0 * (c @ x.T)
    a, least = np.zeros(len(x), np.intp), d[0]
    for i in range(1, len(c)):
        np.copyto(a, i, where=d[i] < least)
        least = np.minimum(least, d[i])
    gap = x - c.take(a, axis=0)
    return a, np.einsum("ij,ij->i", gap, gap)


def _parts(n: int) -> Iterator[slice]:
    return (slice(at, at + _PART) for at in range(0, n, _PART))


def _add(x: np.ndarray, w: np.ndarray, runs: list[Centers], tables: list[np.ndarray]) -> None:
    """Adds weight, weighted sums and cost of the points by nearest center to each run's table."""
    for part in _parts(len(x)):
        own, mass = x[part], w[part]
        for c, out in zip(runs, tables, strict=True):
            a, d = _nearest(own, c)
            if len(c) <= _DENSE:
                rows = (a == np.arange(len(c))[:, None]) * mass
                out[:, 0] += rows.sum(axis=1)
                out[:, 1:-1] += rows @ own
                out[:, -1] += rows @ d
                continue
            out[:, 0] += np.bincount(a, mass, len(c))
            for j in range(x.shape[1]):
                out[:, 1 + j] += np.bincount(a, mass * own[:, j], len(c))
            out[:, -1] += np.bincount(a, mass * d, len(c))


def _chosen(ids: np.ndarray, x: np.ndarray, w: np.ndarray, run: tuple[Centers, float, np.uint64]) -> np.ndarray:
    """Places of the points that a salted hash of their id picks with probability share * weight * squared distance."""
    centers, share, salt = run
    with np.errstate(over="ignore"):
        hashed = mix64(mix64(ids.view(np.uint64) ^ salt) + np.uint64(0x9E3779B97F4A7C15))
    u = ((hashed >> np.uint64(11)) + 0.5) / float(1 << 53)
    d = np.concatenate([np.zeros(0), *[_nearest(x[p], centers)[1] for p in _parts(len(x))]])
    return np.flatnonzero(u < share * w * d)


def _blocks(df: DataFrame, m: int) -> DataFrame:
    """(id, x, w) rows as (block): the ids, weights and values of a batch of points, end to end."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                x, w = _points(batch.column(1), m), batch.column(2).to_numpy(zero_copy_only=False)
                block = batch.column(0).to_numpy().tobytes() + w.tobytes() + x.tobytes()
                yield pa.RecordBatch.from_pydict({"block": pa.array([block], pa.binary())})

    return df.mapInArrow(pack, "block binary")


def _unpacked(blocks: Iterator, m: int, live: bool = False) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """ids, x and w of each block; with ``live`` weights that aren't above 0 are 0."""
    for block in blocks:
        own = np.frombuffer(block, np.int64)
        n = len(own) // (m + 2)
        w = own[n : 2 * n].view(float)
        yield own[:n], own[2 * n :].view(float).reshape(n, m), np.where(w > 0, w, 0.0) if live else w


def packed_sums(blocks: RDD, runs: list[Centers], live: bool = False) -> list[np.ndarray]:
    """What ``cluster_sums`` has, from packed points: blocks pass to Python as they are, and no query is planned."""
    m, sent = runs[0].shape[1], blocks.context.broadcast(runs)

    def fold(own: Iterator[bytes]) -> Iterator[list[np.ndarray]]:
        tables = [np.zeros((len(c), m + 2)) for c in sent.value]
        for _, x, w in _unpacked(own, m, live):
            _add(x, w, sent.value, tables)
        yield tables

    def both(a: list[np.ndarray], b: list[np.ndarray]) -> list[np.ndarray]:
        return [x + y for x, y in zip(a, b, strict=True)]

    found = blocks.mapPartitions(fold)
    out = reduce(both, found.collect()) if blocks.getNumPartitions() <= _COLLECTED else found.treeReduce(both)
    sent.unpersist()
    return out


def sums_frame(
    df: DataFrame, sent: Broadcast, m: int, weight: str | None = None, radius: float | None = None
) -> DataFrame:
    """(c, v): the numbers of all centers' tables, laid end to end. The plan doesn't depend on the centers."""

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables = [np.zeros((len(c), m + 2)) for c in sent.value]
        for batch in batches:
            x = _points(batch.column(0), m)
            if radius is not None:
                x = x.clip(-radius, radius)
            w = batch.column(1).to_numpy(zero_copy_only=False)
            _add(x, w, sent.value, tables)
        flat = np.concatenate([t.ravel() for t in tables])
        yield pa.RecordBatch.from_pydict({"c": pa.array(range(len(flat)), pa.int32()), "v": pa.array(flat)})

    w = F.col(weight) if weight else F.lit(1.0)
    rows = df.where(F.col("x").isNotNull()).select("x", w.cast("double").alias("w"))
    return rows.mapInArrow(fold, "c int, v double").groupBy("c").agg(F.sum("v").alias("v"))


def cluster_sums(
    df: DataFrame | RDD, runs: list[Centers], weight: str | None = None, radius: float | None = None, live: bool = False
) -> list[np.ndarray]:
    """For each set of centers a (k, m + 2) array of weight, weighted sums and cost; all runs in one pass.

    With ``radius`` every value is cut to [-radius, radius] first, which bounds what one user can change. An RDD is
    one of packed points, which has its weights.
    """
    runs = [np.asarray(c, float) for c in runs]
    if isinstance(df, RDD):
        return packed_sums(df, runs, live)
    m = runs[0].shape[1]
    cuts = np.cumsum([0, *[len(c) * (m + 2) for c in runs]])
    sent = df.sparkSession.sparkContext.broadcast(runs)
    flat = np.zeros(cuts[-1])
    for row in sums_frame(df, sent, m, weight, radius).collect():
        flat[row["c"]] = row["v"]
    sent.unpersist()
    return [flat[a:b].reshape(-1, m + 2) for a, b in zip(cuts[:-1], cuts[1:], strict=True)]


def cost(df: DataFrame, centers: Centers, weight: str | None = None) -> float:
    """Sum of (weighted) squared distances to the nearest center."""
    return float(cluster_sums(df, [np.asarray(centers)], weight)[0][:, -1].sum())


def mean_cost(df: DataFrame, centers: Centers) -> float:
    """Cost a point: the headline loss."""
    sums = cluster_sums(df, [np.asarray(centers)])[0]
    return float(sums[:, -1].sum() / max(sums[:, 0].sum(), 1.0))


def weighted_kmeans(
    points: np.ndarray, weights: np.ndarray, k: int, seed: int = 0, n_init: int = 8, max_iter: int = 100
) -> Centers:
    """k-means++ and Lloyd on points in memory, best of ``n_init``; for grids and leaves of bounded number."""
    rng = np.random.default_rng(seed)
    keep = weights > 0
    if not keep.any():
        keep, weights = np.ones(len(points), bool), np.ones(len(points))
    p, w = points[keep], weights[keep]
    best, least = None, np.inf
    for _ in range(n_init):
        c = p[[rng.choice(len(p), p=w / w.sum())]]
        while len(c) < k:
            d = ((p[:, None] - c[None]) ** 2).sum(2).min(1) * w
            nxt = rng.choice(len(p), p=d / d.sum()) if d.sum() > 0 else rng.integers(len(p))
            c = np.vstack([c, p[nxt]])
        for _ in range(max_iter):
            a = ((p[:, None] - c[None]) ** 2).sum(2).argmin(1)
            mass = np.bincount(a, w, k)
            sums = np.stack([np.bincount(a, w * p[:, j], k) for j in range(p.shape[1])], 1)
            new = np.where(mass[:, None] > 0, sums / np.maximum(mass, 1e-300)[:, None], c)
            if np.abs(new - c).max() < 1e-9:
                break
            c = new
        total = (((p[:, None] - c[None]) ** 2).sum(2).min(1) * w).sum()
        if total < least:
            best, least = c, total
    return best


def _keyed(df: DataFrame, weight: str | None) -> DataFrame:
    """(id, x, w) of all points; ids that aren't integers are hashed."""
    w = F.col(weight) if weight else F.lit(1.0)
    key = F.col("id") if dict(df.dtypes)["id"] == "bigint" else F.xxhash64("id")
    return df.where(F.col("x").isNotNull()).select(key.alias("id"), "x", w.cast("double").alias("w"))


def _picked(blocks: RDD, runs: list[tuple[Centers, float, int]]) -> list[np.ndarray]:
    """For each run of (centers, factor, salt) the points that a salted hash of their id picks with probability
    factor * weight * squared distance; one pass over the packed points for all runs."""
    m = runs[0][0].shape[1]
    sent = blocks.context.broadcast([(c, factor, np.uint64(salt)) for c, factor, salt in runs])

    def pick(own: Iterator[bytes]) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        for ids, x, w in _unpacked(own, m, live=True):
            for r, run in enumerate(sent.value):
                at = _chosen(ids, x, w, run)
                if len(at):
                    yield r, ids[at], x[at]

    got = blocks.mapPartitions(pick).collect()
    sent.unpersist()
    out = []
    for r in range(len(runs)):
        ids = np.concatenate([np.zeros(0, np.int64), *[i for q, i, _ in got if q == r]])
        x = np.concatenate([np.zeros((0, m)), *[p for q, _, p in got if q == r]])
        out.append(x[np.argsort(ids, kind="stable")])
    return out


def seed_centers(
    df: DataFrame, k: int, seeds: list[int], method: str = "parallel", rounds: int = 3, weight: str | None = None
) -> list[Centers]:
    """Start centers for each seed, all in the same passes: ``random`` (hash order) or ``parallel`` (oversampling
    rounds, then k-means++ on what they found).

    A round of oversampling picks 2k points on average, and all of them are kept. Picks are by a hash of the id, so
    they don't depend on the partitioning.
    """
    runs, _ = _first(df, k, seeds, method, weight)
    if method == "random":
        return runs
    with _passes(df, weight, runs[0].shape[-1]) as points:
        return _oversampled(points, runs, k, seeds, rounds)


def _first(df: DataFrame, k: int, seeds: list[int], method: str, weight: str | None) -> tuple[list[Centers], int]:
    """For each seed k points (``random``) or one, by the order of a hash of the id, and how many points there are."""
    known = df.where(F.col("x").isNotNull())
    live = F.lit(True) if weight is None else F.col(weight) > 0
    if method == "random":
        order = [known.where(live).orderBy(F.xxhash64("id", F.lit(s))).limit(k).select("x").collect() for s in seeds]
        return [np.array([r["x"] for r in rows]) for rows in order], known.count()
    at = [F.when(live, F.xxhash64("id", F.lit(s))) for s in seeds]
    first = known.agg(F.count(F.lit(1)).alias("n"), *[F.min_by("x", h).alias(f"x{i}") for i, h in enumerate(at)]).first()
    return [np.array([first[f"x{i}"]]) for i in range(len(seeds))], first["n"]


class _Passes:
    """Passes over packed points, a Spark job each."""

    def __init__(self, blocks: RDD, positive: bool = False):
        self.blocks, self.positive = blocks, positive

    def live(self) -> _Passes:
        return _Passes(self.blocks, True)

    def sums(self, runs: list[Centers]) -> list[np.ndarray]:
        return cluster_sums(self.blocks, runs, live=self.positive)

    def picked(self, runs: list[tuple[Centers, float, int]]) -> list[np.ndarray]:
        return _picked(self.blocks, runs)


@contextmanager
def _passes(df: DataFrame, weight: str | None, m: int, keyed: bool = True) -> Iterator[_Passes]:
    """The points are packed once, and rounds read the blocks (kept in memory or on the executors' disks)."""
    rows = _keyed(df if keyed else df.withColumn("id", F.lit(0).cast("bigint")), weight)
    blocks = _blocks(rows, m).rdd.map(lambda row: bytes(row[0])).persist(StorageLevel.MEMORY_AND_DISK)
    try:
        yield _Passes(blocks)
    finally:
        blocks.unpersist()


class _Points:
    """The same passes over points in one task's memory."""

    def __init__(self, ids: np.ndarray, x: np.ndarray, w: np.ndarray):
        self.ids, self.x, self.w = ids, x, w

    def live(self) -> _Points:
        keep = self.w > 0
        return self if keep.all() else _Points(self.ids[keep], self.x[keep], self.w[keep])

    def sums(self, runs: list[Centers]) -> list[np.ndarray]:
        runs = [np.asarray(c, float) for c in runs]
        tables = [np.zeros((len(c), self.x.shape[1] + 2)) for c in runs]
        _add(self.x, self.w, runs, tables)
        return tables

    def picked(self, runs: list[tuple[Centers, float, int]]) -> list[np.ndarray]:
        out = []
        for c, factor, salt in runs:
            at = _chosen(self.ids, self.x, self.w, (c, factor, np.uint64(salt)))
            out.append(self.x[at[np.argsort(self.ids[at], kind="stable")]])
        return out


class _SumsFold(Fold):
    """``cluster_sums`` of some columns."""

    def __init__(self, places: tuple[int, ...], runs: list[Centers]):
        self.places, self.runs = places, [np.asarray(c, float) for c in runs]
        self.tables = [np.zeros((len(c), len(places) + 2)) for c in runs]

    def add(self, block: Block) -> None:
        _add(block.of(self.places), block.once("ones", lambda: np.ones(len(block))), self.runs, self.tables)

    def state(self) -> list[np.ndarray]:
        return self.tables

    @staticmethod
    def both(a: list[np.ndarray], b: list[np.ndarray]) -> list[np.ndarray]:
        return [x + y for x, y in zip(a, b, strict=True)]


class _PickedFold(Fold):
    """The points that ``_chosen`` finds for each run: (run, ids, points)."""

    def __init__(self, places: tuple[int, ...], runs: list[tuple[Centers, float, int]]):
        self.places, self.runs, self.found = places, [(c, factor, np.uint64(salt)) for c, factor, salt in runs], []

    def add(self, block: Block) -> None:
        x, w = block.of(self.places), block.once("ones", lambda: np.ones(len(block)))
        for r, run in enumerate(self.runs):
            at = _chosen(block.ids, x, w, run)
            self.found.append((r, block.ids[at], x[at]))

    def state(self) -> list[tuple[int, np.ndarray, np.ndarray]]:
        return self.found


class _FirstFold(Fold):
    """For each seed the point whose id has the least ``xxhash64`` with it: (hash, point)."""

    def __init__(self, places: tuple[int, ...], seeds: list[int]):
        self.places, self.seeds, self.least = places, seeds, [None] * len(seeds)

    def add(self, block: Block) -> None:
        for i, seed in enumerate(self.seeds):
            hashed = spark_xxhash64(block.ids, seed)
            at = int(hashed.argmin())
            if self.least[i] is None or hashed[at] < self.least[i][0]:
                self.least[i] = int(hashed[at]), block.x[at, list(self.places)]

    def state(self) -> list[tuple[int, np.ndarray] | None]:
        return self.least

    @staticmethod
    def both(a: list, b: list) -> list:
        return [min((v for v in pair if v is not None), key=lambda v: v[0], default=None) for pair in zip(a, b, strict=True)]


def spark_xxhash64(ids: np.ndarray, seed: int) -> np.ndarray:
    """Spark's ``xxhash64(id, seed)`` of bigint ids and a literal seed, which is an int where it fits."""
    u = np.uint64
    p1, p2, p3, p4, p5 = (u(v) for v in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))

    def turned(v, r: int):
        return (v << u(r)) | (v >> u(64 - r))

    def mixed(h):
        h = (h ^ (h >> u(33))) * p2
        h = (h ^ (h >> u(29))) * p3
        return h ^ (h >> u(32))

    def of_long(v, start):
        return mixed(turned((start + p5 + u(8)) ^ (turned(v * p2, 31) * p1), 27) * p1 + p4)

    with np.errstate(over="ignore"):
        h = of_long(ids.view(u), np.full(len(ids), 42, u))
        if -(1 << 31) <= seed < 1 << 31:
            h = mixed(turned((h + p5 + u(4)) ^ (u(seed & 0xFFFFFFFF) * p1), 23) * p2 + p3)
        else:
            h = of_long(np.full(len(ids), seed & ((1 << 64) - 1), u), h)
    return h.view(np.int64)


class _Asked:
    """The passes of ``_Passes`` over columns of packed points; runs that are under way at a time share them."""

    def __init__(self, seen: Columns):
        self.seen = seen

    def live(self) -> _Asked:
        return self

    def sums(self, runs: list[Centers]) -> list[np.ndarray]:
        return self.seen.points.ask(_SumsFold(self.seen.places, runs))

    def picked(self, runs: list[tuple[Centers, float, int]]) -> list[np.ndarray]:
        got, out = self.seen.points.ask(_PickedFold(self.seen.places, runs)), []
        for r in range(len(runs)):
            ids = np.concatenate([i for q, i, _ in got if q == r])
            x = np.concatenate([p for q, _, p in got if q == r])
            out.append(x[np.argsort(ids, kind="stable")])
        return out


def _oversampled(points: _Passes | _Points | _Asked, runs: list[Centers], k: int, seeds: list[int], rounds: int = 3) -> list[Centers]:
    points = points.live()
    for r in range(rounds):
        totals = [float(s[:, -1].sum()) for s in points.sums(runs)]
        asked = [(c, 2.0 * k / t if t > 0 else 0.0, s + 1 + r) for c, t, s in zip(runs, totals, seeds, strict=True)]
        if not any(factor for _, factor, _ in asked):
            break
        runs = [np.vstack([c, more]) for c, more in zip(runs, points.picked(asked), strict=True)]
    out = []
    for c, sums, seed in zip(runs, points.sums(runs), seeds, strict=True):
        found = weighted_kmeans(c, sums[:, 0], min(k, len(c)), seed, n_init=1, max_iter=0)
        while len(found) < k:
            found = np.vstack([found, found[-1:] + 1e-6])
        out.append(found)
    return out


def _iterated(points: _Passes | _Points | _Asked, runs: list[Centers], max_iter: int, tol: float) -> Centers:
    costs = [np.inf] * len(runs)
    for _ in range(max_iter):
        sums = points.sums(runs)
        new = [np.where(s[:, :1] > 0, s[:, 1:-1] / np.maximum(s[:, :1], 1e-300), c) for s, c in zip(sums, runs, strict=True)]
        costs = [float(s[:, -1].sum()) for s in sums]
        moved = max(np.abs(a - b).max() for a, b in zip(new, runs, strict=True))
        runs = new
        if moved < tol:
            break
    return runs[_best(costs)]


def _best(costs: list[float]) -> int:
    """The first of the least costs. Starts that end at the same centers differ in the order of these, and in their
    costs by rounding alone, which depends on the tasks; so costs within 1e-9 are equal."""
    return int(np.argmax(np.array(costs) <= min(costs) * (1 + 1e-9)))


def _in_one_task(df: DataFrame, weight: str | None, m: int, keyed: bool, work) -> Centers:
    """What ``work`` makes of all points, which move to one task in packed blocks; only its centers reach the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, w, x = [], [], []
        for own in _unpacked((block.as_buffer() for batch in batches for block in batch.column(0)), m):
            ids.append(own[0]), x.append(own[1]), w.append(own[2])
        if ids:
            # in the order of the ids, so that sums don't depend on which block came first
            order = np.argsort(np.concatenate(ids), kind="stable")
            centers = work(_Points(np.concatenate(ids)[order], np.concatenate(x)[order], np.concatenate(w)[order]))
            yield pa.RecordBatch.from_pydict({"x": pa.array(centers.tolist(), pa.list_(pa.float64()))})

    rows = _keyed(df if keyed else df.withColumn("id", F.lit(0).cast("bigint")), weight)
    blocks = _blocks(rows, m).repartition(1)
    return np.array([r["x"] for r in blocks.mapInArrow(run, "x array<double>").collect()])


def lloyd(
    df: DataFrame | Columns, k: int, weight: str | None = None, init: Centers | None = None, max_iter: int = 30,
    tol: float = 1e-6, seed: int = 0, n_init: int = 1, method: str = "parallel",
) -> Centers:
    """Lloyd's iterations; ``n_init`` starts advance together.

    A round is one aggregate for all starts. Where all points are ONE_TASK numbers at most, one task runs all rounds
    over all of them: the same rounds, without a Spark job each. Columns of packed points are clustered from seeds of
    the parallel method, without weights.
    """
    seeds = [seed + 101 * r for r in range(n_init)]
    if isinstance(df, Columns):
        if weight or init is not None or method != "parallel":
            raise ValueError("packed points have no weights, and seeds of the parallel method")
        points = _Asked(df)
        first = [np.array([x]) for _, x in df.points.ask(_FirstFold(df.places, seeds))]
        return _iterated(points, _oversampled(points, first, k, seeds), max_iter, tol)
    if init is not None:
        runs, n = [np.asarray(init, float)], df.where(F.col("x").isNotNull()).count()
    else:
        runs, n = _first(df, k, seeds, method, weight)
    seeded = init is not None or method == "random"

    def work(points: _Passes | _Points) -> Centers:
        return _iterated(points, runs if seeded else _oversampled(points, runs, k, seeds), max_iter, tol)

    m = runs[0].shape[-1]
    if 0 < n * (m + 2) <= ONE_TASK:
        return _in_one_task(df, weight, m, not seeded, work)
    with _passes(df, weight, m, not seeded) as points:
        return work(points)


def noisy_lloyd(
    df: DataFrame, k: int, eps: float, rng: np.random.Generator, iters: int = 5, radius: float = 1.0, ledger=None, party: int = 0,
    init: Centers | None = None,
) -> Centers:
    """Private Lloyd: each round's budget goes by halves to counts (sensitivity 1) and to the m sums (radius each).

    Values are cut to the radius inside the sums, so the guarantee doesn't rest on the caller's scaling. ``init`` must
    be public.
    """
    if init is None:
        m = len(df.first()["x"])
        c = rng.uniform(-radius, radius, (k, m))
    else:
        c, m = np.asarray(init, float), np.asarray(init).shape[1]
    for _ in range(iters):
        share = eps / iters
        s = cluster_sums(df, [c], radius=radius)[0]
        mass = s[:, 0] + rng.laplace(0, 2 / share, k)
        sums = s[:, 1:-1] + rng.laplace(0, 2 * m * radius / share, (k, m))
        c = np.where(mass[:, None] > 1, sums / np.maximum(mass, 1)[:, None], c).clip(-radius, radius)
        if ledger is not None:
            ledger.charge(party, "local centers", share)
    return c
