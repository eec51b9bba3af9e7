"""Per-user randomized reports: generalized response and optimized local hashing, and their decoding."""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fedgrid.functions.columns import TWO60, md5_hash60, md5_uniform
from fedgrid.operators.packed import Block, Fold, Labels


def choose(eps: float, k: int) -> str:
    """Generalized response while the domain is small for the budget, else local hashing."""
    return "grr" if k < 3 * math.exp(eps) + 2 else "olh"


def buckets(eps: float) -> int:
    return max(2, round(math.exp(eps)) + 1)


def grr(labels: DataFrame, k: int, eps: float, seed: str) -> DataFrame:
    """(id, y): the label kept with probability e^eps / (e^eps + k - 1), else one of the others.

    Drawn by keyed hashes of the id, so a report doesn't depend on partitioning.
    """
    keep = math.exp(eps) / (math.exp(eps) + k - 1)
    other = F.pmod(md5_hash60(F.concat_ws("|", F.lit(seed + "o"), F.col("id").cast("string"))), F.lit(max(k - 1, 1)))
    moved = F.pmod(F.col("a") + 1 + other, F.lit(k))
    y = F.when(md5_uniform(F.lit(seed), "id") <= keep, F.col("a")).otherwise(moved)
    return labels.select("id", y.cast("int").alias("y"))


@dataclass(frozen=True)
class Reports:
    """The reports of ``grr`` on labels of packed points: the same keyed hashes, so the same reports."""

    labels: Labels
    k: int
    eps: float
    seed: str

    def of(self, block: Block) -> np.ndarray:
        key = "grr", self.labels.seen.places, self.labels.centers.tobytes(), self.k, self.eps, self.seed
        return block.once(key, lambda: self._drawn(block.ids, self.labels.of(block)))

    def _drawn(self, ids: np.ndarray, a: np.ndarray) -> np.ndarray:
        def hashed(seed: str) -> np.ndarray:
            start = hashlib.md5(f"{seed}|".encode())
            out = np.empty(len(ids), np.int64)
            for i, own in enumerate(ids.tolist()):
                h = start.copy()
                h.update(b"%d" % own)
                out[i] = int(h.hexdigest()[:15], 16)
            return out

        keep = math.exp(self.eps) / (math.exp(self.eps) + self.k - 1)
        moved = np.flatnonzero((hashed(self.seed) + 1) / TWO60 > keep)
        y = a.copy()
        ids = ids[moved]  # the others' second hashes aren't looked at
        y[moved] = (a[moved] + 1 + hashed(self.seed + "o") % max(self.k - 1, 1)) % self.k
        return y


class _ReportsFold(Fold):
    """Counts of report tuples."""

    def __init__(self, reports: list[Reports]):
        self.reports, self.sizes = reports, (reports[0].k,) * len(reports)
        self.counts = np.zeros(int(np.prod(self.sizes)))

    def add(self, block: Block) -> None:
        cell = np.ravel_multi_index([r.of(block) for r in self.reports], self.sizes)
        self.counts += np.bincount(cell, minlength=len(self.counts))

    def state(self) -> np.ndarray:
        return self.counts


def grr_matrix(k: int, eps: float) -> np.ndarray:
    """P(report y | label a), k x k."""
    e = math.exp(eps)
    return (np.eye(k) * (e - 1) + 1) / (e + k - 1)


def olh_hash(seed: Column, label: Column, g: int) -> Column:
    """The user's own hash of a label into g buckets."""
    return F.pmod(md5_hash60(F.concat_ws("|", seed.cast("string"), label.cast("string"))), F.lit(g)).cast("int")


def olh(labels: DataFrame, k: int, eps: float, key: str) -> DataFrame:
    """(id, seed, y): a per-user hash of the label into g buckets, reported by generalized response on g."""
    g = buckets(eps)
    keep = math.exp(eps) / (math.exp(eps) + g - 1)
    rows = labels.select("id", "a", md5_hash60(F.concat_ws("|", F.lit(key + "h"), F.col("id").cast("string"))).alias("seed"))
    own = olh_hash(F.col("seed"), F.col("a"), g)
    other = F.pmod(md5_hash60(F.concat_ws("|", F.lit(key + "o"), F.col("id").cast("string"))), F.lit(g - 1))
    y = F.when(md5_uniform(F.lit(key), "id") <= keep, own).otherwise(F.pmod(own + 1 + other, F.lit(g)))
    return rows.select("id", "seed", y.cast("int").alias("y"))


def olh_support(reports: DataFrame, k: int, eps: float) -> DataFrame:
    """(id, hits): for each label whether the user's report speaks for it."""
    g = buckets(eps)
    hits = F.array(*[(olh_hash(F.col("seed"), F.lit(a), g) == F.col("y")).cast("double") for a in range(k)])
    return reports.select("id", hits.alias("hits"))


def olh_counts(reports: DataFrame, k: int, eps: float) -> np.ndarray:
    """Users that speak for each label: the sufficient statistic of one party."""
    hits = olh_support(reports, k, eps)
    row = hits.agg(*[F.sum(F.get("hits", F.lit(a))).alias(f"n{a}") for a in range(k)]).first()
    return np.array([row[f"n{a}"] or 0.0 for a in range(k)])


def grr_counts(reports: list[DataFrame] | list[Reports], k: int) -> np.ndarray:
    """Counts of report tuples: all users collapse to k^S numbers before anything is decoded."""
    if isinstance(reports[0], Reports):
        return reports[0].labels.seen.points.ask(_ReportsFold(reports)).reshape((k,) * len(reports))
    frames = [r.select("id", F.col("y").alias(f"y{p}")) for p, r in enumerate(reports)]
    wide = frames[0]
    for f in frames[1:]:
        wide = wide.join(f, "id")
    names = [f"y{p}" for p in range(len(reports))]
    out = np.zeros((k,) * len(reports))
    for r in wide.groupBy(*names).count().collect():
        out[tuple(r[n] for n in names)] = r["count"]
    return out


def decode(counts: np.ndarray, k: int, eps: float, decoder: str = "unbiased") -> np.ndarray:
    """Cell weights from tuple counts: the inverse along each axis, or the uniform-prior posterior."""
    p = grr_matrix(k, eps)
    back = np.linalg.inv(p) if decoder == "unbiased" else (p / p.sum(axis=0, keepdims=True)).T
    for axis in range(counts.ndim):
        counts = np.moveaxis(np.tensordot(back, counts, axes=(1, axis)), 0, axis)
    return counts


def olh_weights(reports: list[DataFrame], k: int, eps: float, decoder: str = "unbiased") -> np.ndarray:
    """Cell weights from hashed reports: summed outer products of per-user support vectors.

    Users' tuples don't collapse here, so each task sums its own k^S table, and the tables are added.
    """
    g, e, s = buckets(eps), math.exp(eps), len(reports)
    keep = e / (e + g - 1)
    frames = [olh_support(r, k, eps).withColumnRenamed("hits", f"h{p}") for p, r in enumerate(reports)]
    wide = reduce(lambda x, y: x.join(y, "id"), frames)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(k**s)
        for b in batches:
            table = np.ones((b.num_rows, 1))
            for p in range(s):
                hit = b.column(p).flatten().to_numpy(zero_copy_only=False).reshape(-1, k)
                if decoder == "unbiased":
                    vec = (hit - 1.0 / g) / (keep - 1.0 / g)
                else:
                    like = np.where(hit > 0, keep, (1 - keep) / (g - 1))
                    vec = like / like.sum(1, keepdims=True)
                table = (table[:, :, None] * vec[:, None, :]).reshape(b.num_rows, -1)
            total += table.sum(0)
        yield pa.RecordBatch.from_pydict({"c": pa.array(range(k**s), pa.int32()), "w": pa.array(total)})

    parts = wide.drop("id").mapInArrow(run, "c int, w double").groupBy("c").agg(F.sum("w").alias("w"))
    out = np.zeros(k**s)
    for r in parts.collect():  # k^S rows
        out[r["c"]] = r["w"]
    return out.reshape((k,) * s)
