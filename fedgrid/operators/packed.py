"""Points of an experiment, packed once and kept, for everything that its runs add up over all of them.

A step asks for a ``Fold``: what it adds up over the points, task by task. Steps that ask while a Spark job is under
way meet in the next one, so runs in threads share their passes, and no query is planned for a pass.
"""

from __future__ import annotations

import pickle
import time
from collections.abc import Iterator
from concurrent.futures import Future
from dataclasses import dataclass
from functools import reduce
from threading import Condition

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Seconds that a pass waits for steps that are about to ask too.
LINGER = 0.02
#: Tasks up to which their states meet at the driver at once.
_COLLECTED = 256


def tasks(spark: SparkSession) -> int:
    """Tasks of a pass: two a core. A session's default would cut small tables into hundreds of tasks."""
    return max(2 * spark.sparkContext.defaultParallelism, 16)


class Block:
    """Some of the points: ``ids``, labels ``y`` and all columns ``x``; what several folds need of them is made once."""

    def __init__(self, ids: np.ndarray, y: np.ndarray, x: np.ndarray):
        self.ids, self.y, self.x = ids, y, x
        self.made: dict[tuple, object] = {}

    @classmethod
    def unpacked(cls, raw: bytes, m: int) -> Block:
        own = np.frombuffer(raw, np.int64)
        n = len(own) // (m + 2)
        return cls(own[:n], own[n : 2 * n], own[2 * n :].view(float).reshape(n, m))

    def __len__(self) -> int:
        return len(self.ids)

    def once(self, key: tuple, make):
        if key not in self.made:
            self.made[key] = make()
        return self.made[key]

    @property
    def columns(self) -> list[np.ndarray]:
        return self.once(("columns",), lambda: list(np.ascontiguousarray(self.x.T)))

    def of(self, places: tuple[int, ...]) -> np.ndarray:
        if places == tuple(range(self.x.shape[1])):
            return self.x
        return self.once(("of", places), lambda: np.ascontiguousarray(self.x[:, list(places)]))


class Fold:
    """What a step adds up; ``state`` is what leaves a task, and ``both`` adds two of them.

    Folds that come ``last`` wait for a pass without others, so that more of them meet and have work in common.
    """

    last = False

    def add(self, block: Block) -> None:
        raise NotImplementedError

    @classmethod
    def add_all(cls, folds: list[Fold], block: Block) -> None:
        """Folds of one class take a block together, where they have work in common."""
        for f in folds:
            f.add(block)

    def state(self):
        raise NotImplementedError

    @staticmethod
    def both(a, b):
        return a + b


class _Ids(Fold):
    """Numbers of points, null ids, points with missing values and repeats of an id (all of one id are in one task)."""

    def __init__(self):
        self.ids = []

    def add(self, block: Block) -> None:
        self.ids.append(block.ids)

    def state(self) -> np.ndarray:
        n = sum(map(len, self.ids))
        return np.array([n, n - len(np.unique(np.concatenate(self.ids))) if n else 0])


class Packed:
    """The points of ``df`` (id, columns ``names``, y), validated: no null or repeated id, no null or NaN.

    Where ids only draw the first centers (not ``unique``), one may come several times, as points of their own.
    """

    def __init__(self, df: DataFrame, names: list[str], unique: bool = True):
        self.names, self.m = tuple(names), len(names)
        self.state, self.queue, self.busy = Condition(), [], False
        spark, m = df.sparkSession, self.m
        x = F.array(*[F.col(c).cast("double") for c in names])
        y = F.col("y").cast("bigint") if "y" in df.columns else F.lit(0).cast("bigint")
        rows = df.select(F.col("id").cast("bigint").alias("id"), y.alias("y"), x.alias("x"))

        def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                if not batch.num_rows:
                    continue
                ids, y = batch.column(0), batch.column(1).fill_null(-1).to_numpy()
                x = batch.column(2).flatten().to_numpy(zero_copy_only=False).astype(float, copy=False).reshape(-1, m)
                bad, nulls = int(np.isnan(x).any(axis=1).sum()), ids.null_count
                block = ids.fill_null(0).to_numpy().tobytes() + y.tobytes() + x.tobytes()
                columns = [pa.array([block], pa.binary()), pa.array([nulls], pa.int64()), pa.array([bad], pa.int64())]
                yield pa.RecordBatch.from_arrays(columns, names=["block", "nulls", "bad"])

        made = rows.mapInArrow(pack, "block binary, nulls bigint, bad bigint").rdd
        kept = made.map(lambda r: (bytes(r[0]), r[1], r[2])).persist(StorageLevel.MEMORY_AND_DISK)
        self.spark, self.kept, self.blocks = spark, kept, kept.map(lambda r: r[0])
        counts = kept.map(lambda r: (r[1], r[2], len(r[0]) // (8 * (m + 2))))
        nulls, bad, self.n = counts.fold((0, 0, 0), lambda a, b: tuple(x + y for x, y in zip(a, b, strict=True)))
        if nulls or bad:
            self.unpersist()
            raise ValueError(f"{nulls} null ids and {bad} rows with missing values")
        if unique and self.ask(_Ids())[1]:
            self.unpersist()
            raise ValueError("an id occurs twice")

    def unpersist(self) -> None:
        self.kept.unpersist()

    def ask(self, fold: Fold):
        """The fold's state over all points, from a pass that takes all who ask by then."""
        mine = Future()
        with self.state:
            self.queue.append((fold, mine))
        while True:
            with self.state:
                while self.busy and not mine.done():
                    self.state.wait()
                if mine.done():
                    return mine.result()
                self.busy = True
            try:
                time.sleep(LINGER)
                with self.state:
                    batch = [one for one in self.queue if not one[0].last] or self.queue
                    self.queue = [one for one in self.queue if one not in batch]
                self._pass(batch)
            finally:
                with self.state:
                    self.busy = False
                    self.state.notify_all()

    def _pass(self, batch: list[tuple[Fold, Future]]) -> None:
        m, sent = self.m, self.spark.sparkContext.broadcast(pickle.dumps([f for f, _ in batch]))

        def run(raw: Iterator[bytes]) -> Iterator[list]:
            folds, kinds = pickle.loads(sent.value), {}  # anew: a worker keeps what it was sent for its next task
            for f in folds:
                kinds.setdefault(type(f), []).append(f)
            for one in raw:
                block = Block.unpacked(one, m)
                for kind, own in kinds.items():
                    kind.add_all(own, block)
            yield [f.state() for f in folds]

        kinds = [type(f) for f, _ in batch]

        def both(a: list, b: list) -> list:
            return [kind.both(x, y) for kind, x, y in zip(kinds, a, b, strict=True)]

        try:
            found = self.blocks.mapPartitions(run)
            out = reduce(both, found.collect()) if found.getNumPartitions() <= _COLLECTED else found.treeReduce(both)
            for (_, future), got in zip(batch, out, strict=True):
                future.set_result(got)
        except BaseException as error:
            for _, future in batch:
                if not future.done():
                    future.set_exception(error)
        finally:
            sent.unpersist()


def closest(columns: list[np.ndarray], centers: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Index of and squared distance to the nearest center by differences, as ``assign`` has them."""
    a, least = np.zeros(len(columns[0]), np.int64), None
    for i, center in enumerate(centers.tolist()):
        d = (columns[0] - center[0]) ** 2
        for own, v in zip(columns[1:], center[1:], strict=True):
            gap = own - v
            d += gap * gap
        if least is None:
            least = d
        else:
            np.copyto(a, i, where=d < least)
            least = np.minimum(least, d)
    return a, least


@dataclass(frozen=True)
class Columns:
    """Some columns of packed points: what a party (or a central method) sees of them."""

    points: Packed
    places: tuple[int, ...]

    def count(self) -> int:
        return self.points.n

    def __reduce__(self):  # tasks are sent the places alone
        return Columns, (None, self.places)


@dataclass(frozen=True)
class Labels:
    """Each point's nearest of the centers of a party."""

    seen: Columns
    centers: np.ndarray

    def of(self, block: Block) -> np.ndarray:
        key = "near", self.seen.places, self.centers.tobytes()
        return block.once(key, lambda: closest([block.columns[j] for j in self.seen.places], self.centers))[0]
