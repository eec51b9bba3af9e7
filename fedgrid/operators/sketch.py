"""Maximum-of-geometric sketches: hashing, distributed building, union, and the private partition sketch.

The geometric value falls with the hash, so the maximum over a set is a transform of the minimum hash, and the
logarithm is taken once per sketch cell instead of once per user and key. Each task folds its users into one
(clusters x repeats) table of minima; tables are cut into pieces of PIECE keys, and the pieces meet in two streamed
reductions that keep one running minimum for each piece, however many tasks there are.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fedgrid.functions.columns import TWO60, geometric_base2, geometric_from_uniform, md5_hash60
from fedgrid.operators.packed import Block, Fold, Labels
from fedgrid.privacy import HashKeys, SketchParams, floor_value, phantoms, sketch_epsilon

_U = np.uint64
_CHUNK, _KEYS = 4096, 64
#: Keys in one shuffled piece of a table (2 KB), and the ways that the first reduction is dealt over.
PIECE, SLOTS = 256, 64


def mix64(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


def fold_minima(ids: np.ndarray, labels: np.ndarray, keys: np.ndarray, out: np.ndarray) -> None:
    """Lowers ``out`` (clusters x keys) to the users' keyed hashes; blocks stay within the CPU's caches."""
    with np.errstate(over="ignore"):
        for at in range(0, len(ids), _CHUNK):
            order = np.argsort(labels[at : at + _CHUNK], kind="stable")
            own = mix64(ids[at : at + _CHUNK][order].view(np.uint64) + _U(0x9E3779B97F4A7C15))
            lab = labels[at : at + _CHUNK][order]
            cuts = np.flatnonzero(np.diff(lab, prepend=-1))
            for k in range(0, len(keys), _KEYS):
                hashed = mix64(own[:, None] ^ keys[None, k : k + _KEYS])
                least = np.minimum.reduceat(hashed, cuts, axis=0)
                part = out[lab[cuts], k : k + _KEYS]
                out[lab[cuts], k : k + _KEYS] = np.minimum(part, least)


class MinimaFold(Fold):
    """``minima`` of one labelling of packed points; labellings with the same keys hash the users once.

    A hash can lower some table only below the largest of the tables' minima, so after a label's first users (``FIRST``
    of them, folded as they are) only hashes below it are looked at, labelling by labelling.
    """

    FIRST, USERS, KEYS = 64, 4096, 8
    last = True

    def __init__(self, labels: Labels, keys: HashKeys, k_local: int):
        self.labels, self.keys = labels, keys
        self.seen, self.table = np.zeros(k_local, np.int64), np.full((k_local, len(keys.array())), np.iinfo(np.uint64).max, np.uint64)

    @classmethod
    def add_all(cls, folds: list[MinimaFold], block: Block) -> None:
        groups: dict[HashKeys, list[MinimaFold]] = {}
        for f in folds:
            groups.setdefault(f.keys, []).append(f)
        for keys, own in groups.items():
            cls._fold(own, block, keys.array())

    @classmethod
    def _fold(cls, folds: list[MinimaFold], block: Block, keys: np.ndarray) -> None:
        labels = [f.labels.of(block) for f in folds]
        for f, lab in zip(folds, labels, strict=True):
            early = [np.flatnonzero(lab == a)[: cls.FIRST - n] for a, n in enumerate(f.seen.tolist()) if n < cls.FIRST]
            at = np.concatenate([np.zeros(0, np.int64), *early])
            if len(at):
                fold_minima(block.ids[at], lab[at], keys, f.table)
            f.seen += np.bincount(lab, minlength=len(f.seen))
        h, t, low = *np.empty((2, cls.KEYS, cls.USERS), np.uint64), np.empty((cls.KEYS, cls.USERS), bool)
        with np.errstate(over="ignore"):
            own = mix64(block.ids.view(np.uint64) + _U(0x9E3779B97F4A7C15))
            for start in range(0, len(own), cls.USERS):
                users = own[start : start + cls.USERS]
                here = [lab[start : start + cls.USERS] for lab in labels]
                # users of labels that are still below FIRST are in the tables already
                later = [[c for c in np.unique(a) if f.seen[c] >= cls.FIRST] for f, a in zip(folds, here, strict=True)]
                if not any(later):
                    continue
                most = np.max([f.table[c].max(axis=0) for f, c in zip(folds, later, strict=True) if c], axis=0)
                most |= _U((1 << 33) - 1)  # the hash's last step leaves its upper 31 bits as they are
                n, found = len(users), []
                for k in range(0, len(keys), cls.KEYS):
                    own_keys = keys[k : k + cls.KEYS, None]
                    x, y, z = (v.ravel()[: len(own_keys) * n].reshape(-1, n) for v in (h, t, low))
                    _mix_into(np.bitwise_xor(users, own_keys, out=x), y)
                    np.less_equal(x, most[k : k + cls.KEYS, None], out=z)
                    at = np.flatnonzero(z.ravel())
                    found.append((at + k * n, x.ravel()[at]))
                place, hashed = (np.concatenate(v) for v in zip(*found, strict=True))
                row, col = np.divmod(place, n)
                hashed ^= hashed >> _U(31)
                for f, a in zip(folds, here, strict=True):
                    np.minimum.at(f.table.ravel(), a[col] * len(keys) + row, hashed)

    def state(self) -> np.ndarray:
        return self.table

    @staticmethod
    def both(a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return np.minimum(a, b)


def _mix_into(x: np.ndarray, spare: np.ndarray) -> None:
    """``mix64`` in place, but for its last step."""
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        np.right_shift(x, _U(shift), out=spare)
        np.bitwise_xor(x, spare, out=x)
        np.multiply(x, _U(factor), out=x)


def minima(labels: DataFrame | Labels, keys: HashKeys, k_local: int) -> np.ndarray:
    """(k_local x repeats) minimum hashes of (id, a) rows; all ones where a cluster is empty.

    Ids that aren't integers are hashed to 64 bits first.
    """
    if isinstance(labels, Labels):
        return labels.seen.points.ask(MinimaFold(labels, keys, k_local))
    ids = F.col("id") if dict(labels.dtypes)["id"] == "bigint" else F.xxhash64("id")
    values = keys.array()
    empty = np.iinfo(np.uint64).max
    rows = labels.select(ids.alias("id"), F.col("a").cast("int").alias("a"))
    schema = "slot int, a int, piece int, m binary"
    cuts = range(0, len(values), PIECE)

    def batch_of(rows: list[tuple[int, int, int, np.ndarray]]) -> pa.RecordBatch:
        slot, a, piece, m = zip(*rows, strict=True)
        columns = [pa.array(v, pa.int32()) for v in (slot, a, piece)] + [pa.array([x.tobytes() for x in m], pa.binary())]
        return pa.RecordBatch.from_arrays(columns, names=["slot", "a", "piece", "m"])

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = np.full((k_local, len(values)), empty, np.uint64)
        seen = False
        for batch in batches:
            if batch.num_rows:
                seen = True
                fold_minima(batch.column(0).to_numpy(), batch.column(1).to_numpy(), values, table)
        if seen:
            slot = int(mix64(table[:, 0]).sum() % _U(SLOTS))
            yield batch_of([(slot, a, c // PIECE, table[a, c : c + PIECE]) for a in range(k_local) for c in cuts])

    def least(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # pieces of any slots and clusters, one after the other
        kept: dict[tuple[int, int, int], np.ndarray] = {}
        for batch in batches:
            for *key, m in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
                own = np.frombuffer(m, np.uint64)
                held = kept.get(tuple(key))
                if held is None:
                    kept[tuple(key)] = own.copy()
                else:
                    np.minimum(held, own, out=held)
        if kept:
            yield batch_of([(0, a, piece, own) for (_, a, piece), own in kept.items()])

    parts = rows.mapInArrow(partial, schema)
    parts = parts.repartition("slot", "a", "piece").mapInArrow(least, schema)
    parts = parts.repartition("a", "piece").mapInArrow(least, schema)
    out = np.full((k_local, len(values)), empty, np.uint64)
    for row in parts.collect():  # k_local tables in pieces
        at = row["piece"] * PIECE
        out[row["a"], at : at + PIECE] = np.frombuffer(row["m"], np.uint64)
    return out


def values_of(least: np.ndarray, gamma: float) -> np.ndarray:
    """Maxima of geometric values from minimum hashes, 0 where the set is empty; repeats x clusters."""
    u = (least.astype(np.float64) + 1.0) / 2.0**64
    alpha = np.maximum(np.ceil(-np.log(u) / math.log1p(gamma)), 1).astype(np.int32)
    alpha[least == np.iinfo(np.uint64).max] = 0
    return alpha.T


def union(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.maximum(a, b)


def phantom_maxima(shape: tuple[int, ...], n: int, gamma: float, rng: np.random.Generator) -> np.ndarray:
    """Maxima of n geometric values, one draw each by the inverse of the maximum's distribution."""
    log_u = np.log(rng.uniform(1e-300, 1.0, shape)) / n
    tail = -np.expm1(log_u)
    return np.maximum(np.ceil(-np.log(np.maximum(tail, 1e-300)) / math.log1p(gamma)), 1).astype(np.int32)


def privatise(alpha: np.ndarray, eps_row: float, gamma: float, rng: np.random.Generator) -> np.ndarray:
    """The largest of real value, phantoms and floor, cell by cell."""
    ghosts = phantom_maxima(alpha.shape, phantoms(eps_row), gamma, rng)
    return np.maximum(np.maximum(alpha, ghosts), floor_value(eps_row, gamma))


def partition_sketch(
    labels: DataFrame, k_local: int, eps2: float, delta2: float, params: SketchParams, rng: np.random.Generator,
    calibration: str = "published", ledger=None, party: int = 0, least: np.ndarray | None = None,
) -> np.ndarray:
    """A party's private membership message: repeats x clusters. Empty clusters look like all others.

    ``least`` are the labels' minimum hashes, where they are known.
    """
    eps_row = sketch_epsilon(eps2, delta2, params.repeats, calibration)
    alpha = values_of(minima(labels, params.keys, k_local) if least is None else least, params.gamma)
    if ledger is not None:
        ledger.charge(party, "membership", eps2, delta2)
    return privatise(alpha, eps_row, params.gamma, rng)


def sketch_rows(labels: DataFrame, repeats: int, gamma: float, by: tuple[str, ...] = ("a",)) -> DataFrame:
    """The same sketch in plain DataFrame form over md5 hashes, (by.., i, alpha): for small numbers of repeats.

    The minimum hash is taken first, and one logarithm of it then.
    """
    keyed = labels.select("id", *by, F.explode(F.sequence(F.lit(1), F.lit(repeats))).alias("i"))
    text = F.concat_ws("|", F.col("id").cast("string"), F.col("i").cast("string"))
    least = keyed.groupBy(*by, "i").agg(F.min(md5_hash60(text)).alias("h"))
    if gamma == 1.0:
        value = geometric_base2(F.col("h"))
    else:
        value = geometric_from_uniform((F.col("h") + 1) / F.lit(TWO60), gamma)
    return least.select(*by, "i", value.alias("alpha"))


def collected(rows: DataFrame, k: int, repeats: int) -> np.ndarray:
    """One party's sketch rows (a, i, alpha) as a (repeats x clusters) table, 0 where a set is empty."""
    out = np.zeros((repeats, k), np.int32)
    for r in rows.collect():  # repeats * k rows
        out[r["i"] - 1, r["a"]] = r["alpha"]
    return out


def sketch_arrays(rows: DataFrame, by: list[str]) -> DataFrame:
    """Long sketch rows to one array of values per set, ordered by repeat."""
    packed = rows.groupBy(*by).agg(F.array_sort(F.collect_list(F.struct("i", "alpha"))).alias("s"))
    return packed.select(*by, F.transform("s", lambda e: e["alpha"]).alias("alpha"))
