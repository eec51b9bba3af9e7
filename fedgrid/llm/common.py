"""Shared helpers of the corpus operators: table loading, hold-out masks, samples by hash, lineage cuts."""

from __future__ import annotations

import ctypes
import gc
import re
from collections.abc import Callable
from functools import wraps
from typing import Any

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fedgrid.checkpoints import checkpointed, stored

__all__ = ["checkpointed", "crc_mod", "hash_share", "kept", "named", "shielded", "stored", "table", "trim"]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables, read through Spark only (any Hadoop path works)."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def crc_mod(key: str | Column, modulus: int) -> Column:
    """crc32 of the key as text, modulo ``modulus``; null keys count as remainder -1."""
    col = F.col(key) if isinstance(key, str) else key
    return F.coalesce(F.crc32(col.cast("string").cast("binary")) % modulus, F.lit(-1))


def hash_share(key: str | Column, share: Column | float) -> Column:
    """True for a ``share`` of the keys, always the same ones (a partition-independent sample)."""
    col = F.col(key) if isinstance(key, str) else key
    return F.pmod(F.xxhash64(col), F.lit(1_000_003)) < share * 1_000_003


def named(df: DataFrame, name: str) -> str:
    """``name`` as a helper column that ``df`` doesn't have (columns are told apart without regard to case)."""
    there = {c.lower() for c in df.columns}
    out = f"__{name}"
    while out.lower() in there:
        out = f"_{out}"
    return out


def shielded(operator: Callable[..., DataFrame]) -> Callable[..., DataFrame]:
    """For operators that keep further columns: those with names of helper columns (two underscores in front) or with
    signs in their names are called otherwise inside, and by their names again in the result."""

    @wraps(operator)
    def run(*args, **how) -> DataFrame:
        at = next(i for i, x in enumerate(args) if isinstance(x, DataFrame))
        docs = args[at]
        odd = [c for c in docs.columns if c.startswith("__") or not re.fullmatch(r"[A-Za-z0-9_]+", c)]
        there = {c.lower() for c in docs.columns}
        inside = {c: next(n for n in (f"kept{i}{'x' * k}" for k in range(len(there) + 1)) if n not in there) for i, c in enumerate(odd)}
        if not inside:
            return operator(*args, **how)
        out = operator(*args[:at], docs.withColumnsRenamed(inside), *args[at + 1 :], **how)
        return out.withColumnsRenamed({n: c for c, n in inside.items() if n in out.columns})

    return run


def trim() -> None:
    """Gives free memory of this Python worker back to the machine, where its C library can (glibc)."""
    import pyarrow as pa

    gc.collect()
    pa.default_memory_pool().release_unused()
    release = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if release is not None:
        release(0)


#: What the operator at work keeps in this Python worker from task to task.
_KEPT: dict[str, Any] = {}


def kept(owner: str, make: Callable[[], Any] = bool) -> Any:
    """The worker's table of ``owner``, made on first use.

    The tables of other operators go then: a worker outlives the stage that filled them, and must not carry them
    into the next one.
    """
    if owner not in _KEPT:
        _KEPT.clear()
        trim()
        _KEPT[owner] = make()
    return _KEPT[owner]
