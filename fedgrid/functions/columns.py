"""Column functions: scaling, time features, portable hashing, geometric values, distances, noise."""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TWO60 = float(1 << 60)


def _col(c: Column | str) -> Column:
    return F.col(c) if isinstance(c, str) else c


def scale(c: Column | str, low: float, high: float, target: tuple[float, float] = (-1.0, 1.0)) -> Column:
    """Linear map of the public range [low, high] to ``target``, clipped; a range of width 0 maps to the middle."""
    lo, hi = target
    if high <= low:
        return F.when(_col(c).isNotNull(), F.lit((lo + hi) / 2))
    x = F.least(F.greatest(_col(c).cast("double"), F.lit(float(low))), F.lit(float(high)))
    scaled = F.lit(lo) + (x - F.lit(float(low))) * F.lit((hi - lo) / (high - low))
    return F.when(_col(c).isNotNull(), scaled)  # least and greatest would skip a null


def scale_to_range(
    df: DataFrame, ranges: dict[str, tuple[float, float]], target: dict[str, tuple[float, float]] | None = None
) -> DataFrame:
    """``df`` with each ranged column scaled; per-attribute targets weight attributes against each other."""
    target = target or {}
    return df.withColumns({c: scale(c, *r, target=target.get(c, (-1.0, 1.0))) for c, r in ranges.items()})


def observed_ranges(df: DataFrame, columns: list[str]) -> dict[str, tuple[float, float]]:
    """Data-derived ranges; not private, for experiments only."""
    row = df.agg(*[f(F.col(c).cast("double")).alias(f"{n}_{c}") for c in columns for n, f in (("a", F.min), ("b", F.max))])
    got = row.first()
    return {c: (got[f"a_{c}"], got[f"b_{c}"]) for c in columns}


def private_range(df: DataFrame, column: str, eps: float, low: float, high: float, rng, bins: int = 64, tail: float = 0.01):
    """A range by noisy quantiles of a histogram over the public range (eps-DP, one count per user)."""
    from fedgrid.privacy import laplace

    bucket = F.least(F.greatest(F.width_bucket(F.col(column).cast("double"), F.lit(low), F.lit(high), F.lit(bins)), F.lit(1)), F.lit(bins))
    counts = [0.0] * bins
    for r in df.where(F.col(column).isNotNull()).groupBy(bucket.alias("b")).count().collect():  # at most ``bins`` rows
        counts[r["b"] - 1] = r["count"]
    noisy = laplace(counts, 1.0, eps, rng).clip(min=0.0)
    total, step, run = noisy.sum() or 1.0, (high - low) / bins, noisy.cumsum()
    first = int((run < tail * total).sum())
    last = int((run < (1 - tail) * total).sum())
    return low + first * step, low + (last + 1) * step


def clip_upper(df: DataFrame, columns: list[str], q: float = 0.95, exact: bool = False) -> DataFrame:
    """Columns cut at their upper quantile: one aggregate pass, exact or by a bounded-error sketch."""
    measure = F.percentile if exact else (lambda c, p: F.percentile_approx(c, p, F.lit(10_000)))
    caps = df.agg(*[measure(F.col(c).cast("double"), F.lit(q)).alias(c) for c in columns]).first()
    return df.withColumns({c: F.least(F.col(c).cast("double"), F.lit(caps[c])) for c in columns if caps[c] is not None})


def week_seconds(c: Column | str) -> Column:
    """Seconds since the week began (Monday), 0 to 604800."""
    t = _col(c).cast("timestamp")
    return (F.unix_timestamp(t) - F.unix_timestamp(F.date_trunc("week", t))).cast("double")


def day_seconds(c: Column | str) -> Column:
    t = _col(c).cast("timestamp")
    return (F.unix_timestamp(t) - F.unix_timestamp(F.date_trunc("day", t))).cast("double")


def md5_hash60(c: Column) -> Column:
    """The first 15 hex digits of md5 as an integer: the same number in any SQL engine."""
    return F.conv(F.substring(F.md5(c.cast("binary")), 1, 15), 16, 10).cast("bigint")


def md5_uniform(*parts: Column | str | int) -> Column:
    """Uniform in (0, 1] from the parts' text, joined by bars."""
    text = F.concat_ws("|", *[F.lit(p) if isinstance(p, int) else _col(p).cast("string") for p in parts])
    return (md5_hash60(text) + 1) / F.lit(TWO60)


def geometric_from_uniform(u: Column, gamma: float) -> Column:
    """Value above t with probability (1 + gamma)^-t, decreasing in u."""
    return F.greatest(F.ceil(-F.ln(u) / F.lit(math.log1p(gamma))), F.lit(1)).cast("int")


def geometric_base2(h: Column) -> Column:
    """The same for gamma = 1 by integers alone: leading zeros of the 60-bit hash plus one."""
    return (F.lit(61) - F.length(F.bin(h))).cast("int")


def laplace_from_uniform(u: Column, scale_: float) -> Column:
    """Laplace noise by inverse distribution function."""
    return F.when(u < 0.5, F.lit(scale_) * F.ln(2 * u)).otherwise(F.lit(-scale_) * F.ln(2 * (1 - u) + F.lit(1e-18)))


def squared_distance(x: Column, center: list[float]) -> Column:
    """Unrolled over the attributes, so that it stays in generated code."""
    terms = [(F.get(x, F.lit(j)) - F.lit(float(c))) * (F.get(x, F.lit(j)) - F.lit(float(c))) for j, c in enumerate(center)]
    out = terms[0]
    for t in terms[1:]:
        out = out + t
    return out


#: Terms (centers times attributes) up to which distances are unrolled into generated code.
UNROLLED = 160


def nearest_center(x: Column, centers: list[list[float]]) -> Column:
    """struct(d, a): squared distance and index of the nearest center; ties go to the lowest index.

    Unrolled into generated code while it is small; many centers go through one Arrow kernel instead.
    """
    if len(centers) * len(centers[0]) <= UNROLLED:
        return nearest(x, centers)
    table = np.asarray(centers, float)

    def kernel(xs: pd.Series) -> pd.DataFrame:
        p = np.array(xs.tolist(), float).reshape(-1, table.shape[1])
        a = ((table * table).sum(1)[None, :] - 2.0 * (p @ table.T)).argmin(axis=1)
        return pd.DataFrame({"d": ((p - table[a]) ** 2).sum(axis=1), "a": a.astype(np.int32)})

    return F.pandas_udf(kernel, "d double, a int")(x)


def nearest(x: Column, centers: list[list[float]]) -> Column:
    """struct(d, a): squared distance and index of the nearest center; ties go to the lowest index."""
    options = [F.struct(squared_distance(x, c).alias("d"), F.lit(a).alias("a")) for a, c in enumerate(centers)]
    return F.array_min(F.array(*options)) if len(options) > 1 else options[0]
