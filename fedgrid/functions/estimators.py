"""Cardinality read-outs of maximum-of-geometric values, in numpy and as Column expressions."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def bias(gamma: float) -> float:
    """What the harmonic mean of powers is to be multiplied by (its limit for large sets)."""
    return gamma / ((1.0 + gamma) * math.log1p(gamma))


def cardinality(alpha: np.ndarray, gamma: float, mean: str = "harmonic_power", corrected: bool = True) -> np.ndarray:
    """Read-out over axis 0 (the repeats).

    ``harmonic_power``: harmonic mean of (1+gamma)^alpha. ``harmonic_exponent`` and ``geometric``: power of
    the harmonic or arithmetic mean of the exponents, as the words of the text may be read (biased upward).
    """
    a = np.asarray(alpha, float)
    if mean == "harmonic_power":
        low = a.min(axis=0)
        out = np.exp(low * math.log1p(gamma)) / np.mean(np.exp((low - a) * math.log1p(gamma)), axis=0)
        return out * bias(gamma) if corrected else out
    if mean == "harmonic_exponent":
        return (1.0 + gamma) ** (1.0 / np.mean(1.0 / a, axis=0))
    if mean == "geometric":
        return (1.0 + gamma) ** a.mean(axis=0)
    raise ValueError(mean)


def cardinality_column(alpha: Column, gamma: float, corrected: bool = True) -> Column:
    """The harmonic read-out of an array of values."""
    total = F.aggregate(alpha, F.lit(0.0), lambda s, a: s + F.pow(F.lit(1.0 + gamma), -a.cast("double")))
    out = F.size(alpha) / total
    return out * F.lit(bias(gamma)) if corrected else out
