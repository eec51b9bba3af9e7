"""The server's weight estimators over released messages. Cells are S-way tensors of k' per axis, k'^S numbers
that don't grow with the users; ``MAX_CELLS`` guards their size. No function here gets a key or a user."""

from __future__ import annotations

import itertools
import math
import warnings
from collections.abc import Iterator

import numpy as np

from fedgrid.functions.estimators import cardinality
from fedgrid.privacy import phantoms, sketch_epsilon

MAX_CELLS = 1 << 24
#: Rounds of a refinement that warns when it hasn't settled by then.
MAX_ROUNDS = 60_000


def _guard(shape: tuple[int, ...]) -> None:
    if math.prod(shape) > MAX_CELLS:
        raise ValueError(f"a grid of {shape} is above {MAX_CELLS} cells; choose a smaller k'")


def consistent(w: np.ndarray, total: float, how: str = "simplex") -> np.ndarray:
    """Weights that are nonnegative and sum to ``total``: nearest such point, or clipped and scaled."""
    if how == "none":
        return w
    total = max(float(total), 0.0)
    if how == "clip_scale":
        cut = w.clip(min=0.0)
        return cut * (total / cut.sum()) if cut.sum() > 0 else np.full(w.shape, total / w.size)
    flat = np.sort(w.ravel())[::-1]
    run = (np.cumsum(flat) - total) / np.arange(1, flat.size + 1)
    theta = run[np.flatnonzero(flat > run)[-1]] if total > 0 else flat[0]
    return (w - theta).clip(min=0.0)


def leave_one_out(sketch: np.ndarray) -> np.ndarray:
    """For each cluster the maximum over all others (repeats x clusters), from the two largest values."""
    if sketch.shape[1] == 1:
        return np.zeros_like(sketch)
    order = np.argsort(sketch, axis=1)
    top, second = order[:, -1], order[:, -2]
    rows = np.arange(len(sketch))
    out = np.repeat(sketch[rows, top][:, None], sketch.shape[1], axis=1)
    out[rows, top] = sketch[rows, second]
    return out


def complement_unions(sketches: list[np.ndarray]) -> Iterator[tuple[tuple[int, ...], np.ndarray]]:
    """For each choice of all parties' clusters but the last's: the union sketches (repeats x last party's clusters)
    of the other clusters of every party."""
    rests = [leave_one_out(s) for s in sketches]
    for head in itertools.product(*(range(s.shape[1]) for s in sketches[:-1])):
        u = rests[-1]
        for r, a in zip(rests, head, strict=False):
            u = np.maximum(u, r[:, a][:, None])
        yield head, u


def union_of_complements(sketches: list[np.ndarray], gamma: float, mean: str = "harmonic_power") -> np.ndarray:
    """Cardinality read-outs of the union of the other clusters, for every cell."""
    shape = tuple(s.shape[1] for s in sketches)
    _guard(shape)
    out = np.empty(shape)
    for head, u in complement_unions(sketches):
        out[head] = cardinality(u, gamma, mean) if u.any() else 0.0
    return out


def complement_weights(
    sketches: list[np.ndarray], n_hat: float, n_p: int, gamma: float, mean: str = "harmonic_power"
) -> np.ndarray:
    """Raw weights: all users minus the union of the cell's complements, ``n_p`` phantoms a sketch taken off."""
    ghosts = sum(s.shape[1] - 1 for s in sketches) * n_p
    return n_hat - (union_of_complements(sketches, gamma, mean) - ghosts)


def complement_union(
    sketches: list[np.ndarray], n_hat: float, eps2: float, delta2: float, gamma: float,
    how: str = "simplex", mean: str = "harmonic_power", calibration: str = "published",
) -> np.ndarray:
    """Users of each cell by ``complement_weights``, made consistent."""
    n_p = phantoms(sketch_epsilon(eps2, delta2, len(sketches[0]), calibration))
    return consistent(complement_weights(sketches, n_hat, n_p, gamma, mean), n_hat, how)


def size_estimates(sketch: np.ndarray, n_p: int, gamma: float, mean: str = "harmonic_power") -> np.ndarray:
    """Users of each cluster, ``n_p`` phantoms taken off."""
    return cardinality(sketch, gamma, mean) - n_p


def cluster_sizes(
    sketch: np.ndarray, eps2: float, delta2: float, gamma: float, mean: str = "harmonic_power", calibration: str = "published"
) -> np.ndarray:
    return size_estimates(sketch, phantoms(sketch_epsilon(eps2, delta2, len(sketch), calibration)), gamma, mean)


def project(w: np.ndarray, l1: int, l2: int) -> np.ndarray:
    """Two-party table of a grid."""
    rest = tuple(a for a in range(w.ndim) if a not in (l1, l2))
    return w.sum(axis=rest)


def product_grid(sizes: list[np.ndarray], n_hat: float) -> np.ndarray:
    out = np.array(float(n_hat))
    for s in sizes:
        out = np.multiply.outer(out, s / n_hat)
    return out


def refine(
    start: np.ndarray, tables: dict[tuple[int, int], np.ndarray], n_hat: float, rng: np.random.Generator,
    rounds: int | None = None, eta=1.0, order: str = "random", tol: float = 1e-6, update: str = "additive",
    finalize: str = "simplex", clip: bool = True,
) -> np.ndarray:
    """Fits a grid to all two-party tables, one pair a round, until a sweep over all pairs moves no cell by more than
    tol * n_hat, or for exactly so many ``rounds``. A fit that hasn't settled after MAX_ROUNDS warns.

    ``additive`` spreads a cell's difference evenly over its group; ``multiplicative`` scales the group. ``clip`` cuts
    negative cells in each round; without it (the literal form) cells of a product start can't be emptied.
    ``order``: ``random`` draws an order of the pairs and keeps to it, so that noisy tables that contradict each other
    settle too; ``cyclic`` takes them as they are; ``independent`` draws each round's pair anew.
    """
    w, pairs = start.astype(float).copy(), sorted(tables)
    if order == "random":
        pairs = [pairs[i] for i in rng.permutation(len(pairs))]
    most, before = rounds or MAX_ROUNDS, w
    for t in range(1, most + 1):
        l1, l2 = pairs[rng.integers(len(pairs))] if order == "independent" else pairs[(t - 1) % len(pairs)]
        now, want = project(w, l1, l2), tables[l1, l2]
        expand = tuple(slice(None) if a in (l1, l2) else None for a in range(w.ndim))
        if update == "multiplicative":
            w = w.clip(min=1e-9) * (want.clip(min=0.0) / project(w.clip(min=1e-9), l1, l2))[expand]
        else:
            step = eta(t) if callable(eta) else (1 / math.sqrt(t) if eta == "1/sqrt" else float(eta))
            group = w.size // (w.shape[l1] * w.shape[l2])
            w = w - (step / group * (now - want))[expand]
            if clip:
                np.maximum(w, 0.0, out=w)
        if t % len(pairs) == 0:
            if rounds is None and np.abs(w - before).max() <= tol * max(n_hat, 1.0):
                break
            before = w
    else:
        if rounds is None:
            warnings.warn(f"the grid hasn't settled after {most} rounds", stacklevel=2)
    return consistent(w, n_hat, finalize)


def pairwise_refined(
    sketches: list[np.ndarray], n_hat: float, eps2: float, delta2: float, gamma: float, rng: np.random.Generator,
    mean: str = "harmonic_power", calibration: str = "published", **how,
) -> np.ndarray:
    """Product start from single sizes, then fitted to the complement-union tables of all pairs."""
    _guard(tuple(s.shape[1] for s in sketches))
    common = {"mean": mean, "calibration": calibration}
    sizes = [cluster_sizes(s, eps2, delta2, gamma, **common).clip(min=0.0) for s in sketches]
    if len(sketches) == 1:
        return consistent(sizes[0], n_hat, how.get("finalize", "simplex"))
    tables = {
        (a, b): complement_union([sketches[a], sketches[b]], n_hat, eps2, delta2, gamma, **common)
        for a, b in itertools.combinations(range(len(sketches)), 2)
    }
    return refine(product_grid(sizes, n_hat), tables, n_hat, rng, **how)


def independence(histograms: list[np.ndarray], n_hat: float) -> np.ndarray:
    """Product of the parties' noisy shares; negative counts count as none."""
    _guard(tuple(len(h) for h in histograms))
    return product_grid([h.clip(min=0.0) for h in histograms], n_hat)


def refine_reports(table: np.ndarray, rng: np.random.Generator, **how) -> np.ndarray:
    """The improved report baseline: the pair tables of the decoded cells, fitted like the sketches' tables."""
    n = table.sum()
    if table.ndim < 3:
        return consistent(table, n)
    tables = {p: consistent(project(table, *p), n) for p in itertools.combinations(range(table.ndim), 2)}
    sizes = [table.sum(axis=tuple(b for b in range(table.ndim) if b != a)).clip(min=0.0) for a in range(table.ndim)]
    return refine(product_grid(sizes, n), tables, n, rng, **how)


def grid_points(centers: list[np.ndarray]) -> np.ndarray:
    """The Cartesian product of the parties' centers, one row per cell in row-major order."""
    _guard(tuple(len(c) for c in centers))
    return np.array([np.concatenate(parts) for parts in itertools.product(*centers)])
