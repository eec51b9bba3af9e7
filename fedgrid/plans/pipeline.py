"""The whole method: parties' private local centers and membership messages, the server's weighted grid, and the
final centers. ``party_*`` functions see data and keys; ``server_*`` functions see released messages only."""

from __future__ import annotations

import time
from collections.abc import Callable
from concurrent.futures import Future, ThreadPoolExecutor
from dataclasses import dataclass, field, replace
from threading import Lock

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fedgrid.checkpoints import checkpointed
from fedgrid.operators import grid_frames, local_dp, lsh_forest, weights
from fedgrid.operators.kmeans import assign, lloyd, noisy_lloyd, weighted_kmeans
from fedgrid.operators.measures import CellsFold
from fedgrid.operators.packed import Columns, Labels
from fedgrid.operators.sketch import minima, partition_sketch
from fedgrid.operators.views import PartyView, validate
from fedgrid.privacy import Budget, HashKeys, Ledger, SketchParams, choose_k_local, laplace, phantoms, sketch_epsilon, split

METHODS = ("pairwise", "complement", "independence", "reports", "reports_refined", "nonprivate")


class Shared:
    """What the runs of an experiment on the same points have in common, made once: exact centers, leaf sums, counts
    and minimum hashes of the same seeds and labels. No noise is drawn in them, so each run's own stays fresh.

    For experiments only: a party that releases several such runs pays for each of them.
    """

    def __init__(self):
        self.lock, self.made = Lock(), {}

    def once(self, key: tuple, make: Callable):
        with self.lock:
            own = key not in self.made
            if own:
                self.made[key] = Future()
            found = self.made[key]
        if own:
            try:
                found.set_result(make())
            except BaseException as error:
                found.set_exception(error)
        return found.result()


def _anew(key: tuple, make: Callable):
    return make()


@dataclass
class Result:
    """``grid`` and ``cell_weights`` are arrays; above ``weights.MAX_CELLS`` the weights are rows (a0.., w), and the
    grid's points aren't listed."""

    centers: np.ndarray
    grid: np.ndarray | None
    cell_weights: np.ndarray | DataFrame
    local_centers: list[np.ndarray]
    n_hat: float
    k_local: int
    ledger: Ledger
    messages: list[tuple[int, str]] = field(default_factory=list)
    grid_seconds: float = 0.0

    @property
    def rounds(self) -> int:
        """Exchanges from parties to server: each party sends its centers and membership at once."""
        return max((sum(p == q for q, kind in self.messages if kind == "message") for p, _ in self.messages), default=0)


def party_centers(
    v: PartyView, k: int, eps: float, rng: np.random.Generator, method: str = "lsh_forest", seed: int = 0, ledger=None, party: int = 0,
    once: Callable = _anew,
) -> np.ndarray:
    """Local centers of one party, by any of the three engines."""
    points = v.columns or v.frame
    if method == "nonprivate":
        return once(("lloyd", id(v.frame), k, seed), lambda: lloyd(points, k, seed=seed, n_init=2, max_iter=15, tol=1e-4))
    if method == "noisy_lloyd":
        return noisy_lloyd(v.frame, k, eps, rng, ledger=ledger, party=party)
    return lsh_forest.fit(points, k, eps, rng, seed=seed, ledger=ledger, party=party, once=once)


def party_labels(v: PartyView, centers: np.ndarray) -> DataFrame | Labels:
    """(id, a): each user's local cluster. Narrow; recomputed from the party's columns where it is needed."""
    if v.columns:
        return Labels(v.columns, centers)
    return assign(v.frame, centers).select("id", "a")


def party_histogram(labels: DataFrame | Labels, k: int, eps2: float, rng: np.random.Generator, ledger=None, party: int = 0) -> np.ndarray:
    if isinstance(labels, Labels):
        counts = labels.seen.points.ask(CellsFold([labels]))
    else:
        counts = np.zeros(k)
        for r in labels.groupBy("a").count().collect():
            counts[r["a"]] = r["count"]
    if ledger is not None:
        ledger.charge(party, "membership", eps2)
    return laplace(counts, 1.0, eps2, rng)


def party_count(v: PartyView, eps0: float, rng: np.random.Generator, ledger=None, party: int = 0, once: Callable = _anew) -> float:
    if ledger is not None:
        ledger.charge(party, "count", eps0)
    n = once(("count", id(v.frame)), (v.columns or v.frame).count)
    return float(max(laplace(n, 1.0, eps0, rng), 1.0))


def exact_weights(labels: list[DataFrame] | list[Labels], sizes: list[int]) -> np.ndarray:
    """Users of each cell by a join on the id: the non-private baseline, and the truth in experiments.

    Labels of packed points stand beside each other already.
    """
    if isinstance(labels[0], Labels):
        return labels[0].seen.points.ask(CellsFold(labels)).reshape(sizes)
    wide = labels[0].select("id", F.col("a").alias("a0"))
    for p, frame in enumerate(labels[1:], start=1):
        wide = wide.join(frame.select("id", F.col("a").alias(f"a{p}")), "id")
    names = [f"a{p}" for p in range(len(labels))]
    out = np.zeros(sizes)
    for r in wide.groupBy(*names).count().collect():  # k'^S rows at most
        out[tuple(r[n] for n in names)] = r["count"]
    return out


def server_centers(grid: np.ndarray, w: np.ndarray, k: int, seed: int = 0) -> np.ndarray:
    """k centers of the weighted grid; cells of weight zero are dropped."""
    return weighted_kmeans(grid, w.ravel(), k, seed)


def fit(
    views: list[PartyView], k: int, eps: float = 1.0, delta: float | None = None, method: str = "pairwise",
    k_local: int | str | None = None, local: str = "lsh_forest", params: SketchParams | None = None, seed: int | None = None,
    membership: str = "private", calibration: str = "published", refine: dict | None = None, check: bool = True,
    shared: Shared | None = None,
) -> Result:
    """The method end to end, by one of METHODS.

    ``local='nonprivate'`` is the ablation with exact local centers, ``membership='exact'`` the one with exact
    weights; what such a part would have cost isn't given to the other. ``k_local='auto'`` asks for the user
    count first and then follows the rule; the default is the final k. Without ``delta`` it is one over the (noisy)
    count. A ``seed`` makes a run repeatable and its noise known: for tests and experiments only; without one noise
    comes from fresh entropy. ``check`` has every view validated first. ``shared`` keeps
    what is exact for other runs on the same views (the caller holds on to them).
    """
    if method not in METHODS:
        raise ValueError(f"{method} is none of {METHODS}")
    if check:
        for v in views:
            validate(v)
    rng, parties, ledger = np.random.default_rng(seed), len(views), Ledger()
    once = shared.once if shared else _anew
    private, reports = method != "nonprivate", method.startswith("reports")
    params = params or SketchParams(4096, 0.1, HashKeys(tuple(int(x) for x in rng.integers(0, 1 << 63, 4096))))
    counter = int(rng.integers(parties))
    counted = private and (not reports or k_local == "auto")
    budget = split(eps, delta or 0.5, parties, method=method, counted=counted)
    if counted:
        n_hat = party_count(views[counter], budget.eps0, rng, ledger, counter, once)
    else:  # nothing is private, or every user's report will be seen
        n_hat = float((views[0].columns or views[0].frame).count()) if delta is None or k_local == "auto" else 0.0
    delta = delta or 1.0 / max(n_hat, 2.0)
    budget = split(eps, delta, parties, method=method, counted=counted)
    if k_local == "auto":
        k_local = choose_k_local(n_hat, k, parties, budget.eps2, delta, params.repeats)
    k_local = int(k_local or k)
    local = local if private else "nonprivate"
    seeds = [int(s) for s in rng.integers(1 << 31, size=parties)]

    def one(p: int) -> np.ndarray:
        own = np.random.default_rng([seeds[p], p])
        return party_centers(views[p], k_local, budget.eps1, own, local, seeds[p], ledger, p, once)

    with ThreadPoolExecutor(max_workers=parties) as pool:  # the parties' jobs overlap
        centers = list(pool.map(one, range(parties)))
    if reports and local_dp.choose(budget.eps2, k_local) == "olh":
        views = [replace(v, columns=None) for v in views]  # these reports are rows
    labels = [party_labels(v, c) for v, c in zip(views, centers, strict=True)]
    many = k_local**parties > weights.MAX_CELLS and membership == "private" and method in ("pairwise", "complement")
    grid = None if many else weights.grid_points(centers)
    result = Result(np.zeros(0), grid, np.zeros(0), centers, n_hat, k_local, ledger)
    result.messages = [(p, "message") for p in range(parties)]
    final = int(rng.integers(1 << 31))
    if not private or membership == "exact":
        began = time.perf_counter()
        w = exact_weights(labels, [k_local] * parties)
        result.n_hat = n_hat or float(w.sum())
    else:
        known = [("minima", id(v.frame), c.tobytes(), params.keys, k_local) for v, c in zip(views, centers, strict=True)]
        message = _messages(labels, method, k_local, budget, params, rng, calibration, ledger, known, once)
        began = time.perf_counter()
        if many:
            return _frames(result, message, method, budget, params.gamma, k, calibration, final, began, refine or {})
        w = _server_weights(message, method, n_hat, budget, params.public(), k_local, rng, calibration, refine or {})
        result.n_hat = n_hat or float(w.sum())
    result.cell_weights = w
    result.grid_seconds = time.perf_counter() - began
    result.centers = server_centers(result.grid, w, k, final)
    return result


def _frames(result, message, method, budget: Budget, gamma, k, calibration, seed, began, refine) -> Result:
    """The server's part on rows, for grids that are too large for one machine's tensor."""
    spark = SparkSession.active()
    n_p = phantoms(sketch_epsilon(budget.eps2, budget.delta2, len(message[0]), calibration))
    if method == "pairwise":
        made = grid_frames.pairwise_refined_frame(spark, message, result.n_hat, n_p, gamma, seed=seed, **refine)
    else:
        made = grid_frames.complement_frame(spark, message, result.n_hat, n_p, gamma)
    result.cell_weights = checkpointed(made)
    result.grid_seconds = time.perf_counter() - began
    points = grid_frames.weighted_points(result.cell_weights, result.local_centers)
    result.centers = lloyd(points, k, weight="w", seed=seed, n_init=2)
    return result


def _messages(labels, method, k, budget: Budget, params, rng, calibration, ledger, known, once) -> list:
    least = [None] * len(labels)
    if method in ("pairwise", "complement"):  # the parties' jobs overlap
        with ThreadPoolExecutor(max_workers=len(labels)) as pool:
            jobs = [lambda f=frame: minima(f, params.keys, k) for frame in labels]
            least = list(pool.map(once, known, jobs))
    out = []
    protocol = local_dp.choose(budget.eps2, k)
    for p, frame in enumerate(labels):
        if method == "independence":
            out.append(party_histogram(frame, k, budget.eps2, rng, ledger, p))
        elif method.startswith("reports"):
            ledger.charge(p, "membership", budget.eps2)
            key = int(rng.integers(1 << 62))
            if isinstance(frame, Labels):
                out.append(local_dp.Reports(frame, k, budget.eps2, str(key)))
                continue
            out.append(local_dp.grr(frame, k, budget.eps2, str(key)) if protocol == "grr" else local_dp.olh(frame, k, budget.eps2, str(key)))
        else:
            out.append(partition_sketch(frame, k, budget.eps2, budget.delta2, params, rng, calibration, ledger, p, least[p]))
    return out


def _server_weights(message, method, n_hat, budget: Budget, params, k, rng, calibration, refine) -> np.ndarray:
    args = (n_hat, budget.eps2, budget.delta2, params.gamma)
    if method == "pairwise":
        return weights.pairwise_refined(message, *args, rng, calibration=calibration, **refine)
    if method == "complement":
        return weights.complement_union(message, *args, calibration=calibration)
    if method == "independence":
        return weights.consistent(weights.independence(message, n_hat), n_hat)
    if isinstance(message[0], DataFrame) and "seed" in message[0].columns:
        table = local_dp.olh_weights(message, k, budget.eps2)
    else:
        table = local_dp.decode(local_dp.grr_counts(message, k), k, budget.eps2)
    if method == "reports_refined":
        return weights.refine_reports(table, rng, **refine)
    return weights.consistent(table, table.sum())


def fit_central(
    df: DataFrame | Columns, k: int, eps: float | None, local: str = "lsh_forest", seed: int | None = None, ledger=None,
    noise: str = "gaussian", delta: float | None = None, l2_bound: float | None = None,
    once: Callable = _anew,
) -> np.ndarray:
    """Central clustering of all columns: non-private without ``eps``, else private with the full budget.

    The private baseline is the hash forest in its central form: a public bound on the points' norm (by default that
    of attributes in [-1, 1]) and Gaussian noise; ``noise='laplace'`` is the vertical form on all columns.
    """
    rng = np.random.default_rng(seed)
    seed = int(rng.integers(1 << 31)) if seed is None else seed
    if eps is None:
        return once(("central", id(df), k, seed), lambda: lloyd(df, k, seed=seed, n_init=3, max_iter=20, tol=1e-4))
    if local == "noisy_lloyd":
        return noisy_lloyd(df, k, eps, rng, ledger=ledger)
    if noise == "gaussian" and delta is None:  # the count is charged too
        eps0, eps = 0.02 * eps, 0.98 * eps
        delta = 1.0 / max(float(laplace(once(("count", id(df)), df.count), 1.0, eps0, rng)), 2.0)
        if ledger is not None:
            ledger.charge(0, "count", eps0)
    return lsh_forest.fit(df, k, eps, rng, delta=delta or 0.0, noise=noise, l2_bound=l2_bound, seed=seed, ledger=ledger, once=once)
