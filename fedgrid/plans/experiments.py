"""The experiment workloads X1-X11. Each gives a DataFrame of measured rows; parameters are arguments, so small
runs (tests, queries) and full ones (several seeds, all budgets) are the same code."""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass, replace
from functools import lru_cache

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fedgrid.operators.kmeans import lloyd
from fedgrid.operators.measures import Clustering, measure_all, relative_error, silhouette, v_of_counts
from fedgrid.operators.packed import Columns, Packed, tasks
from fedgrid.operators.views import build_views, correlation_split, random_split, ratio_split, validate, view
from fedgrid.plans.pipeline import Result, Shared, fit, fit_central
from fedgrid.plans.workloads import workload
from fedgrid.privacy import HashKeys, SketchParams, bytes_per_party, choose_k_local, split

RUN = "workload string, method string, parties int, eps double, seed int, k_local int, loss double, v_measure double, weight_error double, bytes bigint, grid_seconds double"
METHODS = ("pairwise", "complement", "independence", "reports", "reports_refined", "nonprivate")


@lru_cache(maxsize=8)
def keys(seed: int, repeats: int) -> HashKeys:
    rng = np.random.default_rng(seed + 5)
    return HashKeys(tuple(int(x) for x in rng.integers(0, 1 << 63, repeats)))


def params(repeats: int, seed: int, gamma: float = 0.1) -> SketchParams:
    return SketchParams(repeats, gamma, keys(seed, repeats))


#: Workloads whose correlated attributes go to different parties; all others are dealt at random.
CORRELATED = ("trip", "indep")


def _groups(df: DataFrame | Columns, name: str, names: list[str], parties: int, seed: int, sizes: list[int] | None) -> list[list[str]]:
    if sizes:
        return ratio_split(names, sizes, seed)
    return correlation_split(df, names, parties) if name in CORRELATED else random_split(names, parties, seed)


@dataclass(frozen=True)
class Run:
    """What one row of an experiment is measured with."""

    parties: int
    eps: float
    method: str
    seed: int = 0
    k: int = 5
    k_local: int | str | None = None
    repeats: int = 4096
    sizes: tuple[int, ...] | None = None
    local: str = "lsh_forest"
    membership: str = "private"

    @property
    def layout(self) -> tuple:
        return self.parties, self.seed, self.sizes


#: Runs of an experiment that are under way at a time, so that they meet in the same passes.
AT_ONCE = 64
#: Methods that cluster without privacy, round by round: they begin first.
LONG = ("central", "nonprivate")


class _Points:
    """A workload's points, read, validated, packed and split once for all runs of an experiment."""

    def __init__(self, spark: SparkSession, sf_dir: str, name: str, runs: list[Run]):
        df, self.names = workload(spark, sf_dir, name)
        # the readers of small files would leave the points in one partition
        self.df = df.repartition(tasks(spark), "id")
        self.packed, self.shared = Packed(self.df, self.names), Shared()  # an id's rows of all parties are one row here
        self.n, self.wide = self.packed.n, Columns(self.packed, tuple(range(len(self.names))))
        self.views, self.flat = {}, {}
        for r in runs:
            if r.layout not in self.views:
                groups = _groups(self.wide, name, self.names, r.parties, r.seed, list(r.sizes or ()))
                views = build_views(self.df, "id", groups)
                self.views[r.layout] = [replace(v, columns=Columns(self.packed, self.places(v.names))) for v in views]
                self.flat[r.layout] = Columns(self.packed, self.places(tuple(sum(groups, []))))

    def truth(self, k: int, seed: int) -> np.ndarray:
        """Centers of a central clustering, whose labels stand for the truth."""
        return self.shared.once(("truth", k, seed), lambda: lloyd(self.wide, k, seed=seed, n_init=2))

    def places(self, names: tuple[str, ...]) -> tuple[int, ...]:
        return tuple(self.names.index(c) for c in names)

    def central(self, r: Run) -> tuple[Clustering, None]:
        flat = self.flat[r.layout]
        centers = fit_central(flat, r.k, None if r.method == "central" else r.eps, seed=r.seed, delta=1.0 / self.n,
                              noise="laplace" if r.method == "central_laplace" else "gaussian", once=self.shared.once)
        return Clustering(centers, flat.places), None

    def clustered(self, r: Run) -> tuple[Clustering, Result | None]:
        if r.method.startswith("central"):
            return self.central(r)
        parties = self.views[r.layout]

        def made() -> Result:
            return fit(parties, r.k, r.eps, method=r.method, k_local=r.k_local, local=r.local, membership=r.membership,
                       params=params(r.repeats, r.seed), seed=r.seed, delta=1.0 / self.n, check=False, shared=self.shared)

        # no budget is spent in a non-private run, so it is the same at each
        got = self.shared.once(("fit", replace(r, eps=0.0)), made) if r.method == "nonprivate" else made()
        own = tuple((self.places(v.names), c) for v, c in zip(parties, got.local_centers, strict=True))
        return Clustering(got.centers, self.flat[r.layout].places, own), got


def measured(spark: SparkSession, sf_dir: str, name: str, many: list[Run], score: bool = True) -> list[tuple]:
    """A row for each run, all on one workload: the runs overlap, and one pass measures them all.

    Its ``grid_seconds`` are taken beside other runs; x8 has those of runs alone.
    """
    points = _Points(spark, sf_dir, name, many)
    with ThreadPoolExecutor(max_workers=AT_ONCE) as pool:
        central = score and "y" not in points.df.columns
        truth = {key: pool.submit(points.truth, *key) for key in {(r.k, r.seed) for r in many}} if central else {}
        jobs = {r: pool.submit(points.clustered, r) for r in sorted(set(many), key=lambda r: r.method not in LONG)}
        found = [jobs[r].result() for r in many]
        centers = [truth[r.k, r.seed].result() if central else None for r in many]
    rows = []
    for r, (run, got), seen in zip(many, found, measure_all(points.wide, [f for f, _ in found], centers), strict=True):
        v = v_of_counts(seen.pairs)[2] if score else None
        if got is None:
            row = (r.k, seen.loss, v, None, 0, 0.0)
        else:
            kind = {"independence": "independence", "nonprivate": "exact"}.get(r.method, "reports" if "reports" in r.method else "sketch")
            sent = max(bytes_per_party(kind, got.k_local, len(own), points.n, r.repeats) for own, _ in run.parties)
            row = (got.k_local, seen.loss, v, relative_error(got.cell_weights, seen.cells, points.n), sent, got.grid_seconds)
        rows.append((name, r.method, r.parties, float(r.eps), r.seed, *row))
    points.packed.unpersist()
    return rows


def _grid(eps, seeds, methods, parties: int = 2, sizes=None, **how) -> list[Run]:
    return [Run(parties, e, m, s, sizes=tuple(sizes) if sizes else None, **how) for s in seeds for e in eps for m in methods]


def runs(
    spark: SparkSession, sf_dir: str, name: str, parties: int = 2, eps: tuple[float, ...] = (1.0,), seeds: tuple[int, ...] = (0,),
    methods: tuple[str, ...] = METHODS, k: int = 5, k_local: int | str | None = None, repeats: int = 4096,
    sizes: list[int] | None = None, local: str = "lsh_forest", membership: str = "private", score: bool = True,
) -> DataFrame:
    """Loss, V-measure and weight error of each method, budget and seed on one workload."""
    how = {"k": k, "k_local": k_local, "repeats": repeats, "local": local, "membership": membership}
    many = _grid(eps, seeds, methods, parties, sizes, **how)
    return spark.createDataFrame(measured(spark, sf_dir, name, many, score), RUN)


ALL = (*METHODS, "central", "central_private", "central_laplace")
EPS = (0.5, 1.0, 2.0, 4.0, 8.0)


def x1_x2_loss_and_v(spark, sf_dir, names=("gauss", "trip", "loan", "indep"), parties=(2, 4), eps=EPS, seeds=(0,), methods=ALL):
    """Loss and V-measure against the budget, all methods."""
    parts = [measured(spark, sf_dir, w, [r for s in parties for r in _grid(eps, seeds, methods, s)]) for w in names]
    return spark.createDataFrame(sum(parts, []), RUN)


def x3_uneven(spark, sf_dir, eps=(1.0,), seeds=(0,), methods=("pairwise", "independence", "reports_refined"), score=True, **how):
    """Even and uneven splits of the attributes."""
    parts = [measured(spark, sf_dir, w, [r for s in many for r in _grid(eps, seeds, methods, sizes=s, **how)], score) for w, many in
             (("gauss", ((4, 4), (3, 5), (2, 6))), ("loan", ((8, 8), (6, 10), (4, 12))))]
    return spark.createDataFrame(sum(parts, []), RUN)


def x4_parties(
    spark, sf_dir, parties=(2, 4, 8), eps=(1.0, 2.0), seeds=(0,), methods=("pairwise", "complement", "independence"), k_local=3,
    score=True, **how,
):
    """Loss against the number of parties, at k' = 3 so that eight parties' grid has 6,561 cells."""
    many = [r for s in parties for r in _grid(eps, seeds, methods, s, k_local=k_local, **how)]
    return spark.createDataFrame(measured(spark, sf_dir, "loan", many, score), RUN)


def x5_weight_error(spark, sf_dir, parties=(2, 4), eps=EPS, seeds=(0,), methods=METHODS[:-1], **how):
    """Error of the cell weights, local centers held non-private."""
    many = [r for s in parties for r in _grid(eps, seeds, methods, s, local="nonprivate", **how)]
    return spark.createDataFrame(measured(spark, sf_dir, "gauss", many, score=False), RUN)


def x6_ablation(spark, sf_dir, parties=(2, 4), eps=EPS, seeds=(0,), score=True, **more):
    """All private; only the weights private; only the local centers private."""
    kinds = {"full": {}, "private weights": {"local": "nonprivate"}, "private centers": {"membership": "exact"}}
    many = [(label, r) for s in parties for label, how in kinds.items() for r in _grid(eps, seeds, ("pairwise",), s, **how, **more)]
    rows = measured(spark, sf_dir, "gauss", [r for _, r in many], score)
    return spark.createDataFrame([(w, label, *row) for (label, _), (w, _, *row) in zip(many, rows, strict=True)], RUN)


def x7_local_clusters(spark, sf_dir, k_locals=range(2, 11), parties=(2, 4), eps=(1.0, 4.0), seeds=(0,), repeats=4096):
    """Loss against k', with the k' that the rule chooses in column ``rule``."""
    n = workload(spark, sf_dir, "gauss")[0].count()
    many, rules = [], []
    for s in parties:
        for e in eps:
            rule = choose_k_local(n, 5, s, split(e, 1 / n, s).eps2, 1 / n, repeats)
            own = [r for q in k_locals for r in _grid((e,), seeds, ("pairwise",), s, k_local=int(q), repeats=repeats)]
            many, rules = many + own, rules + [rule] * len(own)
    rows = measured(spark, sf_dir, "gauss", many)
    return spark.createDataFrame([(*row, rule) for row, rule in zip(rows, rules, strict=True)], RUN + ", rule int")


def x8_costs(spark, sf_dir, k_locals=(5, 8), repeats=(2048, 4096), parties=(2, 4)):
    """Bytes a party sends and seconds of the server's grid, on 20,000 Gaussian users."""
    from fedgrid.plans.workloads import GAUSS, gaussian_mixture

    df = gaussian_mixture(spark, 20_000).repartition("id").cache()
    rows = []
    for kk in k_locals:
        for s in parties:
            views = [validate(v) for v in build_views(df, "id", random_split(GAUSS, s, 0))]
            for method in ("pairwise", "independence", "reports_refined", "nonprivate"):
                for m in repeats if method == "pairwise" else (repeats[-1],):
                    began = time.perf_counter()
                    got = fit(views, 5, 1.0, method=method, k_local=kk, params=params(m, 0), delta=1 / 20_000, check=False)
                    kind = {"pairwise": "sketch", "reports_refined": "reports", "nonprivate": "exact"}.get(method, method)
                    sent = bytes_per_party(kind, kk, 8 // s, 20_000, m)
                    rows.append((kk, m, s, method, sent, got.grid_seconds, time.perf_counter() - began))
    return spark.createDataFrame(rows, "k_local int, repeats int, parties int, method string, bytes bigint, grid_seconds double, seconds double")


def x9_nonprivate(spark, sf_dir, names=("gauss", "trip", "loan", "indep"), parties=(2, 4), seeds=(0,)):
    parts = [measured(spark, sf_dir, w, [r for s in parties for r in _grid((1.0,), seeds, ("nonprivate", "central"), s)]) for w in names]
    return spark.createDataFrame(sum(parts, []), RUN)


def x10_silhouette(spark, sf_dir, names=("gauss", "trip", "loan", "indep"), ks=range(2, 11)):
    """Silhouette of central clusterings of each k. A workload's points are packed once, and its clusterings share their passes."""
    rows = []
    for w in names:
        df, cols = workload(spark, sf_dir, w)
        packed = Packed(df.repartition(tasks(spark), "id"), cols, unique=False)
        wide = Columns(packed, tuple(range(len(cols))))
        with ThreadPoolExecutor(max_workers=AT_ONCE) as pool:
            jobs = [pool.submit(lloyd, wide, int(k), seed=1, n_init=2, max_iter=15) for k in ks]
            scores = [pool.submit(lambda job: silhouette(wide, job.result()), job) for job in jobs]
            rows += [(w, int(k), score.result()) for k, score in zip(ks, scores, strict=True)]
        packed.unpersist()
    return spark.createDataFrame(rows, "workload string, k int, silhouette double")


def x11_repeats(spark, sf_dir, repeats=(256, 1024, 4096), seeds=(0, 1, 2)):
    """Weight error against the number of sketch repeats."""
    many = [r for m in repeats for r in _grid((4.0,), seeds, ("pairwise",), repeats=m, local="nonprivate")]
    rows = measured(spark, sf_dir, "gauss", many, score=False)
    return spark.createDataFrame([(*row, r.repeats) for row, r in zip(rows, many, strict=True)], RUN + ", repeats int")


def other_workloads(spark, sf_dir, names=("cust", "doc", "page", "conv"), eps=(8.0,), seeds=(0,), methods=("pairwise", "nonprivate", "central")):
    """The stand-in workloads beside the published four, at small sketches."""
    return _union([runs(spark, sf_dir, w, 2, eps, seeds, methods, k=3, repeats=512) for w in names])


def _union(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out
