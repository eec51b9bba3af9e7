"""Packed points: what experiments add up over them is what the same steps find on rows."""

from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from fedgrid.functions import columns as C
from fedgrid.operators import kmeans, local_dp, lsh_forest, measures, packed, sketch, views
from fedgrid.plans import experiments as X
from fedgrid.plans import pipeline, workloads


@pytest.fixture(scope="module")
def gauss(spark):
    return workloads.gaussian_mixture(spark, 2000, m=4, k=3, seed=1).repartition(2, "id").cache()


@pytest.fixture(scope="module")
def packed_views(spark, gauss):
    """Packed points, and two parties' views of them with and without their columns."""
    names = ["x1", "x2", "x3", "x4"]
    points = packed.Packed(gauss.repartition(3, "id"), names)
    plain = [views.view(gauss, "id", c) for c in (["x3", "x1"], ["x2", "x4"])]
    columns = [packed.Columns(points, tuple(names.index(c) for c in v.names)) for v in plain]
    yield points, plain, [replace(v, columns=c) for v, c in zip(plain, columns, strict=True)]
    points.unpersist()


def test_packed_points_give_what_rows_do(spark, gauss, packed_views):
    points, plain, over = packed_views
    assert points.n == gauss.count()
    keys, rng = X.keys(0, 96), np.random.default_rng(3)
    for p, q in zip(plain, over, strict=True):
        assert np.allclose(kmeans.lloyd(q.columns, 3, seed=5, n_init=2), kmeans.lloyd(p.frame, 3, seed=5, n_init=2))
        planes = [lsh_forest.directions(2, 4, 1)]
        for how in ({"radius": 0.3}, {"weight_bound": 0.4}):
            assert np.allclose(lsh_forest.leaf_sums(q.columns, planes, **how), lsh_forest.leaf_sums(p.frame, planes, **how))
    centers = [rng.uniform(-1, 1, (4, 2)) for _ in over]
    centers[0][3] = 50.0  # nobody's
    rows, own = ([pipeline.party_labels(v, c) for v, c in zip(vs, centers, strict=True)] for vs in (plain, over))
    assert np.array_equal(pipeline.exact_weights(own, [4, 4]), pipeline.exact_weights(rows, [4, 4]))
    for a, b in zip(rows, own, strict=True):
        assert np.array_equal(sketch.minima(b, keys, 4), sketch.minima(a, keys, 4))
        same = [pipeline.party_histogram(f, 4, 1.0, np.random.default_rng(1)) for f in (a, b)]
        assert np.array_equal(*same)
    sent = [[local_dp.grr(f, 4, 1.0, f"k{p}") for p, f in enumerate(rows)], [local_dp.Reports(f, 4, 1.0, f"k{p}") for p, f in enumerate(own)]]
    assert np.array_equal(*[local_dp.grr_counts(s, 4) for s in sent])
    flat = packed.Columns(points, (0, 1, 2, 3))
    for pair, r in views.correlations(flat, list(points.names)).items():
        assert r == pytest.approx(views.correlations(gauss, list(points.names))[pair], abs=1e-9)
    for method in ("pairwise", "independence", "reports", "nonprivate"):
        a, b = (pipeline.fit(vs, 3, 4.0, method=method, k_local=3, params=X.params(64, 0), seed=0, delta=1e-3) for vs in (plain, over))
        assert np.allclose(a.cell_weights, b.cell_weights, rtol=1e-6) and np.allclose(a.centers, b.centers, atol=1e-6)


def test_packed_hashes_are_the_engines(spark):
    ids = [0, 1, -1, 7, (1 << 63) - 1, -(1 << 63), 1 << 40, None]
    df = spark.createDataFrame([(i,) for i in ids], "id bigint")
    got = {r.id: list(r.h) for r in workloads._hashed(df, ["c0", "u0_1"]).collect()}
    want = df.select("id", *[C.md5_hash60(F.concat_ws("|", F.lit(t), F.col("id").cast("string"))).alias(t) for t in ("c0", "u0_1")])
    assert got == {r.id: [r.c0, r.u0_1] for r in want.collect()}
    known = np.array(ids[:-1], np.int64)
    for seed in (0, 5, -3, (1 << 31) - 1, 1 << 31, (1 << 31) + 77):
        rows = df.where("id is not null").select("id", F.xxhash64("id", F.lit(seed)).alias("h")).collect()
        assert kmeans.spark_xxhash64(known, seed).tolist() == [{r.id: r.h for r in rows}[i] for i in ids[:-1]]


def test_minima_of_many_labellings_are_those_of_each():
    """Labels of few and of many users, over several blocks, and sets of keys that differ."""
    rng = np.random.default_rng(0)
    ids, keys = rng.permutation(1 << 16)[:21_000].astype(np.int64), (X.keys(0, 24), X.keys(1, 40))

    class Given:
        def __init__(self, share):
            self.all = rng.choice(len(share), len(ids), p=share)
            self.all[ids == ids[15_000]] = len(share) - 1  # first met in the second block

        def of(self, block):
            return self.all[block.y]

    labels = [Given(share) for share in ([0.5, 0.5, 0.0], [0.98, 0.0199, 0.0001], [0.3, 0.3, 0.4])]
    folds = [sketch.MinimaFold(own, keys[i % 2], 3) for i, own in enumerate(labels)]
    for at in range(0, len(ids), 9_000):
        own = np.arange(at, min(at + 9_000, len(ids)))
        sketch.MinimaFold.add_all(folds, packed.Block(ids[own], own, np.zeros((len(own), 1))))
    for f in folds:
        want = np.full_like(f.table, np.iinfo(np.uint64).max)
        sketch.fold_minima(ids, f.labels.all, f.keys.array(), want)
        assert np.array_equal(f.state(), want)


def test_packed_points_are_validated(spark):
    good = [(i, float(i)) for i in range(20)]
    for more, why in (((None, 1.0), "1 null ids"), ((3, 1.0), "occurs twice"), ((50, None), "1 rows"), ((50, float("nan")), "1 rows")):
        df = spark.createDataFrame([*good, more], "id bigint, a double")
        with pytest.raises(ValueError, match=why):
            packed.Packed(df.repartition(4, "id"), ["a"])


def test_runs_meet_in_passes_of_few_tasks(spark, sf, monkeypatch):
    """Whatever a session's default number of partitions is, and fewer passes than steps."""
    made, sizes, steps = packed.Packed._pass, [], []

    def counted(self, batch):
        sizes.append(self.blocks.getNumPartitions()), steps.append(len(batch))
        return made(self, batch)

    monkeypatch.setattr(packed.Packed, "_pass", counted)
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", "200")
    try:
        rows = X.x6_ablation(spark, sf, parties=(2,), eps=(4.0,), repeats=64).collect()
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    assert len(rows) == 3 and set(sizes) == {packed.tasks(spark)} and len(steps) < 0.7 * sum(steps)


def test_the_first_of_starts_that_end_alike_is_taken():
    """Their costs differ by rounding, which must not choose the order of the centers."""
    assert kmeans._best([3.0, 1.0 + 1e-13, 1.0, 2.0]) == 1 and kmeans._best([1.0 + 1e-6, 1.0]) == 1
    assert kmeans._best([0.0, 0.0]) == 0 and kmeans._best([np.inf]) == 0


def test_silhouette_of_packed_points(spark, gauss, packed_views):
    points = packed_views[0]
    frame, seen = views.view(gauss, "id", list(points.names)).frame, packed.Columns(points, (0, 1, 2, 3))
    centers = kmeans.lloyd(seen, 3, seed=5)
    lone = gauss.orderBy("id").first()
    alone = np.vstack([centers, [lone[c] for c in points.names], np.full((1, 4), 50.0)])  # a point of its own, and nobody's
    for c in (centers, alone, centers[:2]):
        assert measures.silhouette(seen, c) == pytest.approx(measures.silhouette(frame, c), abs=1e-12)


def test_silhouettes_share_their_passes(spark, sf, monkeypatch):
    """A workload is packed once for all k, whose clusterings meet in the same passes; an id may come twice."""
    made, passes, ids = [], [], spark.range(300).select((F.col("id") % 290).alias("id"))
    df = workloads.gaussian_mixture(spark, ids=ids)
    init, run = packed.Packed.__init__, packed.Packed._pass
    monkeypatch.setattr(X, "workload", lambda *_: (df, workloads.GAUSS))
    monkeypatch.setattr(packed.Packed, "__init__", lambda self, *a, **b: (made.append(0), init(self, *a, **b))[1])
    monkeypatch.setattr(packed.Packed, "_pass", lambda self, batch: (passes.append(len(batch)), run(self, batch))[1])
    got = X.x10_silhouette(spark, sf, names=("gauss",), ks=(2, 3, 5)).collect()
    assert len(made) == 1 and len(passes) <= 0.6 * sum(passes)
    frame = views.view(df, "id", workloads.GAUSS).frame
    for r in got:
        centers = kmeans.lloyd(frame, r.k, seed=1, n_init=2, max_iter=15)
        assert r.silhouette == pytest.approx(measures.silhouette(frame, centers), abs=1e-9)
