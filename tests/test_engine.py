"""The clustering engine: worked examples, golden numbers, identities, properties, and agreement of its forms."""

import itertools
import math
import re

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from fedgrid.functions import columns as C
from fedgrid.functions.estimators import bias, cardinality
from fedgrid.operators import kmeans, local_dp, lsh_forest, measures, sketch, views, weights
from fedgrid.plans import experiments as X
from fedgrid.plans import pipeline, workloads
from fedgrid.privacy import (
    HashedNoise,
    HashKeys,
    Ledger,
    SketchParams,
    approximation_factor,
    best_order,
    bytes_per_party,
    choose_k_local,
    combine,
    floor_value,
    gaussian_scale,
    phantoms,
    rdp_to_dp,
    sketch_epsilon,
    split,
)


def keys(n, seed=0):
    return HashKeys(tuple(int(x) for x in np.random.default_rng(seed).integers(0, 1 << 63, n)))


def sketch_of(labels, k, params, ids=None):
    table = np.full((k, params.repeats), np.iinfo(np.uint64).max, np.uint64)
    sketch.fold_minima(np.arange(len(labels)) if ids is None else ids, np.asarray(labels), params.keys.array(), table)
    return sketch.values_of(table, params.gamma)


# ---- privacy


@pytest.mark.parametrize("n,s,eps,eps2,eps_row,ghosts,k", [
    (20_000, 2, 1, 0.245, 2.940e-4, 3401, 5), (20_000, 2, 8, 1.96, 2.352e-3, 425, 7), (20_000, 4, 1, 0.1225, 1.424e-4, 7022, 5),
    (20_000, 4, 0.5, 0.06125, 7.121e-5, 14044, 4), (60_000, 2, 1, 0.245, 2.798e-4, 3573, 6), (100_000, 2, 1, 0.245, 2.739e-4, 3651, 7),
    (1_500, 2, 1, 0.245, 3.382e-4, 2957, 3), (600_000, 4, 1, 0.1225, 1.248e-4, 8010, 7),
])
def test_golden_table(n, s, eps, eps2, eps_row, ghosts, k):
    b = split(eps, 1 / n, s)
    got = sketch_epsilon(b.eps2, b.delta2, 4096)
    assert b.eps2 == pytest.approx(eps2) and got == pytest.approx(eps_row, rel=1e-3)
    assert abs(phantoms(got) - ghosts) <= 1
    assert choose_k_local(n, 5, s, b.eps2, 1 / n, 4096) == k


def test_floor_and_bounds():
    e = sketch_epsilon(split(1, 1 / 20_000, 2).eps2, 1 / 40_000, 4096)
    assert floor_value(e, 0.1) == 86 and floor_value(e, 1.0) == 12
    with pytest.raises(ValueError):
        sketch_epsilon(25.0, 1e-5, 64)
    assert sketch_epsilon(0.245, 2.5e-5, 4096, "zcdp") == pytest.approx(8.3e-4, rel=0.05)
    assert approximation_factor() == 10
    order, eps = best_order(0.01, 100, 1e-5)
    assert eps == pytest.approx(rdp_to_dp(order, order * 100 * 0.01**2 / 2, 1e-5))


def test_budget_and_ledger():
    b = split(2.0, 1e-5, 4)
    assert b.eps0 + 4 * (b.eps1 + b.eps2) == pytest.approx(2.0)
    assert split(2.0, 1e-5, 4, method="reports").eps0 == 0
    ledger = Ledger()
    ledger.charge(0, "x", 0.5)
    ledger.parallel(1, "y", [(0.2, 0.0), (0.3, 1e-6)])
    assert ledger.total() == (0.8, 1e-6)


@pytest.mark.parametrize("how", ["xor", "sum", "concat"])
def test_keys_need_every_share(how):
    a = combine([b"one", b"two"], 8, how)
    assert a == combine([b"one", b"two"], 8, how) and a != combine([b"one", b"twp"], 8, how)
    assert "values" not in repr(a)


def test_bytes_of_the_cost_table():
    assert [bytes_per_party("sketch", 5, 4, 20_000, m) for m in (2048, 4096)] == [82_080, 164_000]
    assert bytes_per_party("independence", 5, 4, 20_000) == 200
    assert bytes_per_party("exact", 5, 4, 20_000) == 160_160
    assert [bytes_per_party("sketch", 8, 4, 20_000, m) for m in (2048, 4096)] == [131_328, 262_400]


def test_server_functions_take_no_data():
    import inspect

    for name, f in inspect.getmembers(weights, inspect.isfunction):
        assert not {"views", "keys", "labels", "params", "spark"} & set(inspect.signature(f).parameters), name


# ---- sketches


@settings(max_examples=25, deadline=None)
@given(st.lists(st.integers(0, 10_000), min_size=1, max_size=60), st.lists(st.integers(0, 10_000), min_size=1, max_size=60))
def test_merge_laws(a, b):
    p = SketchParams(32, 0.1, keys(32))

    def sk(x):
        return sketch_of([0] * len(x), 1, p, np.array(x, np.int64))

    assert (sketch.union(sk(a), sk(b)) == sketch.union(sk(b), sk(a))).all()
    assert (sketch.union(sk(a), sk(b)) == sk(a + b)).all()
    assert (sk(a + a) == sk(a)).all() and (sk(sorted(a)) == sk(a)).all()


def test_read_out_and_its_spread():
    r = np.random.default_rng(0)
    got = []
    for seed in range(20):
        p = SketchParams(512, 0.1, keys(512, seed))
        got.append(cardinality(sketch_of(np.zeros(5000, int), 1, p), 0.1)[0])
    assert np.mean(got) == pytest.approx(5000, rel=0.03)
    assert np.std(got) / 5000 * math.sqrt(512) == pytest.approx(1.0, abs=0.5)
    a = r.integers(20, 90, (64, 3))
    assert (cardinality(a, 0.1, "harmonic_exponent") <= cardinality(a, 0.1, "geometric") * (1 + 1e-9)).all()
    assert bias(1.0) == pytest.approx(0.5 / math.log(2))


def test_phantoms_by_one_draw():
    r = np.random.default_rng(0)
    one = sketch.phantom_maxima((4000,), 50, 0.1, r)
    many = np.ceil(-np.log(r.uniform(size=(4000, 50))) / math.log1p(0.1)).max(1)
    assert one.mean() == pytest.approx(many.mean(), rel=0.02) and one.std() == pytest.approx(many.std(), rel=0.1)


def test_floor_fades_for_large_sets():
    ratio = []
    for n in (50, 5000):
        p = SketchParams(400, 0.1, keys(400))
        free = np.maximum(sketch_of(np.zeros(n, int), 1, p), sketch.phantom_maxima((400, 1), 200, 0.1, np.random.default_rng(0)))
        ratio.append(np.maximum(free, floor_value(0.005, 0.1)).mean() / free.mean())
    assert ratio[0] > ratio[1] and ratio[1] == pytest.approx(1, abs=0.01)


def test_empty_cluster_does_not_show():
    p = SketchParams(64, 0.1, keys(64))
    alpha = sketch_of([0, 0, 2], 4, p)
    assert (alpha[:, 1] == 0).all()
    out = sketch.privatise(alpha, 0.01, 0.1, np.random.default_rng(0))
    assert (out >= floor_value(0.01, 0.1)).all()


def test_row_privacy_by_histograms():
    """One cell of a sketch on neighbouring sets: no outcome's odds change by more than the row's budget."""
    eps, rng, n = 1.0, np.random.default_rng(1), 200_000
    one = np.ceil(-np.log(rng.uniform(size=(n, 6))) / math.log(2))
    ghosts = np.maximum(sketch.phantom_maxima((n,), phantoms(eps), 1.0, rng), floor_value(eps, 1.0))
    a, b = np.maximum(ghosts, one.max(1)), np.maximum(ghosts, one[:, :5].max(1))
    for v in range(1, 9):
        p, q = (a == v).mean(), (b == v).mean()
        if min(p, q) > 0.005:
            assert abs(math.log(p / q)) <= eps + 0.05


def test_kernel_matches_in_any_partitioning(spark):
    k, p = keys(128), SketchParams(128, 0.1, keys(128))
    df = spark.range(3000).select("id", (F.col("id") * 7 % 5).cast("int").alias("a"))
    one = sketch.minima(df.repartition(1), k, 6)
    many = sketch.minima(df.unionByName(df).repartition(13), k, 6)
    ids = np.arange(3000)
    assert (one == many).all() and (sketch.values_of(one, 0.1) == sketch_of(ids * 7 % 5, 6, p, ids)).all()


def test_sql_surface(spark):
    from fedgrid.functions.register import register

    register(spark)
    got = spark.sql("SELECT count(*) AS n, count(DISTINCT cell) AS c FROM grid_cells(3, 4)").first()
    assert (got.n, got.c) == (81, 81)
    assert spark.sql("SELECT min(geometric_hash(id, 7L, 0.1D)) AS v FROM range(50)").first().v >= 1
    assert spark.sql("SELECT sketch_cardinality(array(10, 20, 30), 0.1D) AS v").first().v > 0
    merged = spark.sql("SELECT sketch_union_agg(a) AS a FROM VALUES (array(1, 5)), (array(3, 2)) t(a)").first().a
    assert list(merged) == [3, 5]


# ---- weights

TWELVE = (np.arange(12) % 3, np.arange(12) // 4)


def exact_of(labels, k):
    out = np.zeros((k,) * len(labels))
    np.add.at(out, tuple(labels), 1)
    return out


def test_worked_example():
    w = exact_of(TWELVE, 3)
    assert w[:, 0].tolist() == [2, 1, 1] and w.sum() == 12
    inside = {i for i in range(12) if TWELVE[0][i] == 0 and TWELVE[1][i] == 0}
    rest = {i for i in range(12) if TWELVE[0][i] != 0} | {i for i in range(12) if TWELVE[1][i] != 0}
    assert len(rest) == 10 and len(inside) == 12 - len(rest)
    ind = weights.independence([w.sum(1), w.sum(0)], 12)
    assert np.allclose(ind, 4 / 3) and measures.relative_error(ind, w, 12) == pytest.approx(1 / 3)


@settings(max_examples=20, deadline=None)
@given(st.integers(2, 4), st.integers(1, 4), st.integers(0, 1000))
def test_identities(parties, k, seed):
    r = np.random.default_rng(seed)
    labels = [r.integers(k, size=40) for _ in range(parties)]
    w = exact_of(labels, k)
    for cell in itertools.product(range(k), repeat=parties):
        away = set().union(*[set(np.flatnonzero(x != c)) for x, c in zip(labels, cell, strict=True)])
        assert 40 - len(away) == w[cell]
    for a, b in itertools.combinations(range(parties), 2):
        assert (weights.project(w, a, b) == exact_of([labels[a], labels[b]], k)).all()


@settings(max_examples=40, deadline=None)
@given(st.lists(st.floats(-50, 50), min_size=1, max_size=20), st.floats(0.5, 100))
def test_consistency_is_the_nearest_point(w, total):
    w = np.array(w)
    got = weights.consistent(w, total)
    assert got.min() >= 0 and got.sum() == pytest.approx(total)
    for how in np.random.default_rng(0).dirichlet(np.ones(len(w)), 20) * total:
        assert ((got - w) ** 2).sum() <= ((how - w) ** 2).sum() + 1e-6


def estimates(eps, parties, seed, n=8000, k=4, repeats=1024, copied=0.8):
    r = np.random.default_rng(seed)
    base = r.integers(k, size=n)
    labels = [np.where(r.random(n) < copied, base, r.integers(k, size=n)) for _ in range(parties)]
    b, p = split(eps, 1 / n, parties), SketchParams(repeats, 0.1, keys(repeats, seed))
    e = sketch_epsilon(b.eps2, b.delta2, repeats)
    sk = [sketch.privatise(sketch_of(x, k, p), e, 0.1, r) for x in labels]
    args = (sk, n, b.eps2, b.delta2, 0.1)
    exact = exact_of(labels, k)
    return {
        "pairwise": measures.relative_error(weights.pairwise_refined(*args, r), exact, n),
        "complement": measures.relative_error(weights.complement_union(*args), exact, n),
        "independence": measures.relative_error(weights.independence([exact_of([x], k) for x in labels], n), exact, n),
    }, args, r


def test_two_parties_refined_equals_direct():
    got, args, r = estimates(4.0, 2, 0)
    assert got["pairwise"] == pytest.approx(got["complement"], abs=1e-6)


def test_orderings_over_seeds():
    runs = [estimates(2.0, 4, s)[0] for s in range(10)]
    mean = {m: np.mean([r[m] for r in runs]) for m in runs[0]}
    assert mean["pairwise"] < mean["complement"] and mean["pairwise"] < mean["independence"]
    low = np.mean([estimates(1.0, 2, s)[0]["complement"] for s in range(5)])
    high = np.mean([estimates(16.0, 2, s)[0]["complement"] for s in range(5)])
    assert high < low


def test_more_repeats_less_error():
    few = np.mean([estimates(8.0, 2, s, repeats=128)[0]["complement"] for s in range(5)])
    many = np.mean([estimates(8.0, 2, s, repeats=4096)[0]["complement"] for s in range(3)])
    assert many < few


def test_weights_edges():
    _, (sk, n, e2, d2, g), r = estimates(2.0, 3, 1)
    one = [s[:, :1] for s in sk]
    assert weights.complement_union(one, n, e2, d2, g).sum() == pytest.approx(n)
    assert weights.pairwise_refined(sk[:1], n, e2, d2, g, r).sum() == pytest.approx(n)
    uneven = [sk[0], sk[1][:, :2], sk[2][:, :3]]
    w = weights.pairwise_refined(uneven, n, e2, d2, g, r)
    assert w.shape == (4, 2, 3) and w.min() >= 0 and w.sum() == pytest.approx(n)
    with pytest.raises(ValueError):
        weights.grid_points([np.zeros((5000, 1))] * 3)
    assert (weights.leave_one_out(np.array([[3, 1, 3]])) == [[3, 3, 3]]).all()


# ---- reports


def test_reports_decode_without_bias(spark):
    df = spark.range(6000).select("id", (F.col("id") % 3).cast("int").alias("a"))
    other = df.select("id", F.when(F.col("id") % 2 == 0, F.col("a")).otherwise(0).cast("int").alias("a"))
    exact = pipeline.exact_weights([df, other], [3, 3])
    two = [local_dp.grr(df, 3, 3.0, "x"), local_dp.grr(other, 3, 3.0, "y")]
    got = local_dp.decode(local_dp.grr_counts(two, 3), 3, 3.0)
    assert measures.relative_error(got, exact, 6000) < 0.15 and got.sum() == pytest.approx(6000)
    hashed = [local_dp.olh(df, 3, 3.0, "p"), local_dp.olh(other, 3, 3.0, "q")]
    assert measures.relative_error(local_dp.olh_weights(hashed, 3, 3.0), exact, 6000) < 0.4
    assert local_dp.choose(0.2, 5) == "grr" and local_dp.choose(0.2, 50) == "olh"


# ---- clustering


@pytest.fixture(scope="module")
def gauss(spark):
    df = workloads.gaussian_mixture(spark, 3000, m=4, k=3, sigma=0.05, seed=4).cache()
    df.count()
    return df


def test_small_tables_are_clustered_in_one_task(spark, gauss, monkeypatch):
    """All rounds over all points without a Spark job each, and the centers are those of a job a round."""
    v = views.view(gauss, "id", ["x1", "x2", "x3", "x4"]).frame.withColumn("w", F.col("id") % 3)
    jobs, sums = [], kmeans.cluster_sums
    monkeypatch.setattr(kmeans, "cluster_sums", lambda *a, **k: jobs.append(1) or sums(*a, **k))
    start = np.array([[0.1 * i] * 4 for i in range(3)])
    for how in ({"n_init": 2}, {"n_init": 2, "weight": "w"}, {"init": start, "max_iter": 3, "tol": 0.0}, {"method": "random", "seed": 2}):
        jobs.clear()
        one = kmeans.lloyd(v.repartition(3), 3, **how)
        assert not jobs
        with monkeypatch.context() as m:
            m.setattr(kmeans, "ONE_TASK", 0)
            assert np.allclose(kmeans.lloyd(v, 3, **how), one, atol=1e-12) and jobs


def test_lloyd_and_measures(spark, gauss):
    v = views.view(gauss, "id", ["x1", "x2", "x3", "x4"])
    centers = kmeans.lloyd(v.frame, 3, seed=0, n_init=3)
    x = np.array([r.x for r in v.frame.collect()])
    d = ((x[:, None] - centers[None]) ** 2).sum(2)
    assert kmeans.cost(v.frame, centers) == pytest.approx(d.min(1).sum())
    assert kmeans.mean_cost(v.frame, centers) == pytest.approx(d.min(1).mean())
    found = kmeans.assign(v.frame, centers).join(gauss.select("id", "y"), "id")
    assert measures.v_measure(found)[2] > 0.95
    assert measures.silhouette(v.frame, centers) > 0.6
    from pyspark.ml.clustering import KMeans
    from pyspark.ml.functions import array_to_vector

    library = KMeans(k=3, seed=1, featuresCol="f").fit(v.frame.select(array_to_vector("x").alias("f")))
    assert kmeans.cost(v.frame, centers) <= library.summary.trainingCost * 1.01


def test_many_centers_by_the_kernel(spark, gauss):
    v = views.view(gauss, "id", ["x1", "x2", "x3", "x4"])
    r = np.random.default_rng(0).uniform(-1, 1, (60, 4))
    got = {row.id: (row.a, row.d) for row in kmeans.assign(v.frame, r).collect()}
    for row in v.frame.limit(50).collect():
        d = ((r - np.array(row.x)) ** 2).sum(1)
        assert got[row.id][0] == d.argmin() and got[row.id][1] == pytest.approx(d.min())


def test_ties_go_to_the_lowest_index(spark):
    df = spark.createDataFrame([(1, [0.0])], "id bigint, x array<double>")
    assert kmeans.assign(df, np.array([[1.0], [-1.0], [1.0]])).first().a == 0


def test_private_clusterings(spark, gauss):
    v, rng = views.view(gauss, "id", ["x1", "x2", "x3", "x4"]), np.random.default_rng(0)
    loose, tight, ledger = [], [], Ledger()
    for s in range(3):
        tight.append(kmeans.mean_cost(v.frame, lsh_forest.fit(v.frame, 3, 20.0, rng, seed=s, ledger=ledger)))
        loose.append(kmeans.mean_cost(v.frame, lsh_forest.fit(v.frame, 3, 0.05, rng, seed=s)))
    assert np.mean(tight) < np.mean(loose) and ledger.total()[0] == pytest.approx(60)
    centers = lsh_forest.fit(v.frame, 3, 5.0, rng, delta=1e-5, noise="gaussian", l2_bound=2.0)
    assert np.linalg.norm(centers, axis=1).max() <= 2.0 + 1e-9
    noisy = kmeans.noisy_lloyd(v.frame, 3, 10.0, rng, iters=4, ledger=ledger)
    assert np.abs(noisy).max() <= 1 and ledger.total()[0] == pytest.approx(70)


def test_weighted_kmeans_against_brute_force():
    r = np.random.default_rng(0)
    p, w = r.uniform(-1, 1, (8, 2)), r.integers(1, 5, 8).astype(float)
    best = np.inf
    for a in itertools.product(range(2), repeat=8):
        a = np.array(a)
        c = [np.average(p[a == j], axis=0, weights=w[a == j]) if (a == j).any() else np.zeros(2) for j in (0, 1)]
        best = min(best, sum(w[i] * ((p[i] - c[a[i]]) ** 2).sum() for i in range(8)))
    c = kmeans.weighted_kmeans(p, w, 2, n_init=20)
    assert (((p[:, None] - c[None]) ** 2).sum(2).min(1) * w).sum() == pytest.approx(best)


# ---- preparation and views


def test_splits_and_alignment(spark, gauss):
    names = [f"c{i}" for i in range(16)]
    assert sorted(sum(views.random_split(names, 4, 0), [])) == sorted(names)
    assert [len(g) for g in views.ratio_split(names, [6, 10], 1)] == [6, 10]
    df = gauss.withColumn("z1", F.col("x1") * 2).withColumn("z2", F.col("x2") * 3)
    groups = views.correlation_split(df, ["x1", "z1", "x2", "z2"], 2)
    assert all({"x1", "z1"} != set(g) and {"x2", "z2"} != set(g) for g in groups)
    a, b = views.view(gauss.where("id < 10"), "id", ["x1"]), views.view(gauss.where("id >= 5 AND id < 20"), "id", ["x2"])
    assert [v.frame.count() for v in views.align([a, b])] == [5, 5]
    assert [v.frame.count() for v in views.align([a, b], "impute")] == [20, 20]
    assert [v.frame.count() for v in views.align([a, b], "own")] == [10, 15]


def test_validation(spark):
    def make(rows):
        return views.PartyView(spark.createDataFrame(rows, "id bigint, x array<double>"), ("a",))

    views.validate(make([(1, [0.5]), (2, [0.1])]))
    for bad in ([(1, [None])], [(1, [float("nan")])], [(None, [0.1])], [(1, [0.1]), (1, [0.2])]):
        with pytest.raises(ValueError):
            views.validate(make(bad))


def test_scaling(spark):
    df = spark.createDataFrame([(1.0,), (5.0,), (99.0,), (None,)], "v double")
    got = [r[0] for r in df.select(C.scale("v", 1, 9)).collect()]
    assert got == [-1.0, 0.0, 1.0, None]
    assert df.select(C.scale("v", 3, 3)).first()[0] == 0.0
    low, high = C.private_range(spark.range(5000).select((F.col("id") % 100).cast("double").alias("v")), "v", 5.0, -1000, 1000, np.random.default_rng(0))
    assert -80 < low <= 10 and 90 <= high < 200


# ---- whole runs


@pytest.mark.parametrize("method", pipeline.METHODS)
def test_pipeline(spark, sf, method):
    df = workloads.customers(spark, sf)
    parties = views.build_views(df, "id", [sum(workloads.CUST_GROUPS[:2], []), sum(workloads.CUST_GROUPS[2:], [])])
    got = pipeline.fit(parties, 3, 4.0, method=method, k_local=3, params=X.params(128, 0), seed=0, delta=1 / 150)
    assert got.centers.shape == (3, 15) and got.rounds == 1
    assert got.cell_weights.min() >= 0 and got.cell_weights.sum() == pytest.approx(got.n_hat)
    eps, delta = got.ledger.total()
    assert eps == pytest.approx(0 if method == "nonprivate" else 4.0)
    if method in ("pairwise", "complement"):
        assert delta == pytest.approx(1 / 150)


def test_experiment_rows(spark, sf):
    rows = X.runs(spark, sf, "gauss", 2, (8.0,), (0,), ("pairwise", "independence", "nonprivate"), repeats=1024).collect()
    got = {r.method: r for r in rows}
    assert got["nonprivate"].weight_error == 0 and got["nonprivate"].loss <= got["pairwise"].loss
    assert got["pairwise"].loss < got["independence"].loss
    auto = X.runs(spark, sf, "gauss", 2, (8.0,), (0,), ("pairwise",), k_local="auto", repeats=256, score=False).first()
    assert auto.k_local >= 3


def test_messages_round_trip(spark, tmp_path):
    from fedgrid.sources import tables

    r = np.random.default_rng(0)
    for p in range(2):
        tables.save_message(spark, str(tmp_path / "m"), p, np.full((3, 2), float(p)), r.integers(1, 9, (5, 3)))
    got = tables.load_messages(spark, str(tmp_path / "m"))
    assert len(got) == 2 and got[1][0].shape == (3, 2) and got[0][1].shape == (5, 3)


def test_streams(spark, sf, tmp_path):
    from fedgrid.streaming import sketches

    base = spark.range(200).select("id", (F.col("id") % 3).cast("int").alias("a"), F.timestamp_seconds(F.lit(1_000_000_000) + F.col("id") * 600).alias("ts"))
    for k in range(3):  # the last part repeats the first: a replay
        base.where(F.col("id") % 2 == k % 2).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    source = spark.readStream.schema(base.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    run = sketches.cumulative(source, 8).writeStream.format("memory").queryName("cum").outputMode("complete")
    run.option("checkpointLocation", str(tmp_path / "c1")).trigger(availableNow=True).start().awaitTermination()
    want = {(r.a, r.i): r.alpha for r in sketches.cumulative(base, 8).collect()}
    assert {(r.a, r.i): r.alpha for r in spark.table("cum").collect()} == want
    again = sketches.without_repeats(source, "id", "30 days").writeStream.format("memory").queryName("once").outputMode("append")
    again.option("checkpointLocation", str(tmp_path / "c2")).trigger(availableNow=True).start().awaitTermination()
    assert spark.table("once").count() == 200


def test_stateful_minima(spark, tmp_path):
    from fedgrid.streaming import sketches

    base = spark.range(300).select("id", (F.col("id") % 2).cast("int").alias("a"))
    for k in range(2):
        base.where(F.col("id") % 3 == k).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    old = spark.conf.get("spark.sql.streaming.stateStore.providerClass")
    spark.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        source = spark.readStream.schema(base.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
        run = sketches.stateful_minima(source, keys(16).array()).writeStream.format("memory").queryName("st").outputMode("update")
        run.option("checkpointLocation", str(tmp_path / "c")).trigger(availableNow=True).start().awaitTermination()
    finally:
        spark.conf.set("spark.sql.streaming.stateStore.providerClass", old)
    want = sketch.minima(base.where("id % 3 < 2"), keys(16), 2)
    rows = spark.table("st").collect()
    for a in (0, 1):
        least = np.minimum.reduce([np.frombuffer(r.m, np.uint64) for r in rows if r.a == a])
        assert (least == want[a]).all()


# ---- plans


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark, sf):
    raw = workloads.customers(spark, sf)
    v = views.view(raw, "id", ["c_acctbal", "nation"])
    text = plan(kmeans.assign(v.frame, np.zeros((3, 2))))
    assert "Python" not in text and "CartesianProduct" not in text
    assert "c_mktsegment" not in text.split("ReadSchema")[1][:200]  # a party reads its own columns
    top = plan(__import__("fedgrid.sources.tables", fromlist=["x"]).first_records(raw, ["id"], 5))
    assert "TakeOrderedAndProject" in top


def test_grid_frames_match_the_tensors(spark):
    from fedgrid.operators import grid_frames as G

    _, (sk, n, e2, d2, g), _ = estimates(4.0, 3, 2, n=2000, k=3, repeats=64)
    ghosts = sum(s.shape[1] - 1 for s in sk) * phantoms(sketch_epsilon(e2, d2, 64))

    def tensor(df):
        out = np.zeros((3, 3, 3))
        for r in df.collect():
            out[r.a0, r.a1, r.a2] = r.w
        return out

    raw = weights.complement_union(sk, n, e2, d2, g, how="none")
    frame = G.complement_union_frame(spark, sk, n, ghosts, g)
    assert np.allclose(tensor(frame), raw)
    assert np.allclose(tensor(G.simplex_frame(frame, n)), weights.consistent(raw, n), atol=1e-6)
    sizes = [np.array([900.0, 700.0, 400.0])] * 3
    start = G.product_frame(spark, sizes, n)
    assert np.allclose(tensor(start), weights.product_grid(sizes, n))
    tables = {(a, b): weights.complement_union([sk[a], sk[b]], n, e2, d2, g) for a, b in ((0, 1), (0, 2), (1, 2))}
    by_hand = weights.refine(weights.product_grid(sizes, n), tables, n, np.random.default_rng(0), rounds=6, finalize="none")
    with pytest.warns(UserWarning, match="still moved"):
        assert np.allclose(tensor(G.refine_frame(start, tables, n, sweeps=2, tol=0)), by_hand)
    points = [np.arange(3.0)[:, None] + 10 * p for p in range(3)]
    got = {tuple(r.x): r.w for r in G.weighted_points(frame, points).collect()}
    assert len(got) == (raw > 0).sum() and got[0.0, 10.0, 20.0] == pytest.approx(raw[0, 0, 0]) if raw[0, 0, 0] > 0 else True


def test_large_grids_go_to_frames(spark, sf, monkeypatch):
    df = workloads.gaussian_mixture(spark, 2000, m=6, k=3, sigma=0.05, seed=3).repartition(2, "id").cache()
    parts = views.build_views(df, "id", [["x1", "x2"], ["x3", "x4"], ["x5", "x6"]])
    how = {"k_local": 3, "params": X.params(512, 0), "seed": 1, "delta": 1e-4}
    whole = {m: pipeline.fit(parts, 3, 60.0, method=m, **how) for m in ("pairwise", "complement")}
    wide = views.joined(parts)
    monkeypatch.setattr(weights, "MAX_CELLS", 20)
    for method, small in whole.items():
        got = pipeline.fit(parts, 3, 60.0, method=method, **how)
        assert got.grid is None and got.cell_weights.columns == ["a0", "a1", "a2", "w"]
        for r in got.cell_weights.collect():
            assert r.w == pytest.approx(small.cell_weights[r.a0, r.a1, r.a2], abs=0.01 * 2000)
        assert kmeans.mean_cost(wide, got.centers) <= 1.3 * kmeans.mean_cost(wide, small.centers) + 0.05


# ---- refinement


def test_refinement_converges():
    """Exact tables of all pairs, parties that agree on every user: the grid comes back."""
    n, k, s = 15_000, 5, 4
    base = np.random.default_rng(0).integers(k, size=n)
    exact = exact_of([base] * s, k)
    tables = {p: weights.project(exact, *p) for p in itertools.combinations(range(s), 2)}
    sizes = [exact.sum(axis=tuple(b for b in range(s) if b != a)) for a in range(s)]
    start = weights.product_grid(sizes, n)
    got = weights.refine(start, tables, n, np.random.default_rng(1))
    assert measures.relative_error(got, exact, n) < 0.01
    short = weights.refine(start, tables, n, np.random.default_rng(1), rounds=100)
    assert measures.relative_error(short, exact, n) > 0.5  # which is what a fixed small number of rounds leaves


def test_unsettled_refinement_warns(monkeypatch):
    monkeypatch.setattr(weights, "MAX_ROUNDS", 5)
    tables = {(0, 1): np.eye(2) * 5, (0, 2): np.eye(2)[::-1] * 5, (1, 2): np.eye(2) * 5}  # they contradict each other
    with pytest.warns(UserWarning, match="settled"):
        weights.refine(np.full((2, 2, 2), 10 / 8), tables, 10.0, np.random.default_rng(0))
    assert weights.refine(np.full((2, 2, 2), 10 / 8), tables, 10.0, np.random.default_rng(0), rounds=40).sum() == pytest.approx(10)


def test_refined_beats_direct_at_every_budget():
    """Four parties that agree on nearly all users."""
    for eps in (1.0, 4.0, 16.0):
        runs = [estimates(eps, 4, s, n=15_000, k=5, repeats=4096, copied=0.99)[0] for s in range(2)]
        assert np.mean([r["pairwise"] for r in runs]) < np.mean([r["complement"] for r in runs])


# ---- what one user can change


def test_gaussian_noise_is_valid_at_large_budgets():
    for eps, delta in ((0.1, 1e-5), (1.0, 1e-5), (8.0, 1e-6), (30.0, 1e-4)):
        sd = gaussian_scale(1.0, eps, delta)

        def spent(sd, eps=eps):
            def tail(x):
                return 0.5 * math.erfc(-x / math.sqrt(2))

            return tail(0.5 / sd - eps * sd) - math.exp(eps) * tail(-0.5 / sd - eps * sd)

        assert spent(sd) <= delta * 1.0001 and spent(sd * 0.99) > delta
    assert gaussian_scale(3.0, 8.0, 1e-6) == pytest.approx(3 * gaussian_scale(1.0, 8.0, 1e-6))
    with pytest.raises(ValueError):
        gaussian_scale(1.0, 1.0, 0.0)


def test_values_outside_the_range_count_as_its_ends(spark):
    rows = [(k, [0.1, -0.2]) for k in range(50)]
    far = spark.createDataFrame([*rows, (99, [1e6, -1e6])], "id bigint, x array<double>")
    near = spark.createDataFrame([*rows, (99, [1.0, -1.0])], "id bigint, x array<double>")
    planes = [lsh_forest.directions(2, 4, 0)]
    for a, b in zip(lsh_forest.leaf_sums(far, planes, radius=1.0), lsh_forest.leaf_sums(near, planes, radius=1.0), strict=True):
        assert np.allclose(a, b)
    bound = sum(np.abs(t[:, 1:]).sum() for t in lsh_forest.leaf_sums(far, planes, 1.0))
    assert bound < 50 * 0.3 + 1.5
    c = np.array([[0.0, 0.0], [0.5, -0.5]])
    assert np.allclose(kmeans.cluster_sums(far, [c], radius=1.0)[0], kmeans.cluster_sums(near, [c])[0])
    noise = [kmeans.noisy_lloyd(df, 2, 4.0, HashedNoise("t"), iters=2, init=c) for df in (far, near)]
    assert np.allclose(*noise)


def test_count_for_the_rule_is_charged(spark, sf):
    parts = views.build_views(workloads.customers(spark, sf), "id", [sum(workloads.CUST_GROUPS[:2], []), sum(workloads.CUST_GROUPS[2:], [])])
    got = pipeline.fit(parts, 3, 4.0, method="reports", k_local="auto", params=X.params(64, 0), seed=0)
    assert [r[1] for r in got.ledger.rows].count("count") == 1 and got.n_hat != 150
    assert got.ledger.total()[0] == pytest.approx(4.0)
    a, b = (pipeline.fit(parts, 3, 4.0, method="independence", k_local=2, params=X.params(64, 0)) for _ in range(2))
    assert not np.allclose(a.cell_weights, b.cell_weights)  # no seed: fresh noise
    holed = views.PartyView(parts[0].frame.unionByName(parts[0].frame.limit(1)), parts[0].names)
    with pytest.raises(ValueError):
        pipeline.fit([holed, parts[1]], 3, 4.0)


def test_central_baselines(spark, gauss):
    v, ledger = views.view(gauss, "id", ["x1", "x2", "x3", "x4"]), Ledger()
    costs = [kmeans.mean_cost(v.frame, pipeline.fit_central(v.frame, 3, e, seed=0, delta=1e-4, ledger=ledger)) for e in (None, 30.0, 0.05)]
    assert costs[0] <= costs[1] < costs[2] and ledger.total() == pytest.approx((30.05, 2e-4))


# ---- workloads


def test_workloads_as_published(spark, sf):
    raw, loan = workloads.loan_raw(spark, sf), workloads.workload(spark, sf, "loan")[0]
    cap = np.quantile([r[0] for r in raw.select("l_extendedprice").collect()], 0.95)
    top = loan.agg(F.max("l_extendedprice")).first()[0]
    assert top == pytest.approx(-1 + 2 * (cap - 900) / (105_000 - 900), abs=0.01) and top < 0.95
    trip, names = workloads.workload(spark, sf, "trip")
    groups = X._groups(trip, "trip", names, 2, 0, None)
    assert groups == views.correlation_split(trip, names, 2)
    strong = max(views.correlations(trip, names).items(), key=lambda kv: abs(kv[1]))[0]
    assert not any(set(strong) <= set(g) for g in groups)
    for name in workloads.WORKLOADS:
        df, cols = workloads.workload(spark, sf, name)
        for v in views.build_views(df, "id", [cols]):
            views.validate(v)
        low, high = df.select(F.least(*cols).alias("a"), F.greatest(*cols).alias("b")).agg(F.min("a"), F.max("b")).first()
        assert -1 <= low <= high <= 1


def test_rounds_share_one_plan(spark, gauss):
    v = views.view(gauss, "id", ["x1", "x2", "x3", "x4"])
    texts = set()
    for seed in range(2):
        sent = spark.sparkContext.broadcast([np.random.default_rng(seed).uniform(-1, 1, (3, 4))])
        text = plan(kmeans.sums_frame(v.frame, sent, 4))
        texts.add(re.sub(r"#\d+L?|plan_id=\d+", "", text))
    assert len(texts) == 1


# ---- runs of an experiment have their exact parts in common


def test_runs_share_what_is_exact(spark, sf, monkeypatch):
    """Runs that differ in budget or method cluster, hash and measure the same points once, with the same results."""
    calls = {"lloyd": 0, "minima": 0, "measure_all": 0}

    def counted(module, name):
        made = getattr(module, name)

        def run(*a, **k):
            calls[name] += 1
            return made(*a, **k)

        monkeypatch.setattr(module, name, run)

    counted(pipeline, "lloyd"), counted(pipeline, "minima"), counted(X, "measure_all")
    how = {"parties": (2,), "repeats": 256, "methods": ("pairwise", "complement")}
    rows = X.x5_weight_error(spark, sf, eps=(1.0, 8.0), **how).collect()
    assert calls == {"lloyd": 2, "minima": 2, "measure_all": 1}
    assert [(r.eps, r.method) for r in rows] == [(e, m) for e in (1.0, 8.0) for m in ("pairwise", "complement")]
    alone = X.x5_weight_error(spark, sf, eps=(8.0,), **how | {"methods": ("complement",)}).first()
    assert rows[3].weight_error == alone.weight_error and rows[3].loss == pytest.approx(alone.loss, abs=1e-12)


def test_one_pass_measures_what_single_ones_do(spark, gauss):
    names = ["x1", "x2", "x3", "x4"]
    parts = [views.view(gauss, "id", c) for c in (["x3", "x1"], ["x2", "x4"])]
    wide = views.view(gauss, "id", names).frame
    rng = np.random.default_rng(0)
    own, final, central = [rng.uniform(-1, 1, (3, 2)) for _ in parts], rng.uniform(-1, 1, (4, 4)), rng.uniform(-1, 1, (3, 4))
    run = measures.Clustering(final, (2, 0, 1, 3), (((2, 0), own[0]), ((1, 3), own[1])))
    labelled = wide.join(gauss.select("id", "y"), "id").select("x", "y")
    by_y, by_centers = measures.measure_all(labelled, [run, run], [None, central])
    flat = views.view(gauss, "id", ["x3", "x1", "x2", "x4"]).frame
    found = kmeans.assign(flat, final).select("id", "a")
    assert by_y.loss == pytest.approx(kmeans.mean_cost(flat, final))
    labels = [kmeans.assign(v.frame, c).select("id", "a") for v, c in zip(parts, own, strict=True)]
    assert np.array_equal(by_y.cells, pipeline.exact_weights(labels, [3, 3]))
    truth = kmeans.assign(wide, central).select("id", F.col("a").alias("y"))
    for seen, y in ((by_y, gauss.select("id", "y")), (by_centers, truth)):
        assert measures.v_of_counts(seen.pairs) == pytest.approx(measures.v_measure(found.join(y, "id")))


def test_kernels_match_the_columns(spark, gauss):
    """Leaf sums and correlations are those of the engine's own expressions, nulls and constants too."""
    v = views.view(gauss, "id", ["x1", "x2", "x3"])
    planes = lsh_forest.directions(3, 4, 1)
    table = lsh_forest.leaf_sums(v.frame, [planes], radius=0.5)[0]
    cut = F.transform("x", lambda e: F.greatest(F.least(e, F.lit(0.5)), F.lit(-0.5)))
    coded = v.frame.select(cut.alias("x")).withColumn("c", lsh_forest.code(F.col("x"), planes))
    for r in coded.groupBy("c").agg(F.count(F.lit(1)).alias("n"), F.sum(F.get("x", F.lit(1))).alias("s")).collect():
        assert table[r.c, 0] == r.n and table[r.c, 2] == pytest.approx(r.s)
    df = gauss.select(
        F.when(F.col("id") % 3 > 0, F.col("x1")).alias("a"), F.when(F.col("id") % 5 > 0, F.col("x2") + 1e6).alias("b"),
        F.lit(0.1).alias("same"), F.lit(None).cast("double").alias("none"), (F.col("id") % 7).alias("whole"),
    )
    for (a, b), r in views.correlations(df, df.columns).items():
        flat = {a, b} & {"same", "none"}  # the engine's own fails on these
        assert r == (0.0 if flat else pytest.approx(df.agg(F.corr(F.col(a), F.col(b).cast("double"))).first()[0], abs=1e-7))
