"""Driver queries of the engine with their SQL: each entry shows one method, baseline, measure or operator.

Labels of the users are cut from real columns (LABELS), noise comes from md5 of the keys, so that any SQL engine
computes the same rows.
"""

from __future__ import annotations

import itertools
import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fedgrid.functions import columns as C
from fedgrid.functions.estimators import bias, cardinality_column
from fedgrid import checkpoints
from fedgrid.operators import grid_frames, kmeans, local_dp, lsh_forest, measures, sketch, views, weights
from fedgrid.plans import experiments as X
from fedgrid.plans import pipeline, workloads
from fedgrid.operators.views import PartyView, build_views, correlations
from fedgrid.privacy import HashedNoise, bytes_per_party, choose_k_local, floor_value, phantoms, split
from fedgrid.sources.tables import first_records, load
from fedgrid.streaming import sketches as streams

U = "((('0x' || substr(md5({}), 1, 15))::BIGINT + 1) / 1152921504606846976.0)"
M, GAMMA = 16, 0.1
LOG = math.log1p(GAMMA)

# Three parties' clusters of the customers.
LABELS = """
labels AS (
  SELECT c_custkey AS id,
         CASE WHEN c_acctbal < 2500 THEN 0 WHEN c_acctbal < 6000 THEN 1 ELSE 2 END AS a1,
         c_nationkey % 3 AS a2,
         CASE WHEN coalesce(n, 0) < 8 THEN 0 WHEN n < 12 THEN 1 ELSE 2 END AS a3
  FROM customer LEFT JOIN (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey) ON c_custkey = o_custkey
)"""
GRID2 = "cells AS (SELECT p.a AS a1, q.a AS a2 FROM (SELECT unnest(range(3)) AS a) p, (SELECT unnest(range(3)) AS a) q)"
SKETCH = f""", long AS (
  SELECT party, a, i, max(CAST(greatest(ceil(-ln({U.format("id || '|' || i")}) / {LOG!r}), 1) AS INT)) AS alpha
  FROM (SELECT 1 AS party, a1 AS a, id FROM labels UNION ALL SELECT 2, a2, id FROM labels UNION ALL SELECT 3, a3, id FROM labels)
  CROSS JOIN (SELECT unnest(range(1, {M + 1})) AS i) GROUP BY party, a, i
)"""


def labels(spark: SparkSession, sf: str) -> DataFrame:
    n = load(spark, sf, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))
    c = load(spark, sf, "customer").join(n, F.col("c_custkey") == F.col("o_custkey"), "left")
    few = F.coalesce("n", F.lit(0))
    return c.select(
        F.col("c_custkey").alias("id"),
        F.when(F.col("c_acctbal") < 2500, 0).when(F.col("c_acctbal") < 6000, 1).otherwise(2).alias("a1"),
        (F.col("c_nationkey") % 3).alias("a2"),
        F.when(few < 8, 0).when(few < 12, 1).otherwise(2).alias("a3"),
    )


def long_labels(spark: SparkSession, sf: str) -> DataFrame:
    """(party, id, a): all three parties' labels in one table."""
    parts = F.array(*[F.struct(F.lit(p).alias("party"), F.col(f"a{p}").alias("a")) for p in (1, 2, 3)])
    return labels(spark, sf).select("id", F.inline(parts))


def long_sketch(spark: SparkSession, sf: str) -> DataFrame:
    """(party, a, i, alpha) without noise, over M md5 keys."""
    return sketch.sketch_rows(long_labels(spark, sf), M, GAMMA, by=("party", "a"))


def party_sketches(spark: SparkSession, sf: str, parties=(1, 2, 3)) -> list[np.ndarray]:
    """The released tables (M x 3) of the parties, as the server gets them."""
    df = labels(spark, sf)
    return [sketch.collected(sketch.sketch_rows(df.select("id", F.col(f"a{p}").alias("a")), M, GAMMA), 3, M) for p in parties]


def sketch_frame(spark: SparkSession, tables: dict[int, np.ndarray], value: str = "alpha") -> DataFrame:
    """Tables by party as (party, a, i, value) rows."""
    rows = [(p, a, i + 1, int(t[i, a])) for p, t in tables.items() for i in range(t.shape[0]) for a in range(t.shape[1])]
    return spark.createDataFrame(rows, f"party int, a int, i bigint, {value} int")


def label_frames(spark: SparkSession, sf: str, names=("a1", "a2")) -> list[DataFrame]:
    df = labels(spark, sf)
    return [df.select("id", F.col(c).alias("a")) for c in names]


def exact(spark: SparkSession, sf: str, names=("a1", "a2", "a3")) -> np.ndarray:
    return pipeline.exact_weights(label_frames(spark, sf, names), [3] * len(names))


def _view(df: DataFrame, key: str) -> PartyView:
    """Users alone, without attributes."""
    return PartyView(df.select(F.col(key).alias("id"), F.array(F.lit(0.0)).alias("x")).distinct(), ("one",))


def _values(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema)


def _grid_rows(spark: SparkSession, w: np.ndarray, digits: int | None, names=("a1", "a2", "a3")) -> DataFrame:
    kind, read = ("bigint", lambda v: int(round(v))) if digits is None else ("double", lambda v: round(float(v), digits))
    rows = [(*map(int, i), read(w[i])) for i in np.ndindex(w.shape)]
    return spark.createDataFrame(rows, ", ".join(f"{n} int" for n in names[: w.ndim]) + f", w {kind}")


# Users with orders of each priority: the user counts that budgets, costs and bounds are told for.
USERS = "users AS (SELECT CAST(substr(o_orderpriority, 1, 1) AS INT) AS priority, count(DISTINCT o_custkey) AS n FROM orders WHERE o_custkey IS NOT NULL GROUP BY 1)"


def users(spark: SparkSession, sf: str) -> list[tuple[int, int]]:
    """(priority, number of users); one row for each priority is collected."""
    priority = F.substring("o_orderpriority", 1, 1).cast("int").alias("priority")
    o = load(spark, sf, "orders").where(F.col("o_custkey").isNotNull())
    return [(r["priority"], r["n"]) for r in o.groupBy(priority).agg(F.count_distinct("o_custkey").alias("n")).collect()]


QUERIES: dict[str, object] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql:
            SQL[name] = sql
        return f

    return keep


# ---- preparation -------------------------------------------------------------------------------------


@query("normalize_range_lineitem", """
SELECT l_orderkey, l_partkey, round(-1.0 + (least(greatest(l_quantity, 1.0), 50.0) - 1.0) * (2.0 / 49.0), 6) AS quantity,
       round(-1.0 + (least(greatest(l_tax, 0.0), 0.08) - 0.0) * (2.0 / 0.08), 6) AS tax FROM lineitem""")
def _(spark, sf):
    df = load(spark, sf, "lineitem")
    return df.select("l_orderkey", "l_partkey", F.round(C.scale("l_quantity", 1.0, 50.0), 6).alias("quantity"),
                     F.round(C.scale("l_tax", 0.0, 0.08), 6).alias("tax"))


@query("normalize_minmax_lineitem", """
SELECT l_orderkey, l_partkey, round(-1.0 + (l_extendedprice - lo) * (2.0 / (hi - lo)), 6) AS price
FROM lineitem, (SELECT min(l_extendedprice) AS lo, max(l_extendedprice) AS hi FROM lineitem)""")
def _(spark, sf):
    df = load(spark, sf, "lineitem")
    lo, hi = C.observed_ranges(df, ["l_extendedprice"])["l_extendedprice"]
    return df.select("l_orderkey", "l_partkey", F.round(C.scale("l_extendedprice", lo, hi), 6).alias("price"))


@query("normalize_target_ranges", """
SELECT l_orderkey, l_partkey, round(-3.0 + (least(greatest(l_quantity, 1.0), 50.0) - 1.0) * (6.0 / 49.0), 6) AS quantity FROM lineitem""")
def _(spark, sf):
    df = C.scale_to_range(load(spark, sf, "lineitem"), {"l_quantity": (1.0, 50.0)}, {"l_quantity": (-3.0, 3.0)})
    return df.select("l_orderkey", "l_partkey", F.round("l_quantity", 6).alias("quantity"))


@query("clip_q95_lineitem", """
WITH q AS (SELECT quantile_cont(l_extendedprice, 0.95) AS cap FROM lineitem)
SELECT l_returnflag, count(*) AS n, round(max(least(l_extendedprice, cap)), 4) AS top, round(avg(least(l_extendedprice, cap)), 4) AS mean
FROM lineitem, q GROUP BY l_returnflag""")
def _(spark, sf):
    df = C.clip_upper(load(spark, sf, "lineitem"), ["l_extendedprice"], 0.95, exact=True)
    return df.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), F.round(F.max("l_extendedprice"), 4).alias("top"),
                                          F.round(F.avg("l_extendedprice"), 4).alias("mean"))


@query("week_seconds_events", """
SELECT event_id, CAST(epoch(date_trunc('second', ts)) - epoch(date_trunc('week', ts)) AS DOUBLE) AS second FROM events""")
def _(spark, sf):
    return load(spark, sf, "events").select("event_id", C.week_seconds("ts").alias("second"))


@query("first_records_loan", """
SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity FROM lineitem
ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate LIMIT 1000""")
def _(spark, sf):
    keys = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate"]
    return first_records(load(spark, sf, "lineitem"), keys, 1000).select(*keys[:4], "l_quantity")


@query("party_view_customer", """
SELECT c_custkey AS id, c_acctbal, CAST(c_nationkey AS DOUBLE) AS nation FROM customer""")
def _(spark, sf):
    return workloads.customers_raw(spark, sf).select("id", "c_acctbal", "nation")


@query("party_view_orders", """
SELECT c_custkey AS id, CAST(count(o_orderkey) AS DOUBLE) AS n_orders, round(coalesce(sum(o_totalprice), 0), 2) AS order_total
FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey""")
def _(spark, sf):
    return workloads.customers_raw(spark, sf).select("id", "n_orders", F.round("order_total", 2).alias("order_total"))


@query("party_view_lines", """
SELECT c_custkey AS id, CAST(count(l_orderkey) AS DOUBLE) AS n_lines, round(coalesce(sum(l_extendedprice), 0), 2) AS line_total,
       round(coalesce(avg(l_quantity), 0), 4) AS mean_quantity
FROM customer LEFT JOIN orders ON c_custkey = o_custkey LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY c_custkey""")
def _(spark, sf):
    raw = workloads.customers_raw(spark, sf)
    return raw.select("id", "n_lines", F.round("line_total", 2).alias("line_total"), F.round("mean_quantity", 4).alias("mean_quantity"))


@query("party_view_events", """
SELECT c_custkey AS id, CAST(count(event_id) AS DOUBLE) AS n_events, round(coalesce(sum(value), 0), 3) AS event_total
FROM customer LEFT JOIN events ON c_custkey = user_id GROUP BY c_custkey""")
def _(spark, sf):
    return workloads.customers_raw(spark, sf).select("id", "n_events", F.round("event_total", 3).alias("event_total"))


@query("wide_loan_16", """
SELECT l_returnflag AS flag_text, count(*) AS n, round(avg(l_extendedprice * (1 - l_discount) * (1 + l_tax)), 4) AS net_price,
       round(avg(o_totalprice), 4) AS o_totalprice, round(avg(c_acctbal), 4) AS c_acctbal, round(avg(p_retailprice), 4) AS p_retailprice,
       round(avg(s_acctbal), 4) AS s_acctbal, round(avg(CAST(substr(o_orderpriority, 1, 1) AS INT)), 4) AS priority
FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey
JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey GROUP BY l_returnflag""")
def _(spark, sf):
    raw = workloads.loan_raw(spark, sf)
    text = F.element_at(F.array(*map(F.lit, ["A", "N", "R"])), F.col("flag") + 1)
    names = ["net_price", "o_totalprice", "c_acctbal", "p_retailprice", "s_acctbal", "priority"]
    return raw.groupBy(text.alias("flag_text")).agg(F.count(F.lit(1)).alias("n"), *[F.round(F.avg(c), 4).alias(c) for c in names])


@query("align_complete", """
SELECT DISTINCT c_custkey AS id FROM customer JOIN orders ON c_custkey = o_custkey JOIN events ON c_custkey = user_id""")
def _(spark, sf):
    parts = [_view(load(spark, sf, t), key) for t, key in (("customer", "c_custkey"), ("orders", "o_custkey"), ("events", "user_id"))]
    return views.align(parts, "complete")[0].frame.select("id")


@query("align_semi", "SELECT DISTINCT user_id AS id FROM events WHERE EXISTS (SELECT 1 FROM orders WHERE o_custkey = user_id)")
def _(spark, sf):
    parts = [_view(load(spark, sf, "orders"), "o_custkey"), _view(load(spark, sf, "events"), "user_id")]
    return views.align(parts, "complete")[1].frame.select("id")


@query("align_impute", """
SELECT c_custkey AS id, count(user_id) = 0 AS filled FROM customer LEFT JOIN (SELECT DISTINCT user_id FROM events) ON user_id = c_custkey GROUP BY c_custkey""")
def _(spark, sf):
    parts = [_view(load(spark, sf, "customer"), "c_custkey"), _view(load(spark, sf, "events").where("user_id < 1000000000"), "user_id")]
    got = views.align(parts, "impute", default=-1.0)[1].frame
    return got.join(parts[0].frame.select("id"), "id", "left_semi").select("id", (F.get("x", F.lit(0)) == -1.0).alias("filled"))


@query("align_coverage_fullouter", """
SELECT o IS NOT NULL AS in_orders, e IS NOT NULL AS in_events, count(*) AS users
FROM (SELECT DISTINCT o_custkey AS o FROM orders) FULL JOIN (SELECT DISTINCT user_id AS e FROM events) ON o = e GROUP BY 1, 2""")
def _(spark, sf):
    got = views.coverage([_view(load(spark, sf, "orders"), "o_custkey"), _view(load(spark, sf, "events"), "user_id")])
    return got.withColumnsRenamed({"in_0": "in_orders", "in_1": "in_events"})


@query("align_anti", "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def _(spark, sf):
    got = views.unmatched(_view(load(spark, sf, "orders"), "o_orderkey"), _view(load(spark, sf, "lineitem"), "l_orderkey"))
    return got.withColumnRenamed("id", "o_orderkey")


@query("pair_correlations_cust", """
WITH v AS (SELECT c_custkey, count(DISTINCT o_orderkey) AS n_orders, count(l_orderkey) AS n_lines, coalesce(sum(l_extendedprice), 0) AS line_total
           FROM customer LEFT JOIN orders ON c_custkey = o_custkey LEFT JOIN lineitem ON l_orderkey = o_orderkey GROUP BY c_custkey)
SELECT 'n_orders' AS x, 'n_lines' AS y, round(corr(n_orders, n_lines), 6) AS r FROM v
UNION ALL SELECT 'n_orders', 'line_total', round(corr(n_orders, line_total), 6) FROM v
UNION ALL SELECT 'n_lines', 'line_total', round(corr(n_lines, line_total), 6) FROM v""")
def _(spark, sf):
    found = correlations(workloads.customers_raw(spark, sf), ["n_orders", "n_lines", "line_total"])
    return _values(spark, [(a, b, round(r, 6)) for (a, b), r in found.items()], "x string, y string, r double")


# ---- clustering --------------------------------------------------------------------------------------

CENTERS = [[-0.6, -0.5], [0.0, 0.2], [0.6, 0.7]]
_POINTS = """
p AS (SELECT c_custkey AS id, -1.0 + (least(greatest(c_acctbal, -1000.0), 10000.0) + 1000.0) * (2.0 / 11000.0) AS x0,
             -1.0 + c_nationkey * (2.0 / 24.0) AS x1 FROM customer
), d AS (SELECT *, {} FROM p
), n AS (SELECT *, CASE WHEN d0 <= d1 AND d0 <= d2 THEN 0 WHEN d1 <= d2 THEN 1 ELSE 2 END AS a, least(d0, d1, d2) AS d FROM d)""".format(
    ", ".join(f"(x0 - {a!r}) * (x0 - {a!r}) + (x1 - {b!r}) * (x1 - {b!r}) AS d{k}".replace("- -", "+ ") for k, (a, b) in enumerate(CENTERS))
)


def points(spark: SparkSession, sf: str) -> DataFrame:
    c = load(spark, sf, "customer")
    x = F.array(C.scale("c_acctbal", -1000.0, 10000.0), C.scale("c_nationkey", 0.0, 24.0))
    return c.select(F.col("c_custkey").alias("id"), x.alias("x"))


@query("assign_nearest_fixed", f"WITH {_POINTS} SELECT id, a, round(d, 6) AS d FROM n")
def _(spark, sf):
    return kmeans.assign(points(spark, sf), np.array(CENTERS)).select("id", "a", F.round("d", 6).alias("d"))


@query("lloyd_one_step", f"WITH {_POINTS} SELECT a, count(*) AS n, round(avg(x0), 6) AS c0, round(avg(x1), 6) AS c1 FROM n GROUP BY a")
def _(spark, sf):
    sums = kmeans.cluster_sums(points(spark, sf), [np.array(CENTERS)])[0]
    rows = [(a, int(s[0]), round(float(s[1] / s[0]), 6), round(float(s[2] / s[0]), 6)) for a, s in enumerate(sums) if s[0]]
    return _values(spark, rows, "a int, n bigint, c0 double, c1 double")


@query("cost_fixed_centers", f"WITH {_POINTS} SELECT round(sum(d), 4) AS cost, round(avg(d), 6) AS mean_cost FROM n")
def _(spark, sf):
    rows = kmeans.assign(points(spark, sf), np.array(CENTERS))
    return rows.agg(F.round(F.sum("d"), 4).alias("cost"), F.round(F.avg("d"), 6).alias("mean_cost"))


@query("weighted_cost_grid", f"""
WITH {_POINTS}, w AS (SELECT n.*, c_nationkey + 1 AS w FROM n JOIN customer ON id = c_custkey)
SELECT a, round(sum(w * d), 4) AS cost, CAST(sum(w) AS DOUBLE) AS w FROM w GROUP BY a""")
def _(spark, sf):
    df = load(spark, sf, "customer").select(F.col("c_custkey").alias("id"), (F.col("c_nationkey") + 1).alias("w"))
    sums = kmeans.cluster_sums(points(spark, sf).join(df, "id"), [np.array(CENTERS)], "w")[0]
    rows = [(a, round(float(s[3]), 4), float(s[0])) for a, s in enumerate(sums) if s[0]]
    return _values(spark, rows, "a int, cost double, w double")


def _lloyd_sql(rounds: int, weight: str = "1") -> str:
    """So many Lloyd steps from CENTERS, one CTE after the other."""
    start = ", ".join(f"({k}, {a!r}, {b!r})" for k, (a, b) in enumerate(CENTERS))
    parts = [f"WITH {_POINTS}, q AS (SELECT id, x0, x1, CAST({weight} AS DOUBLE) AS w FROM p JOIN customer ON id = c_custkey)",
             f"k0(a, c0, c1) AS (VALUES {start})"]
    for t in range(1, rounds + 1):
        d = f"(x0 - c0) * (x0 - c0) + (x1 - c1) * (x1 - c1)"
        parts.append(f"n{t} AS MATERIALIZED (SELECT id, any_value(x0) AS x0, any_value(x1) AS x1, any_value(w) AS w, arg_min(a, {d}) AS a FROM q, k{t - 1} GROUP BY id)")
        parts.append(f"k{t}(a, c0, c1) AS MATERIALIZED (SELECT a, sum(w * x0) / sum(w), sum(w * x1) / sum(w) FROM n{t} GROUP BY a)")
    return ", ".join(parts) + f" SELECT a, round(c0, 6) AS c0, round(c1, 6) AS c1 FROM k{rounds}"


def _center_rows(spark, c):
    return _values(spark, [(a, round(float(x[0]), 6), round(float(x[1]), 6)) for a, x in enumerate(c)], "a int, c0 double, c1 double")


@query("lloyd_five_steps", _lloyd_sql(5))
def _(spark, sf):
    return _center_rows(spark, kmeans.lloyd(points(spark, sf), 3, init=np.array(CENTERS), max_iter=5, tol=0.0))


@query("weighted_lloyd_step_grid", _lloyd_sql(1, "c_nationkey + 1"))
def _(spark, sf):
    w = load(spark, sf, "customer").select(F.col("c_custkey").alias("id"), (F.col("c_nationkey") + 1).alias("w"))
    return _center_rows(spark, kmeans.lloyd(points(spark, sf).join(w, "id"), 3, weight="w", init=np.array(CENTERS), max_iter=1))


@query("mean_cost", f"WITH {_POINTS} SELECT round(avg(d), 6) AS mean_cost FROM n")
def _(spark, sf):
    return _values(spark, [(round(kmeans.mean_cost(points(spark, sf), np.array(CENTERS)), 6),)], "mean_cost double")


_LAP = "(CASE WHEN {u} < 0.5 THEN {s} * ln(2 * {u}) ELSE -{s} * ln(2 * (1 - {u}) + 1e-18) END)"


# budget 0.5 in one round: counts get Laplace(4), each of two sums Laplace(8); draws in the order counts, sums by cluster
@query("noisy_lloyd_step", f"""
WITH {_POINTS}, g AS (SELECT a, count(*) AS n, sum(x0) AS s0, sum(x1) AS s1 FROM n GROUP BY a
), z AS (SELECT a, n + {_LAP.format(u=U.format("'nl|' || a"), s=4.0)} AS n, s0 + {_LAP.format(u=U.format("'nl|' || (3 + 2 * a)"), s=8.0)} AS s0,
                s1 + {_LAP.format(u=U.format("'nl|' || (4 + 2 * a)"), s=8.0)} AS s1 FROM g)
SELECT a, round(greatest(least(s0 / n, 1), -1), 6) AS c0, round(greatest(least(s1 / n, 1), -1), 6) AS c1 FROM z""")
def _(spark, sf):
    return _center_rows(spark, kmeans.noisy_lloyd(points(spark, sf), 3, 0.5, HashedNoise("nl"), iters=1, init=np.array(CENTERS)))


PLANES = [[0.8, -0.6], [0.3, 0.9], [-0.5, 0.4]]
_CODE = " + ".join(f"(CASE WHEN 0.0 + x0 * {a!r} + x1 * {b!r} >= 0 THEN {1 << (2 - k)} ELSE 0 END)" for k, (a, b) in enumerate(PLANES))


@query("lsh_codes", f"WITH {_POINTS} SELECT id, CAST({_CODE} AS BIGINT) AS code FROM p")
def _(spark, sf):
    return points(spark, sf).select("id", lsh_forest.code(F.col("x"), np.array(PLANES)).alias("code"))


@query("lsh_prefix_counts", f"""
WITH {_POINTS}, c AS (SELECT CAST({_CODE} AS BIGINT) AS code FROM p)
SELECT depth, code >> (3 - depth) AS prefix, count(*) AS n FROM c, (SELECT unnest(range(4)) AS depth) GROUP BY 1, 2""")
def _(spark, sf):
    leaves = lsh_forest.leaf_sums(points(spark, sf), [np.array(PLANES)], radius=1.0)[0]
    tables = [lsh_forest.prefix_table(leaves, d) for d in range(4)]
    rows = [(d, p, int(t[p, 0])) for d, t in enumerate(tables) for p in range(1 << d) if t[p, 0]]
    return _values(spark, rows, "depth bigint, prefix bigint, n bigint")


# ---- exact grids, marginals, identity ----------------------------------------------------------------


@query("exact_grid_s2", f"""
WITH {LABELS}, {GRID2} SELECT c.a1, c.a2, count(id) AS w FROM cells c LEFT JOIN labels l ON c.a1 = l.a1 AND c.a2 = l.a2 GROUP BY c.a1, c.a2""")
def _(spark, sf):
    return _grid_rows(spark, exact(spark, sf, ("a1", "a2")), None)


@query("exact_grid_s3", f"WITH {LABELS} SELECT a1, a2, a3, count(*) AS w FROM labels GROUP BY a1, a2, a3")
def _(spark, sf):
    return _grid_rows(spark, exact(spark, sf), None).where("w > 0")


@query("exact_grid_s4", f"""
WITH {LABELS} SELECT a1, a2, a3, CAST(id % 2 AS INT) AS a4, count(*) AS w FROM labels GROUP BY ALL""")
def _(spark, sf):
    df = labels(spark, sf).withColumn("a4", (F.col("id") % 2).cast("int"))
    w = pipeline.exact_weights([df.select("id", F.col(c).alias("a")) for c in ("a1", "a2", "a3", "a4")], [3, 3, 3, 2])
    return _grid_rows(spark, w, None, ("a1", "a2", "a3", "a4")).where("w > 0")


@query("grid_points_cross", f"""
WITH {LABELS}, p AS (SELECT a1 AS a, avg(c_acctbal) AS x FROM labels JOIN customer ON id = c_custkey GROUP BY a1),
q AS (SELECT a2 AS a, avg(c_nationkey) AS y FROM labels JOIN customer ON id = c_custkey GROUP BY a2)
SELECT p.a AS a1, q.a AS a2, round(p.x, 5) AS x, round(q.y, 5) AS y FROM p, q""")
def _(spark, sf):
    """The grid of two parties' local centers: the mean balances and the mean nations of their own clusters."""
    wide = labels(spark, sf).join(load(spark, sf, "customer"), F.col("id") == F.col("c_custkey"))
    axes = [sorted(tuple(r) for r in wide.groupBy(a).agg(F.avg(x)).collect()) for a, x in (("a1", "c_acctbal"), ("a2", "c_nationkey"))]
    g = weights.grid_points([np.array([[x] for _, x in axis]) for axis in axes])
    cells = itertools.product(*[[a for a, _ in axis] for axis in axes])
    rows = [(*cell, round(float(p[0]), 5), round(float(p[1]), 5)) for cell, p in zip(cells, g, strict=True)]
    return _values(spark, rows, "a1 int, a2 int, x double, y double")


@query("pair_marginals_grouping_sets", f"""
WITH {LABELS} SELECT a1, a2, a3, count(*) AS w FROM labels GROUP BY GROUPING SETS ((a1, a2), (a1, a3), (a2, a3))""")
def _(spark, sf):
    return grid_frames.pair_tables(labels(spark, sf), ["a1", "a2", "a3"])


@query("project_grid_pair", f"WITH {LABELS} SELECT a1, a3, count(*) AS w FROM labels GROUP BY a1, a3")
def _(spark, sf):
    return _grid_rows(spark, weights.project(exact(spark, sf), 0, 2), None, ("a1", "a3")).where("w > 0")


# the users outside of the union of the complements are counted as such, and compared with the cell itself
@query("complement_identity_check", f"""
WITH {LABELS}, {GRID2} SELECT c.a1, c.a2, count(*) FILTER (l.a1 = c.a1 AND l.a2 = c.a2) AS inside, count(*) FILTER (l.a1 <> c.a1 OR l.a2 <> c.a2) AS rest
FROM cells c, labels l GROUP BY c.a1, c.a2""")
def _(spark, sf):
    w = exact(spark, sf, ("a1", "a2"))
    cells = F.array(*[F.struct(F.lit(i).alias("c1"), F.lit(j).alias("c2")) for i, j in itertools.product(range(3), repeat=2)])
    away = labels(spark, sf).select("id", "a1", "a2", F.inline(cells)).where("a1 <> c1 OR a2 <> c2")
    away = away.groupBy("c1", "c2").agg(F.count_distinct("id").alias("rest"))
    rows = _grid_rows(spark, w, None).withColumnRenamed("w", "inside")
    return rows.join(away, (F.col("a1") == F.col("c1")) & (F.col("a2") == F.col("c2"))).select("a1", "a2", "inside", "rest")


@query("independence_nonoise", f"""
WITH {LABELS}, n AS (SELECT count(*) AS n FROM labels), p AS (SELECT a1, count(*) AS f FROM labels GROUP BY a1), q AS (SELECT a2, count(*) AS f FROM labels GROUP BY a2)
SELECT a1, a2, round(n * (p.f / n) * (q.f / n), 4) AS w FROM p, q, n""")
def _(spark, sf):
    w = exact(spark, sf, ("a1", "a2"))
    return _grid_rows(spark, weights.independence([w.sum(1), w.sum(0)], w.sum()), 4)


@query("independence_noisy_md5", f"""
WITH {LABELS}, n AS (SELECT count(*) AS n FROM labels),
p AS (SELECT a1, greatest(count(*) + {_LAP.format(u=U.format("'h1|' || a1"), s=4.0)}, 0) AS f FROM labels GROUP BY a1),
q AS (SELECT a2, greatest(count(*) + {_LAP.format(u=U.format("'h2|' || a2"), s=4.0)}, 0) AS f FROM labels GROUP BY a2)
SELECT a1, a2, round(n * (p.f / n) * (q.f / n), 4) AS w FROM p, q, n""")
def _(spark, sf):
    parts = [pipeline.party_histogram(f, 3, 0.25, HashedNoise(t)) for f, t in zip(label_frames(spark, sf), ("h1", "h2"), strict=True)]
    return _grid_rows(spark, weights.independence(parts, labels(spark, sf).count()), 4)


# ---- sketches ----------------------------------------------------------------------------------------


@query("geometric_hash_g1", "SELECT c_custkey AS id, CAST(61 - length(bin(('0x' || substr(md5(c_custkey || '|' || 1), 1, 15))::BIGINT)) AS INT) AS v FROM customer")
def _(spark, sf):
    text = F.concat_ws("|", F.col("c_custkey").cast("string"), F.lit("1"))
    return load(spark, sf, "customer").select(F.col("c_custkey").alias("id"), C.geometric_base2(C.md5_hash60(text)).alias("v"))


@query("geometric_hash_g01", f"SELECT c_custkey AS id, CAST(greatest(ceil(-ln({U.format("c_custkey || '|' || 1")}) / {LOG!r}), 1) AS INT) AS v FROM customer")
def _(spark, sf):
    return load(spark, sf, "customer").select(F.col("c_custkey").alias("id"), C.geometric_from_uniform(C.md5_uniform("c_custkey", 1), GAMMA).alias("v"))


@query("fm_sketch_small_m", f"WITH {LABELS} {SKETCH} SELECT a, i, alpha FROM long WHERE party = 1")
def _(spark, sf):
    return sketch.sketch_rows(labels(spark, sf).select("id", F.col("a1").alias("a")), M, GAMMA).select("a", F.col("i").cast("bigint").alias("i"), "alpha")


@query("partition_sketch_long", f"WITH {LABELS} {SKETCH} SELECT party, a, i, alpha FROM long")
def _(spark, sf):
    return long_sketch(spark, sf).select("party", "a", F.col("i").cast("bigint").alias("i"), "alpha")


@query("fm_union_max", f"WITH {LABELS} {SKETCH} SELECT party, i, max(alpha) AS alpha FROM long GROUP BY party, i")
def _(spark, sf):
    joined = [t[:, [0]] for t in party_sketches(spark, sf)]
    for p, t in enumerate(party_sketches(spark, sf)):
        for a in (1, 2):
            joined[p] = sketch.union(joined[p], t[:, [a]])
    return sketch_frame(spark, {p + 1: t for p, t in enumerate(joined)}).drop("a")


@query("fm_cardinality_corrected", f"WITH {LABELS} {SKETCH} SELECT party, a, round(count(*) / sum(pow({1 + GAMMA!r}, -alpha)) * {bias(GAMMA)!r}, 4) AS n FROM long GROUP BY party, a")
def _(spark, sf):
    packed = sketch.sketch_arrays(long_sketch(spark, sf), ["party", "a"])
    return packed.select("party", "a", F.round(cardinality_column(F.col("alpha"), GAMMA), 4).alias("n"))


@query("fm_min_hash_rewrite", f"WITH {LABELS} {SKETCH} SELECT a, i, alpha FROM long WHERE party = 2")
def _(spark, sf):
    rows = sketch.sketch_rows(labels(spark, sf).select("id", F.col("a2").alias("a")), M, GAMMA)
    return rows.select("a", F.col("i").cast("bigint").alias("i"), "alpha")


EPS_ROW = 0.5
_NP, _FLOOR = phantoms(EPS_ROW), floor_value(EPS_ROW, GAMMA)


# phantoms of a cell are one draw from the distribution of their maximum; draws go by repeat, then cluster
@query("dp_sketch_floor_phantom", f"""
WITH {LABELS} {SKETCH}, ghosts AS (
  SELECT *, CAST(greatest(ceil(-ln(1 - pow({U.format("'g' || party || '|' || ((i - 1) * 3 + a)")}, {1 / _NP!r})) / {LOG!r}), 1) AS INT) AS g FROM long)
SELECT party, a, i, greatest(alpha, g, {_FLOOR}) AS alpha FROM ghosts""")
def _(spark, sf):
    tables = party_sketches(spark, sf)
    return sketch_frame(spark, {p: sketch.privatise(t, EPS_ROW, GAMMA, HashedNoise(f"g{p}")) for p, t in enumerate(tables, start=1)})


_LOO = """, loo AS (SELECT x.party, x.a, x.i, max(y.alpha) AS rest FROM long x JOIN long y ON x.party = y.party AND x.i = y.i AND x.a <> y.a GROUP BY ALL)"""
_UNION = """, u AS (SELECT p.a AS a1, q.a AS a2, p.i, greatest(p.rest, q.rest) AS u FROM loo p JOIN loo q ON p.i = q.i WHERE p.party = 1 AND q.party = 2)"""


@query("leave_one_out_max", f"WITH {LABELS} {SKETCH} {_LOO} SELECT party, a, i, rest FROM loo")
def _(spark, sf):
    tables = party_sketches(spark, sf)
    return sketch_frame(spark, {p: weights.leave_one_out(t) for p, t in enumerate(tables, start=1)}, "rest")


@query("union_sketch_grid_s2", f"WITH {LABELS} {SKETCH} {_LOO} {_UNION} SELECT a1, a2, i, u FROM u")
def _(spark, sf):
    unions = weights.complement_unions(party_sketches(spark, sf, (1, 2)))
    rows = [(head[0], a, i + 1, int(u[i, a])) for head, u in unions for i in range(M) for a in range(3)]
    return _values(spark, rows, "a1 int, a2 int, i bigint, u int")


_RAW = f""", raw AS (SELECT a1, a2, (SELECT count(*) FROM labels) - count(*) / sum(pow({1 + GAMMA!r}, -u)) * {bias(GAMMA)!r} AS w FROM u GROUP BY a1, a2)"""


def _raw(spark, sf):
    n = labels(spark, sf).count()
    return weights.complement_weights(party_sketches(spark, sf, (1, 2)), n, 0, GAMMA), n


@query("complement_union_raw_s2", f"WITH {LABELS} {SKETCH} {_LOO} {_UNION} {_RAW} SELECT a1, a2, round(w, 4) AS w FROM raw")
def _(spark, sf):
    return _grid_rows(spark, _raw(spark, sf)[0], 4)


@query("simplex_consistency", f"""
WITH {LABELS} {SKETCH} {_LOO} {_UNION} {_RAW}, n AS (SELECT count(*) AS n FROM labels),
r AS (SELECT *, row_number() OVER o AS k, (sum(w) OVER o - n) / row_number() OVER o AS t FROM raw, n WINDOW o AS (ORDER BY w DESC, a1, a2 ROWS UNBOUNDED PRECEDING)),
theta AS (SELECT arg_max(t, k) AS t FROM r WHERE w > t)
SELECT a1, a2, round(greatest(w - theta.t, 0), 3) AS w FROM raw, theta""")
def _(spark, sf):
    raw, n = _raw(spark, sf)
    return _grid_rows(spark, weights.consistent(raw, n, "simplex"), 3)


@query("clip_scale_consistency", f"""
WITH {LABELS} {SKETCH} {_LOO} {_UNION} {_RAW}, t AS (SELECT sum(greatest(w, 0)) AS s FROM raw)
SELECT a1, a2, round(greatest(w, 0) * ((SELECT count(*) FROM labels) / s), 3) AS w FROM raw, t""")
def _(spark, sf):
    raw, n = _raw(spark, sf)
    return _grid_rows(spark, weights.consistent(raw, n, "clip_scale"), 3)


@query("cluster_sizes_sketch", f"""
WITH {LABELS} {SKETCH} SELECT party, a, round(count(*) / sum(pow({1 + GAMMA!r}, -greatest(alpha, {_FLOOR}))) * {bias(GAMMA)!r} - {_NP}, 4) AS n FROM long GROUP BY party, a""")
def _(spark, sf):
    found = [weights.size_estimates(np.maximum(t, _FLOOR), _NP, GAMMA) for t in party_sketches(spark, sf)]
    return _values(spark, [(p, a, round(float(v), 4)) for p, n in enumerate(found, start=1) for a, v in enumerate(n)], "party int, a int, n double")


@query("refine_one_step_s3", f"""
WITH {LABELS}, n AS (SELECT count(*) AS n FROM labels),
p AS (SELECT a1, count(*) AS f FROM labels GROUP BY a1), q AS (SELECT a2, count(*) AS f FROM labels GROUP BY a2), r AS (SELECT a3, count(*) AS f FROM labels GROUP BY a3),
g AS (SELECT a1, a2, a3, n * (p.f / n) * (q.f / n) * (r.f / n) AS w FROM p, q, r, n),
t AS (SELECT a1, a2, count(*) AS want FROM labels GROUP BY a1, a2)
SELECT g.a1, g.a2, a3, round(w - (sum(w) OVER (PARTITION BY g.a1, g.a2) - coalesce(want, 0)) / count(*) OVER (PARTITION BY g.a1, g.a2), 4) AS w
FROM g LEFT JOIN t ON g.a1 = t.a1 AND g.a2 = t.a2""")
def _(spark, sf):
    return _refined(spark, sf, [(0, 1)], rounds=1, clip=False)


def _refined(spark, sf, pairs, **how):
    w = exact(spark, sf)
    sizes = [w.sum((1, 2)), w.sum((0, 2)), w.sum((0, 1))]
    tables = {p: weights.project(w, *p) for p in pairs}
    got = weights.refine(weights.product_grid(sizes, w.sum()), tables, w.sum(), np.random.default_rng(0), finalize="none", **how)
    rows = [(*map(int, i), round(float(got[i]), 4)) for i in np.ndindex(got.shape) if all(s[j] for s, j in zip(sizes, i, strict=True))]
    return _values(spark, rows, "a1 int, a2 int, a3 int, w double")


def _refine_sql(rounds: int) -> str:
    """So many rounds over the pairs in turn, negative cells cut in each."""
    pairs = [("a1", "a2"), ("a1", "a3"), ("a2", "a3")]
    parts = [f"""WITH {LABELS}, n AS (SELECT count(*) AS n FROM labels),
p AS (SELECT a1, count(*) AS f FROM labels GROUP BY a1), q AS (SELECT a2, count(*) AS f FROM labels GROUP BY a2), r AS (SELECT a3, count(*) AS f FROM labels GROUP BY a3),
g0 AS MATERIALIZED (SELECT a1, a2, a3, n * (p.f / n) * (q.f / n) * (r.f / n) AS w FROM p, q, r, n)"""]
    parts += [f"t{k} AS MATERIALIZED (SELECT {a}, {b}, count(*) AS want FROM labels GROUP BY {a}, {b})" for k, (a, b) in enumerate(pairs)]
    for t in range(rounds):
        a, b = pairs[t % 3]
        parts.append(f"""g{t + 1} AS MATERIALIZED (SELECT g.a1, g.a2, g.a3, greatest(w - (sum(w) OVER o - coalesce(want, 0)) / count(*) OVER o, 0) AS w
FROM g{t} g LEFT JOIN t{t % 3} t ON g.{a} = t.{a} AND g.{b} = t.{b} WINDOW o AS (PARTITION BY g.{a}, g.{b}))""")
    return ", ".join(parts) + f" SELECT a1, a2, a3, round(w, 4) AS w FROM g{rounds}"


@query("refine_rounds_s3", _refine_sql(50))
def _(spark, sf):
    return _refined(spark, sf, [(0, 1), (0, 2), (1, 2)], rounds=50, order="cyclic")


# ---- reports -----------------------------------------------------------------------------------------

EPS_LDP = 1.0
_KEEP = math.exp(EPS_LDP) / (math.exp(EPS_LDP) + 2)


def _grr_sql(c: str, tag: str) -> str:
    h = f"('0x' || substr(md5('{tag}o|' || id), 1, 15))::BIGINT"
    return f"CASE WHEN {U.format(f"'{tag}|' || id")} <= {_KEEP!r} THEN {c} ELSE ({c} + 1 + {h} % 2) % 3 END"


@query("grr_reports_md5", f"WITH {LABELS} SELECT id, CAST({_grr_sql('a1', 'r1')} AS INT) AS y FROM labels")
def _(spark, sf):
    return local_dp.grr(labels(spark, sf).select("id", F.col("a1").alias("a")), 3, EPS_LDP, "r1")


_P = local_dp.grr_matrix(3, EPS_LDP)
_INV = np.linalg.inv(_P)
_POST = (_P / _P.sum(axis=0, keepdims=True)).T


def _decode_sql(back: np.ndarray) -> str:
    table = ", ".join(f"({i}, {j}, {float(back[i, j])!r})" for i in range(3) for j in range(3))
    return f"""
WITH {LABELS}, y AS (SELECT {_grr_sql('a1', 'r1')} AS y1, {_grr_sql('a2', 'r2')} AS y2 FROM labels),
c AS (SELECT y1, y2, count(*) AS n FROM y GROUP BY y1, y2), b(a, y, v) AS (VALUES {table})
SELECT p.a AS a1, q.a AS a2, round(sum(n * p.v * q.v), 3) AS w FROM c JOIN b p ON p.y = y1 JOIN b q ON q.y = y2 GROUP BY p.a, q.a"""


def _decoded(spark, sf, decoder):
    df = labels(spark, sf)
    reports = [local_dp.grr(df.select("id", F.col(c).alias("a")), 3, EPS_LDP, t) for c, t in (("a1", "r1"), ("a2", "r2"))]
    w = local_dp.decode(local_dp.grr_counts(reports, 3), 3, EPS_LDP, decoder)
    return _values(spark, [(i, j, round(float(w[i, j]), 3)) for i in range(3) for j in range(3)], "a1 int, a2 int, w double")


@query("grr_debias_s2", _decode_sql(_INV))
def _(spark, sf):
    return _decoded(spark, sf, "unbiased")


@query("report_posterior_s2", _decode_sql(_POST))
def _(spark, sf):
    return _decoded(spark, sf, "posterior")


EPS_OLH = 2.0
_G = local_dp.buckets(EPS_OLH)
_KEEP_OLH = math.exp(EPS_OLH) / (math.exp(EPS_OLH) + _G - 1)


def _md5(text: str) -> str:
    return f"('0x' || substr(md5({text}), 1, 15))::BIGINT"


def _olh_sql(c: str, tag: str) -> str:
    """(id, seed, y) of one party's reports."""
    own = f"CAST({_md5(f"seed || '|' || {c}")} % {_G} AS INT)"
    other = _md5(f"'{tag}o|' || id")
    return f"""(SELECT id, seed, CAST(CASE WHEN {U.format(f"'{tag}|' || id")} <= {_KEEP_OLH!r} THEN {own} ELSE ({own} + 1 + {other} % {_G - 1}) % {_G} END AS INT) AS y
FROM (SELECT *, {_md5(f"'{tag}h|' || id")} AS seed FROM labels))"""


_HIT = f"CAST(CASE WHEN CAST({_md5("seed || '|' || l.a")} % {_G} AS INT) = y THEN 1 ELSE 0 END AS DOUBLE)"
_OLH_LABELS = "(SELECT unnest(range(3)) AS a)"


def olh_reports(spark, sf, names=("a1", "a2")) -> list[DataFrame]:
    return [local_dp.olh(f, 3, EPS_OLH, f"o{p}") for p, f in enumerate(label_frames(spark, sf, names), start=1)]


@query("olh_reports_md5", f"WITH {LABELS} SELECT id, seed, y FROM {_olh_sql('a1', 'o1')}")
def _(spark, sf):
    return olh_reports(spark, sf, ("a1",))[0]


@query("olh_support_counts", f"""
WITH {LABELS} SELECT CAST(l.a AS INT) AS a, sum({_HIT}) AS n FROM {_olh_sql('a1', 'o1')}, {_OLH_LABELS} l GROUP BY l.a""")
def _(spark, sf):
    n = local_dp.olh_counts(olh_reports(spark, sf, ("a1",))[0], 3, EPS_OLH)
    return _values(spark, [(a, float(v)) for a, v in enumerate(n)], "a int, n double")


_VEC = f"({_HIT} - {1 / _G!r}) / {_KEEP_OLH - 1 / _G!r}"


@query("olh_weights_s2", f"""
WITH {LABELS}, p AS (SELECT id, l.a, {_VEC} AS v FROM {_olh_sql('a1', 'o1')}, {_OLH_LABELS} l), q AS (SELECT id, l.a, {_VEC} AS v FROM {_olh_sql('a2', 'o2')}, {_OLH_LABELS} l)
SELECT CAST(p.a AS INT) AS a1, CAST(q.a AS INT) AS a2, round(sum(p.v * q.v), 3) AS w FROM p JOIN q ON p.id = q.id GROUP BY p.a, q.a""")
def _(spark, sf):
    return _grid_rows(spark, local_dp.olh_weights(olh_reports(spark, sf), 3, EPS_OLH), 3)


# ---- privacy and costs -------------------------------------------------------------------------------


@query("laplace_inverse_cdf", f"SELECT c_custkey AS id, round({_LAP.format(u=U.format("'lap|' || c_custkey"), s=2.0)}, 5) AS z FROM customer")
def _(spark, sf):
    u = C.md5_uniform(F.lit("lap"), "c_custkey")
    return load(spark, sf, "customer").select(F.col("c_custkey").alias("id"), F.round(C.laplace_from_uniform(u, 2.0), 5).alias("z"))


@query("budget_table", f"""
WITH {USERS} SELECT priority, n, s AS parties, e AS eps, round(0.02 * e, 9) AS eps0, round(0.98 * e / (2 * s), 9) AS eps2, round(1.0 / n / s, 12) AS delta2
FROM users, (VALUES (2), (4)) a(s), (VALUES (0.5), (1.0), (2.0), (4.0), (8.0)) b(e)""")
def _(spark, sf):
    rows = []
    for (p, n), s, e in itertools.product(users(spark, sf), (2, 4), (0.5, 1.0, 2.0, 4.0, 8.0)):
        b = split(e, 1 / n, s)
        rows.append((p, n, s, e, round(b.eps0, 9), round(b.eps2, 9), round(b.delta2, 12)))
    return _values(spark, rows, "priority int, n bigint, parties int, eps double, eps0 double, eps2 double, delta2 double")


@query("k_local_rule_table", f"""
WITH {USERS}, g AS (SELECT priority, n, s, e, k0, 0.649 * (n - CAST(n AS DOUBLE) / (k0 * k0)) / sqrt(4096) + 4 * 0.649 * 2 * (k0 - 1) * sqrt(ln(n)) / (0.98 * e / (2 * s)) AS sd
           FROM users, (VALUES (2), (4)) a(s), (VALUES (0.5), (1.0), (2.0), (4.0), (8.0)) b(e), (SELECT unnest(range(1, 30)) AS k0))
SELECT priority, s AS parties, e AS eps, CAST(greatest(min(k0) FILTER (2 * sd >= CAST(n AS DOUBLE) / (k0 * k0)), ceil(pow(5, 1.0 / s))) AS INT) AS k_local
FROM g GROUP BY priority, s, e""")
def _(spark, sf):
    rows = [(p, s, e, choose_k_local(n, 5, s, split(e, 1 / n, s).eps2, 1 / n, 4096))
            for (p, n), s, e in itertools.product(users(spark, sf), (2, 4), (0.5, 1.0, 2.0, 4.0, 8.0))]
    return _values(spark, rows, "priority int, parties int, eps double, k_local int")


@query("comm_bytes_table", f"""
WITH {USERS} SELECT priority, k AS k_local, m AS repeats, method, CAST(8 * CASE method WHEN 'sketch' THEN k * (4 + m) WHEN 'independence' THEN k * 5 ELSE k * 4 + n END AS BIGINT) AS bytes
FROM users, (VALUES (5), (8)) a(k), (VALUES (2048), (4096)) b(m), (VALUES ('sketch'), ('independence'), ('reports'), ('exact')) c(method)""")
def _(spark, sf):
    rows = [(p, k, m, x, bytes_per_party(x, k, 4, n, m))
            for (p, n), k, m, x in itertools.product(users(spark, sf), (5, 8), (2048, 4096), ("sketch", "independence", "reports", "exact"))]
    return _values(spark, rows, "priority int, k_local int, repeats int, method string, bytes bigint")


# ---- measures ----------------------------------------------------------------------------------------


@query("vmeasure_cube", f"""
WITH {LABELS}, n AS (SELECT count(*) AS n FROM labels), c AS (SELECT a1, a3, count(*) AS c FROM labels GROUP BY a1, a3),
h AS (SELECT -(SELECT sum(c / n * ln(c / n)) FROM c, n) AS j, -(SELECT sum(x / n * ln(x / n)) FROM (SELECT sum(c) AS x FROM c GROUP BY a1), n) AS y,
             -(SELECT sum(x / n * ln(x / n)) FROM (SELECT sum(c) AS x FROM c GROUP BY a3), n) AS f),
v AS (SELECT 1 - (j - f) / y AS h, 1 - (j - y) / f AS c FROM h)
SELECT round(h, 8) AS homogeneity, round(c, 8) AS completeness, round(2 * h * c / (h + c), 8) AS v FROM v""")
def _(spark, sf):
    h, c, v = measures.v_measure(labels(spark, sf), "a1", "a3")
    return _values(spark, [(round(h, 8), round(c, 8), round(v, 8))], "homogeneity double, completeness double, v double")


@query("silhouette_moments", f"""
WITH {_POINTS}, g AS (SELECT a, count(*) AS n, sum(x0) AS s0, sum(x1) AS s1, sum(x0 * x0 + x1 * x1) AS q FROM n GROUP BY a),
t AS (SELECT n.id, n.a, g.a AS b, (g.n * (x0 * x0 + x1 * x1) - 2 * (x0 * s0 + x1 * s1) + q) / (g.n - CASE WHEN g.a = n.a THEN 1 ELSE 0 END) AS m FROM n, g),
s AS (SELECT id, min(m) FILTER (a = b) AS i, min(m) FILTER (a <> b) AS o FROM t GROUP BY id)
SELECT round(avg((o - i) / greatest(o, i)), 6) AS silhouette FROM s""")
def _(spark, sf):
    return _values(spark, [(round(measures.silhouette(points(spark, sf), np.array(CENTERS)), 6),)], "silhouette double")


@query("relative_l1_error", f"""
WITH {LABELS}, n AS (SELECT count(*) AS n FROM labels), p AS (SELECT a1, count(*) AS f FROM labels GROUP BY a1), q AS (SELECT a2, count(*) AS f FROM labels GROUP BY a2),
e AS (SELECT a1, a2, n * (p.f / n) * (q.f / n) AS w FROM p, q, n), t AS (SELECT a1, a2, count(*) AS c FROM labels GROUP BY a1, a2)
SELECT round(sum(abs(w - coalesce(c, 0))) / (SELECT n FROM n), 8) AS error FROM e LEFT JOIN t USING (a1, a2)""")
def _(spark, sf):
    w = exact(spark, sf, ("a1", "a2"))
    got = weights.independence([w.sum(1), w.sum(0)], w.sum())
    return _values(spark, [(round(measures.relative_error(got, w, w.sum()), 8),)], "error double")


# ---- features by time --------------------------------------------------------------------------------


@query("asof_last_event", """
SELECT p.event_id, max(e.ts) AS last_ts, count(e.ts) AS earlier FROM events p LEFT JOIN events e
ON e.user_id = p.user_id AND e.ts < p.ts AND e.value > 100 WHERE p.value <= 100 GROUP BY p.event_id""")
def _(spark, sf):
    """The user's last large event before each small one: one window over both, no range join."""
    large = F.col("value") > 100
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    e = load(spark, sf, "events").select("event_id", "user_id", "ts", "value")
    # rows of one time see each other in a range frame, so large events count from the next microsecond on
    shifted = e.where(large).select(F.lit(None).cast("bigint").alias("event_id"), "user_id", (F.col("ts") + F.expr("INTERVAL 0.000001 SECOND")).alias("ts"), F.col("ts").alias("large_ts"))
    both = e.where(~large).select("event_id", "user_id", "ts", F.lit(None).cast("timestamp_ntz").alias("large_ts")).unionByName(shifted)
    out = both.withColumns({"last_ts": F.max("large_ts").over(w), "earlier": F.count("large_ts").over(w)})
    return out.where(F.col("event_id").isNotNull()).select("event_id", "last_ts", "earlier")


@query("trip_pairs", """
SELECT event_id, user_id, round(value, 4) AS value, CAST(floor(epoch(n)) - floor(epoch(ts)) AS BIGINT) AS gap
FROM (SELECT *, lead(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS n FROM events) WHERE n IS NOT NULL""")
def _(spark, sf):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = load(spark, sf, "events").withColumn("n", F.lead("ts").over(w)).where(F.col("n").isNotNull())
    gap = F.unix_timestamp(F.col("n").cast("timestamp")) - F.unix_timestamp(F.col("ts").cast("timestamp"))
    return e.select("event_id", "user_id", F.round("value", 4).alias("value"), gap.alias("gap"))


# ---- surrounding operators ---------------------------------------------------------------------------


@query("rollup_cluster_sizes", f"""
WITH {LABELS}, l AS (SELECT 1 AS party, a1 AS a FROM labels UNION ALL SELECT 2, a2 FROM labels UNION ALL SELECT 3, a3 FROM labels)
SELECT coalesce(party, -1) AS party, coalesce(a, -1) AS a, count(*) AS n FROM l GROUP BY ROLLUP (party, a)""")
def _(spark, sf):
    rolled = long_labels(spark, sf).rollup("party", "a").agg(F.count(F.lit(1)).alias("n"))
    return rolled.select(F.coalesce("party", F.lit(-1)).alias("party"), F.coalesce("a", F.lit(-1)).alias("a"), "n")


@query("pivot_contingency", f"""
WITH {LABELS} SELECT a1, count(*) FILTER (a3 = 0) AS few, count(*) FILTER (a3 = 1) AS some, count(*) FILTER (a3 = 2) AS many FROM labels GROUP BY a1""")
def _(spark, sf):
    wide = labels(spark, sf).groupBy("a1").pivot("a3", [0, 1, 2]).count().fillna(0)
    return wide.select("a1", F.col("0").alias("few"), F.col("1").alias("some"), F.col("2").alias("many"))


@query("top_cells_per_party", f"""
WITH {LABELS}, c AS (SELECT a1, a2, count(*) AS w FROM labels GROUP BY a1, a2)
SELECT a1, a2, w FROM (SELECT *, row_number() OVER (PARTITION BY a1 ORDER BY w DESC, a2) AS k FROM c) WHERE k <= 2""")
def _(spark, sf):
    c = labels(spark, sf).groupBy("a1", "a2").agg(F.count(F.lit(1)).alias("w"))
    k = F.row_number().over(Window.partitionBy("a1").orderBy(F.col("w").desc(), "a2"))
    return c.withColumn("k", k).where("k <= 2").drop("k")


@query("set_algebra_intersect", f"WITH {LABELS} SELECT id FROM labels WHERE a1 = 0 INTERSECT SELECT id FROM labels WHERE a2 = 1")
def _(spark, sf):
    df = labels(spark, sf)
    return df.where("a1 = 0").select("id").intersect(df.where("a2 = 1").select("id"))


@query("set_algebra_complement", f"WITH {LABELS} SELECT id FROM labels EXCEPT (SELECT id FROM labels WHERE a1 <> 0 UNION SELECT id FROM labels WHERE a2 <> 1)")
def _(spark, sf):
    """The same cell as all users but the union of the complements."""
    df = labels(spark, sf)
    away = df.where("a1 <> 0").select("id").union(df.where("a2 <> 1").select("id"))
    return df.select("id").exceptAll(away.distinct())


@query("histogram_band_join", """
WITH b AS (SELECT unnest(range(11)) AS k)
SELECT k AS bucket, count(c_custkey) AS n FROM b LEFT JOIN customer ON c_acctbal >= -1000 + k * 1000 AND c_acctbal < k * 1000 GROUP BY k""")
def _(spark, sf):
    """Public range buckets: the band is an equi-join on the bucket number, so nothing is compared pairwise."""
    n = load(spark, sf, "customer").groupBy(F.floor((F.col("c_acctbal") + 1000) / 1000).alias("bucket")).agg(F.count(F.lit(1)).alias("n"))
    return spark.range(11).withColumnRenamed("id", "bucket").join(n, "bucket", "left").select("bucket", F.coalesce("n", F.lit(0)).alias("n"))


@query("quantile_bins", """
SELECT tile, count(*) AS n, round(min(o_totalprice), 2) AS lo, round(max(o_totalprice), 2) AS hi
FROM (SELECT o_totalprice, ntile(8) OVER (ORDER BY o_totalprice, o_orderkey) AS tile FROM orders) GROUP BY tile""")
def _(spark, sf):
    """Equal-count bins by exact ranks, without a global window: a range-partitioned sort and the partitions' offsets."""
    rows = load(spark, sf, "orders").select("o_totalprice", "o_orderkey")
    part = rows.repartitionByRange("o_totalprice", "o_orderkey").withColumn("p", F.spark_partition_id())
    part = checkpoints.checkpointed(part)  # ranges are drawn from a sample: fixed here for both uses
    sizes = part.groupBy("p").agg(F.count(F.lit(1)).alias("size"))
    before = F.coalesce(F.sum("size").over(Window.orderBy("p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    offsets = sizes.select("p", before.alias("before"), F.sum("size").over(Window.partitionBy(F.lit(0))).alias("total"))
    rank = F.row_number().over(Window.partitionBy("p").orderBy("o_totalprice", "o_orderkey")) + F.col("before") - 1
    ranked = part.join(F.broadcast(offsets), "p").withColumn("rank", rank)  # a row for each partition
    wide, more = F.floor(F.col("total") / 8), F.col("total") % 8  # the first ``more`` bins have a row more
    tile = F.when(F.col("rank") < more * (wide + 1), F.floor(F.col("rank") / (wide + 1))).otherwise(F.floor((F.col("rank") - more) / wide))
    return ranked.withColumn("tile", tile + 1).groupBy("tile").agg(
        F.count(F.lit(1)).alias("n"), F.round(F.min("o_totalprice"), 2).alias("lo"), F.round(F.max("o_totalprice"), 2).alias("hi"))


@query("events_within_hours", """
SELECT p.event_id, count(e.event_id) AS n FROM events p JOIN events e
ON e.user_id = p.user_id AND e.ts > p.ts AND e.ts <= p.ts + INTERVAL 6 HOUR GROUP BY p.event_id""")
def _(spark, sf):
    """Interval join by user and 6-hour bucket: each event goes to two buckets, and the exact range is checked after."""
    size = 6 * 3_600
    e = load(spark, sf, "events").select("event_id", "user_id", "ts")
    bucket = F.floor(F.unix_timestamp(F.col("ts").cast("timestamp")) / size)
    left = e.select(F.col("event_id").alias("first"), "user_id", F.col("ts").alias("t"), F.explode(F.array(bucket, bucket + 1)).alias("b"))
    right = e.withColumn("b", bucket)
    near = (F.col("ts") > F.col("t")) & (F.col("ts") <= F.col("t") + F.expr("INTERVAL 6 HOURS"))
    return left.join(right, ["user_id", "b"]).where(near).groupBy(F.col("first").alias("event_id")).agg(F.count("event_id").alias("n")).select("event_id", "n")


@query("theta_intersection_check")
def _(spark, sf):
    """Built-in set sketches as a non-private cross-check of one intersection: estimate beside the exact count."""
    df = labels(spark, sf)
    a = df.where("a1 = 0").agg(F.expr("theta_sketch_agg(id)").alias("s"))
    b = df.where("a2 = 1").agg(F.expr("theta_sketch_agg(id)").alias("t"))
    exact = df.agg(F.count_if((F.col("a1") == 0) & (F.col("a2") == 1)).alias("exact"))
    both = a.join(F.broadcast(b)).join(F.broadcast(exact))
    return both.select(F.expr("theta_sketch_estimate(theta_intersection(s, t))").alias("estimate"), "exact")


# ---- whole runs --------------------------------------------------------------------------------------


for _name, _how in {
    "pipeline_pairwise_gauss": {"methods": ("pairwise",)},
    "pipeline_complement_gauss": {"methods": ("complement",)},
    "pipeline_independence_gauss": {"methods": ("independence",)},
    "pipeline_reports_gauss": {"methods": ("reports", "reports_refined")},
    "pipeline_nonprivate_gauss": {"methods": ("nonprivate",)},
    "central_gauss": {"methods": ("central", "central_private")},
    "ablation_private_weights": {"methods": ("pairwise",), "local": "nonprivate"},
    "ablation_private_centers": {"methods": ("pairwise",), "membership": "exact"},
    "local_noisy_lloyd_gauss": {"methods": ("pairwise",), "local": "noisy_lloyd"},
    "k_local_auto_gauss": {"methods": ("pairwise",), "k_local": "auto"},
}.items():
    QUERIES[_name] = lambda spark, sf, how=_how: X.runs(spark, sf, "gauss", 2, (4.0,), (0,), repeats=1024, **how)

_SEEDS, _MORE = (0,), {"repeats": 1024}
QUERIES |= {
    "x1_x2_gauss": lambda spark, sf: X.runs(spark, sf, "gauss", 4, (1.0, 8.0), _SEEDS, X.ALL, **_MORE),
    "x1_x2_trip": lambda spark, sf: X.runs(spark, sf, "trip", 2, (4.0,), _SEEDS, X.ALL, **_MORE),
    "x1_x2_loan": lambda spark, sf: X.runs(spark, sf, "loan", 2, (4.0,), _SEEDS, X.ALL, **_MORE),
    "x1_x2_indep": lambda spark, sf: X.runs(spark, sf, "indep", 2, (4.0,), _SEEDS, X.ALL, **_MORE),
    "x3_uneven": lambda spark, sf: X.x3_uneven(spark, sf, seeds=_SEEDS, **_MORE),
    "x4_parties": lambda spark, sf: X.x4_parties(spark, sf, eps=(2.0,), seeds=_SEEDS, **_MORE),
    "x5_weight_error": lambda spark, sf: X.x5_weight_error(spark, sf, eps=(1.0, 8.0), seeds=_SEEDS, **_MORE),
    "x6_ablation": lambda spark, sf: X.x6_ablation(spark, sf, eps=(4.0,), seeds=_SEEDS, **_MORE),
    "x7_local_clusters": lambda spark, sf: X.x7_local_clusters(spark, sf, k_locals=(2, 5, 8), eps=(1.0, 8.0), seeds=_SEEDS, **_MORE),
    "x8_costs": lambda spark, sf: X.x8_costs(spark, sf),
    "pipeline_nonprivate_cust": lambda spark, sf: X.runs(spark, sf, "cust", 4, (1.0,), _SEEDS, ("nonprivate",), k_local=3),
    "x9_nonprivate": lambda spark, sf: X.x9_nonprivate(spark, sf, parties=(2,), seeds=_SEEDS),
    "x10_silhouette": lambda spark, sf: X.x10_silhouette(spark, sf, ks=(2, 5, 8)),
    "x11_repeats": lambda spark, sf: X.x11_repeats(spark, sf, repeats=(256, 1024, 4096), seeds=_SEEDS),
    "other_workloads": lambda spark, sf: X.other_workloads(spark, sf),
}


# ---- streaming ---------------------------------------------------------------------------------------


def _streamed(spark: SparkSession, sf: str, name: str, make, mode: str) -> DataFrame:
    """Runs a streaming plan over a table's files to their end; what it has found goes to Parquet in the shared folder."""
    path = f"{sf}/{name}.parquet"
    schema = spark.read.parquet(path).schema
    source = spark.readStream.schema(schema).format("parquet").option("pathGlobFilter", f"{name}*.parquet").load(path if _is_dir(spark, path) else sf)
    place = f"{checkpoints.folder(spark)}/stream_{name}_{np.random.default_rng().integers(1 << 60):x}"
    # in complete mode each batch replaces the table; a repeated batch writes the same rows again
    run = make(source).writeStream.outputMode(mode).option("checkpointLocation", f"{place}/state")
    run = run.foreachBatch(lambda rows, _: rows.write.mode("overwrite").parquet(f"{place}/rows"))
    run.trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{place}/rows")


def _is_dir(spark: SparkSession, path: str) -> bool:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


@query("stream_cumulative_sketch", """
SELECT a, i, CAST(max(61 - length(bin(('0x' || substr(md5(user_id || '|' || i), 1, 15))::BIGINT))) AS INT) AS alpha
FROM (SELECT DISTINCT user_id, user_id % 3 AS a FROM events) CROSS JOIN (SELECT unnest(range(1, 9)) AS i) GROUP BY a, i""")
def _(spark, sf):
    def cumulative(events):
        return streams.cumulative(events.select(F.col("user_id").alias("id"), (F.col("user_id") % 3).alias("a")), 8)

    return _streamed(spark, sf, "events", cumulative, "complete").select("a", F.col("i").cast("bigint").alias("i"), "alpha")


@query("stream_tumbling_sketch", """
SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) AS start, a, i,
       CAST(max(61 - length(bin(('0x' || substr(md5(user_id || '|' || i), 1, 15))::BIGINT))) AS INT) AS alpha
FROM (SELECT ts, user_id, user_id % 3 AS a FROM events) CROSS JOIN (SELECT unnest(range(1, 5)) AS i) GROUP BY 1, a, i""")
def _(spark, sf):
    def tumbling(events):
        return streams.windowed(events.select("ts", F.col("user_id").alias("id"), (F.col("user_id") % 3).alias("a")), 4, "1 day")

    got = _streamed(spark, sf, "events", tumbling, "complete")
    return got.select(F.unix_timestamp("start").alias("start"), "a", F.col("i").cast("bigint").alias("i"), "alpha")


@query("stream_session_counts", """
WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER w < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS s FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
h AS (SELECT *, sum(s) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT user_id, CAST(epoch_us(min(ts)) AS BIGINT) AS start, count(*) AS n FROM h GROUP BY user_id, k""")
def _(spark, sf):
    def sessions(events):
        return streams.sessions(events, "user_id")

    got = _streamed(spark, sf, "events", sessions, "complete")
    return got.select("user_id", F.unix_micros("start").alias("start"), "n")


def flagship(spark: SparkSession, sf: str) -> DataFrame:
    """Private clustering of the customers over four parties: the final centers."""
    parts = build_views(workloads.customers(spark, sf), "id", workloads.CUST_GROUPS)
    got = pipeline.fit(parts, 3, 8.0, k_local=2, params=X.params(512, 0), seed=0)
    rows = [(k, [float(v) for v in c]) for k, c in enumerate(got.centers)]
    return spark.createDataFrame(rows, "k int, center array<double>")
