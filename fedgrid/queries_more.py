"""More driver queries with SQL: workloads as they are scaled, accounting and cost formulas, noisy releases by md5 noise,
the multiplicative fit, protocol choice, and a stream-to-stream join. They register beside those of ``queries``."""

from __future__ import annotations

import itertools
import math

import numpy as np
from pyspark.sql import functions as F

from fedgrid import checkpoints
from fedgrid.functions import columns as C
from fedgrid.operators import local_dp, views, weights
from fedgrid.plans import pipeline, workloads
from fedgrid.privacy import (
    HashedNoise,
    Ledger,
    approximation_factor,
    approximation_offset,
    best_order,
    cell_sigma,
    combine,
    floor_value,
    fm_sigma,
    operations,
    phantoms,
    rdp_to_dp,
    report_sigma,
    sketch_epsilon,
)
from fedgrid.queries import _LAP, _POINTS, CENTERS, LABELS, USERS, U, _grid_rows, _is_dir, _refined, _values, exact, points, query, users
from fedgrid.sources.tables import load
from fedgrid.streaming import sketches as streams

# ---- workloads ---------------------------------------------------------------------------------------


def _scaled(column: str, low: float, high: float) -> str:
    return f"round(-1.0 + (least(greatest(CAST({column} AS DOUBLE), {float(low)!r}), {float(high)!r}) - {float(low)!r}) * {2.0 / (high - low)!r}, 6)"


def _rounded(df, names):
    return df.select("id", *[F.round(n, 6).alias(n) for n in names])


_CENTERS3 = np.random.default_rng(0).uniform(-0.8, 0.8, (3, 2)).round(6)


def _mixture(j: int) -> str:
    center = f"CASE y WHEN 0 THEN {float(_CENTERS3[0, j])!r} WHEN 1 THEN {float(_CENTERS3[1, j])!r} ELSE {float(_CENTERS3[2, j])!r} END"
    normal = f"sqrt(-2 * ln({U.format(f"'u0_{j}|' || id")})) * cos(2 * pi() * {U.format(f"'v0_{j}|' || id")})"
    return f"round(least(greatest({center} + 0.1 * {normal}, -1.0), 1.0), 5) AS x{j + 1}"


@query("gaussian_mixture_rows", f"""
WITH c AS (SELECT c_custkey AS id FROM customer), y AS (SELECT id, CAST(floor({U.format("'c0|' || id")} * {3 - 1e-9!r}) AS INT) AS y FROM c)
SELECT id, y, {_mixture(0)}, {_mixture(1)} FROM y""")
def _(spark, sf):
    made = workloads.gaussian_mixture(spark, m=2, k=3, ids=load(spark, sf, "customer").select("c_custkey"))
    return made.select("id", "y", F.round("x1", 5).alias("x1"), F.round("x2", 5).alias("x2"))


@query("workload_indep", "SELECT vec_id AS id, " + ", ".join(f"{_scaled(f'embedding[{j + 1}]', -0.4, 0.4)} AS e{j}" for j in range(16)) + " FROM embeddings")
def _(spark, sf):
    return _rounded(*workloads.workload(spark, sf, "indep"))


_CONV = {"turns": "count(*)", "chars": "sum(coalesce(length(text), 0))", "user_chars": "sum(CASE WHEN role = 'user' THEN coalesce(length(text), 0) ELSE 0 END)",
         "reply_chars": "sum(CASE WHEN role = 'assistant' THEN coalesce(length(text), 0) ELSE 0 END)"}


@query("workload_conv", "SELECT conv_id AS id, " + ", ".join(f"{_scaled(f'({v})', *workloads.CONV[k])} AS {k}" for k, v in _CONV.items()) + " FROM conversations GROUP BY conv_id")
def _(spark, sf):
    return _rounded(*workloads.workload(spark, sf, "conv"))


_PAGE = {"n_html": "length(html)", "n_url": "length(url)", "n_tags": "length(html) - length(replace(html, '<', ''))", "depth": "len(string_split(url, '/')) - 3"}


@query("workload_page", "SELECT page_id AS id, " + ", ".join(f"{_scaled(f'coalesce({v}, 0)', *workloads.PAGE[k])} AS {k}" for k, v in _PAGE.items()) + " FROM pages")
def _(spark, sf):
    return _rounded(*workloads.workload(spark, sf, "page"))


_DOC = {"n_chars": "length(t)", "n_lines": "len(string_split(t, chr(10)))", "lang_code": "list_position(['de', 'en', 'es', 'fr'], lang) - 1",
        "n_digits": "length(regexp_replace(t, '[^0-9]', '', 'g'))", "n_upper": "length(regexp_replace(t, '[^A-Z]', '', 'g'))",
        "n_punct": "length(regexp_replace(t, '[^.,;:!?]', '', 'g'))"}


@query("workload_doc", "WITH d AS (SELECT doc_id AS id, coalesce(text, '') AS t, lang FROM documents WHERE doc_id IS NOT NULL) SELECT id, "
       + ", ".join(f"{_scaled(f'coalesce({v}, 0)', *workloads.DOC[k])} AS {k}" for k, v in _DOC.items()) + " FROM d")
def _(spark, sf):
    return _rounded(workloads.workload(spark, sf, "doc")[0], list(_DOC))


_EPOCH = "floor(epoch({}))"
_WEEK = f"({_EPOCH} - epoch(date_trunc('week', {{}})))"
_DAY = f"({_EPOCH} - epoch(date_trunc('day', {{}})))"
_TRIP = {"start_week": _WEEK.format("ts", "ts"), "start_day": _DAY.format("ts", "ts"), "value": "value", "end_week": _WEEK.format("n", "n"),
         "end_day": _DAY.format("n", "n"), "gap": f"({_EPOCH.format('n')} - {_EPOCH.format('ts')})", "mean_value": "mean_value"}


@query("workload_trip", """
WITH e AS (SELECT event_id AS id, ts, coalesce(value, 0) AS value, lead(ts) OVER w AS n, avg(value) OVER (w ROWS UNBOUNDED PRECEDING) AS mean_value
           FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id))
SELECT id, """ + ", ".join(f"{_scaled(v, *workloads.TRIP[k])} AS {k}" for k, v in _TRIP.items()) + " FROM e WHERE n IS NOT NULL")
def _(spark, sf):
    return _rounded(workloads.workload(spark, sf, "trip")[0], list(_TRIP))


# ---- accounting and formulas -------------------------------------------------------------------------

_CALIBRATION = [(e, m) for e in (0.06125, 0.245, 1.96) for m in (1024, 4096)]
_ROWS = ", ".join(f"({e!r}, {m})" for e, m in _CALIBRATION)


@query("sketch_calibration_table", f"""
WITH {USERS}, g AS (SELECT priority, CAST(eps2 AS DOUBLE) AS eps2, 1.0 / n AS delta2, repeats FROM users, (VALUES {_ROWS}) c(eps2, repeats)),
r AS (SELECT *, eps2 / (4 * sqrt(repeats * ln(1 / delta2))) AS published, pow(sqrt(ln(1 / delta2) + eps2) - sqrt(ln(1 / delta2)), 2) AS rho FROM g)
SELECT priority, eps2, round(delta2, 12) AS delta2, repeats, round(published, 9) AS published, round(sqrt(2 * rho / repeats), 9) AS zcdp,
       CAST(ceil(1 / (exp(published) - 1)) AS INT) AS phantoms, CAST(ceil(-ln(1 - exp(-published)) / {math.log1p(0.1)!r}) AS INT) AS least FROM r""")
def _(spark, sf):
    rows = []
    for (p, n), (e, m) in itertools.product(users(spark, sf), _CALIBRATION):
        row = sketch_epsilon(e, 1 / n, m)
        rows.append((p, e, round(1 / n, 12), m, round(row, 9), round(sketch_epsilon(e, 1 / n, m, "zcdp"), 9), phantoms(row), floor_value(row, 0.1)))
    return _values(spark, rows, "priority int, eps2 double, delta2 double, repeats int, published double, zcdp double, phantoms int, least int")


@query("renyi_table", f"""
WITH {USERS}, g AS (SELECT priority, CAST(eps2 AS DOUBLE) AS eps2, 1.0 / n AS delta, rows FROM users, (VALUES {_ROWS}) c(eps2, rows)),
r AS (SELECT *, rows * eps2 * eps2 / 2 AS rho FROM g), o AS (SELECT *, 1 + sqrt(ln(1 / delta) / rho) AS nu FROM r)
SELECT priority, eps2 AS eps_row, rows, round(delta, 12) AS delta, round(nu, 6) AS nu, round(rho * nu + ln(1 / delta) / (nu - 1), 4) AS eps,
       round(rho * 2 + ln(1 / delta), 4) AS eps_at_2 FROM o""")
def _(spark, sf):
    rows = []
    for (p, n), (e, m) in itertools.product(users(spark, sf), _CALIBRATION):
        order, eps = best_order(e, m, 1 / n)
        rows.append((p, e, m, round(1 / n, 12), round(order, 6), round(eps, 4), round(rdp_to_dp(2.0, m * e**2, 1 / n), 4)))
    return _values(spark, rows, "priority int, eps_row double, rows int, delta double, nu double, eps double, eps_at_2 double")


@query("ledger_table", """
WITH g AS (SELECT CAST(substr(o_orderpriority, 1, 1) AS INT) AS party, o_orderstatus, count(*) AS n FROM orders GROUP BY ALL),
p AS (SELECT party, min(n) AS least FROM g GROUP BY party),
r AS (SELECT party, 'count' AS phase, 'sequential' AS scope, 0.02 AS eps, 0.0 AS delta FROM p UNION ALL SELECT party, 'local centers', 'sequential', 0.5, 0.0 FROM p
      UNION ALL SELECT party, 'membership', 'parallel', 0.5, 1.0 / least FROM p)
SELECT party, phase, scope, round(CAST(eps AS DOUBLE), 9) AS eps, round(CAST(delta AS DOUBLE), 12) AS delta FROM r
UNION ALL SELECT -1, 'all', 'total', round(CAST(sum(eps) AS DOUBLE), 9), round(CAST(sum(delta) AS DOUBLE), 12) FROM r""")
def _(spark, sf):
    """A party for each order priority; its clusters are the orders' states, released with a delta of one over their orders."""
    party = F.substring("o_orderpriority", 1, 1).cast("int").alias("party")
    clusters: dict[int, list[int]] = {}
    for r in load(spark, sf, "orders").groupBy(party, "o_orderstatus").count().collect():
        clusters.setdefault(r["party"], []).append(r["count"])
    ledger = Ledger()
    for p, counts in clusters.items():
        ledger.charge(p, "count", 0.02)
        for _ in range(2):
            ledger.charge(p, "local centers", 0.25)
        ledger.parallel(p, "membership", [(0.5, 1 / n) for n in counts])  # disjoint clusters cost their largest
    parts = spark.createDataFrame(ledger.rows, Ledger.SCHEMA).groupBy("party", "phase", "scope").agg(F.sum("eps").alias("eps"), F.sum("delta").alias("delta"))
    total = spark.createDataFrame([(-1, "all", "total", *map(float, ledger.total()))], "party int, phase string, scope string, eps double, delta double")
    return parts.unionByName(total).withColumns({"eps": F.round("eps", 9), "delta": F.round("delta", 12)})


@query("key_agreement", """
WITH s AS (SELECT o_orderpriority AS party, min(md5(CAST(o_orderkey AS VARCHAR))) AS share FROM orders GROUP BY 1), j AS (SELECT string_agg(share, '|' ORDER BY party) AS seed FROM s)
SELECT i, CAST(('0x' || substr(sha256(encode(seed) || unhex(printf('%08x', i))), 1, 16))::UBIGINT AS VARCHAR) AS k FROM j, (SELECT unnest(range(8)) AS i)""")
def _(spark, sf):
    """Keys from a share of each party (the order priorities), which it hashes from its own orders: repeatable, so not secret."""
    digest = F.md5(F.col("o_orderkey").cast("string").cast("binary"))
    shares = load(spark, sf, "orders").groupBy("o_orderpriority").agg(F.min(digest).alias("share")).orderBy("o_orderpriority").collect()
    found = combine([r["share"].encode() for r in shares], 8, "concat").values
    return _values(spark, [(i, str(k)) for i, k in enumerate(found)], "i bigint, k string")


_SIGMA = [(k, s, e) for k in (3, 5) for s in (2, 4) for e in (0.1225, 0.98)]
_SIGMA_ROWS = f"g AS (SELECT priority, n, k, s, CAST(e AS DOUBLE) AS e FROM users, (VALUES {', '.join(map(str, _SIGMA))}) c(k, s, e))"


@query("sigma_table", f"""
WITH {USERS}, {_SIGMA_ROWS}
SELECT priority, n, k, s, e AS eps2, round(0.649 * (n - CAST(n AS DOUBLE) / (k * k)) / sqrt(4096) + 4 * 0.649 * s * (k - 1) * sqrt(ln(1 / 1e-5)) / e, 5) AS cell,
       round(0.649 * n / sqrt(4096), 9) AS sketch, round(sqrt(n / pow(e, 2 * s)), 4) AS report FROM g""")
def _(spark, sf):
    rows = [(p, n, k, s, e, round(cell_sigma(n, n / k**2, k, s, 4096, e, 1e-5), 5), round(fm_sigma(n, 4096), 9), round(report_sigma(n, e, s), 4))
            for (p, n), (k, s, e) in itertools.product(users(spark, sf), _SIGMA)]
    return _values(spark, rows, "priority int, n bigint, k int, s int, eps2 double, cell double, sketch double, report double")


@query("bounds_table", f"""
WITH {USERS}, {_SIGMA_ROWS}
SELECT priority, n, k, s, e AS eps2, round(2 * 1.5 + 4 * 1.25 + 4 * 1.25 * 1.5, 6) AS factor,
       round(1.0 * 64 * pow(k, 1.5 * s) / sqrt(0.1) * (n / sqrt(4096) + s * (k - 1) * sqrt(ln(1 / 1e-5)) / e) / 1e6, 4) AS millions,
       CAST(n * 4096 AS BIGINT) AS hashes, CAST(4096 * s * pow(k, s) AS BIGINT) AS server, CAST(n * s AS BIGINT) AS exact FROM g""")
def _(spark, sf):
    rows = []
    for (p, n), (k, s, e) in itertools.product(users(spark, sf), _SIGMA):
        offset = approximation_offset(n, 8, k, s, 4096, e, 1e-5)
        ops = [operations(m, n, s, k, 4096) for m in ("party_hashes", "server_sketch", "server_exact")]
        rows.append((p, n, k, s, e, round(approximation_factor(1.5, 1.25), 6), round(offset / 1e6, 4), *ops))
    return _values(spark, rows, "priority int, n bigint, k int, s int, eps2 double, factor double, millions double, hashes bigint, server bigint, exact bigint")


_DOMAINS = ("l_returnflag", "l_linestatus", "l_linenumber", "l_quantity")


@query("report_protocol_table", f"""
WITH b AS ({" UNION ALL ".join(f"SELECT '{c}' AS attribute, count(DISTINCT {c}) AS k FROM lineitem" for c in _DOMAINS)})
SELECT attribute, CAST(e AS DOUBLE) AS eps, CAST(k AS INT) AS k, CASE WHEN k < 3 * exp(e) + 2 THEN 'grr' ELSE 'olh' END AS protocol,
       CAST(greatest(2, round_even(exp(e), 0) + 1) AS INT) AS buckets FROM (VALUES (0.1), (0.5), (1.0), (2.0), (3.0)) a(e), b""")
def _(spark, sf):
    """The protocol for each attribute of the order lines by the number of its values (few: sets of them are collected)."""
    found = load(spark, sf, "lineitem").agg(*[F.size(F.collect_set(c)).alias(c) for c in _DOMAINS]).first()
    rows = [(c, e, found[c], local_dp.choose(e, found[c]), local_dp.buckets(e)) for e in (0.1, 0.5, 1.0, 2.0, 3.0) for c in _DOMAINS]
    return _values(spark, rows, "attribute string, eps double, k int, protocol string, buckets int")


# ---- noisy releases ----------------------------------------------------------------------------------


@query("noisy_count", f"SELECT round(greatest(count(*) + {_LAP.format(u=U.format("'n0|' || 0"), s=5.0)}, 1), 5) AS n FROM customer")
def _(spark, sf):
    v = views.PartyView(points(spark, sf), ("c_acctbal", "c_nationkey"))
    return _values(spark, [(round(pipeline.party_count(v, 0.2, HashedNoise("n0")), 5),)], "n double")


@query("private_range", f"""
WITH h AS (SELECT b, count(c_acctbal) FILTER (c_acctbal IS NOT NULL) AS n FROM (SELECT unnest(range(64)) AS b) LEFT JOIN customer
           ON least(greatest(floor((c_acctbal + 5000) / 312.5), 0), 63) = b GROUP BY b),
z AS (SELECT b, greatest(n + {_LAP.format(u=U.format("'pr|' || b"), s=2.0)}, 0) AS n FROM h), c AS (SELECT sum(n) OVER (ORDER BY b) AS run, sum(n) OVER () AS total FROM z)
SELECT -5000 + 312.5 * count(*) FILTER (run < 0.01 * total) AS low, -5000 + 312.5 * (count(*) FILTER (run < 0.99 * total) + 1) AS high FROM c""")
def _(spark, sf):
    low, high = C.private_range(load(spark, sf, "customer"), "c_acctbal", 0.5, -5000.0, 15_000.0, HashedNoise("pr"))
    return _values(spark, [(float(low), float(high))], "low double, high double")


# ---- server ------------------------------------------------------------------------------------------


@query("party_labels_fixed", f"WITH {_POINTS} SELECT id, a FROM n")
def _(spark, sf):
    return pipeline.party_labels(views.PartyView(points(spark, sf), ("c_acctbal", "c_nationkey")), np.array(CENTERS))


@query("server_center_k1", f"""
WITH {LABELS} SELECT round(avg(a1 * 0.5 - 0.5), 6) AS c0, round(avg(a2 * 0.25 + 0.1), 6) AS c1, round(avg(a3 * a3 * 0.125), 6) AS c2 FROM labels""")
def _(spark, sf):
    axes = [np.array([[a * 0.5 - 0.5] for a in range(3)]), np.array([[a * 0.25 + 0.1] for a in range(3)]), np.array([[a * a * 0.125] for a in range(3)])]
    c = pipeline.server_centers(weights.grid_points(axes), exact(spark, sf), 1)[0]
    return _values(spark, [tuple(round(float(v), 6) for v in c)], "c0 double, c1 double, c2 double")


def _fit_sql(rounds: int) -> str:
    pairs = [("a1", "a2"), ("a1", "a3"), ("a2", "a3")]
    parts = [f"""WITH {LABELS}, n AS (SELECT count(*) AS n FROM labels),
p AS (SELECT a1, count(*) AS f FROM labels GROUP BY a1), q AS (SELECT a2, count(*) AS f FROM labels GROUP BY a2), r AS (SELECT a3, count(*) AS f FROM labels GROUP BY a3),
g0 AS MATERIALIZED (SELECT a1, a2, a3, n * (p.f / n) * (q.f / n) * (r.f / n) AS w FROM p, q, r, n)"""]
    parts += [f"t{k} AS MATERIALIZED (SELECT {a}, {b}, count(*) AS want FROM labels GROUP BY {a}, {b})" for k, (a, b) in enumerate(pairs)]
    for t in range(rounds):
        a, b = pairs[t % 3]
        parts.append(f"""g{t + 1} AS MATERIALIZED (SELECT g.a1, g.a2, g.a3, greatest(w, 1e-9) * coalesce(want, 0) / sum(greatest(w, 1e-9)) OVER (PARTITION BY g.{a}, g.{b}) AS w
FROM g{t} g LEFT JOIN t{t % 3} t ON g.{a} = t.{a} AND g.{b} = t.{b})""")
    return ", ".join(parts) + f" SELECT a1, a2, a3, round(w, 4) AS w FROM g{rounds}"


@query("refine_multiplicative_s3", _fit_sql(12))
def _(spark, sf):
    return _refined(spark, sf, [(0, 1), (0, 2), (1, 2)], rounds=12, order="cyclic", update="multiplicative")


@query("independence_clipped_share", f"""
WITH {LABELS}, n AS (SELECT count(*) AS n FROM labels), p AS (SELECT a1, count(*) AS f FROM labels GROUP BY a1)
SELECT a1, round(f - (SELECT n FROM n) / 3.0, 4) AS above, round(greatest(f - (SELECT n FROM n) / 3.0, 0) * (SELECT n FROM n) /
 (SELECT sum(greatest(f - (SELECT n FROM n) / 3.0, 0)) FROM p), 4) AS w FROM p""")
def _(spark, sf):
    f = exact(spark, sf, ("a1",))
    raw = f - f.sum() / 3
    w = weights.consistent(raw, f.sum(), "clip_scale")
    return _values(spark, [(a, round(float(raw[a]), 4), round(float(w[a]), 4)) for a in range(3) if f[a]], "a1 int, above double, w double")


@query("pair_table_of_grid", f"WITH {LABELS} SELECT a1, a2, count(*) AS w FROM labels GROUP BY a1, a2")
def _(spark, sf):
    return _grid_rows(spark, weights.project(exact(spark, sf), 0, 1), None, ("a1", "a2")).where("w > 0")


# ---- streams -----------------------------------------------------------------------------------------


@query("stream_interval_join", """
SELECT o_orderkey, event_id FROM orders JOIN events ON user_id = o_custkey AND ts <= o_orderdate AND ts >= o_orderdate - INTERVAL 7 DAY""")
def _(spark, sf):
    """Orders with the events of the same customer in the week before, as a join of two streams."""

    def source(name):
        path = f"{sf}/{name}.parquet"
        reader = spark.readStream.schema(spark.read.parquet(path).schema).format("parquet")
        return reader.option("pathGlobFilter", f"{name}*.parquet").load(path if _is_dir(spark, path) else sf)

    orders = source("orders").select("o_orderkey", F.col("o_custkey").alias("o_user"), F.col("o_orderdate").alias("o_ts"))
    joined = streams.interval_join(orders, source("events").select("event_id", "user_id", "ts")).select("o_orderkey", "event_id")
    place = f"{checkpoints.folder(spark)}/stream_join_{np.random.default_rng().integers(1 << 60):x}"
    run = joined.writeStream.format("parquet").outputMode("append").option("checkpointLocation", f"{place}/state")
    run.trigger(availableNow=True).start(f"{place}/rows").awaitTermination()
    return spark.read.schema(joined.schema).parquet(f"{place}/rows")
