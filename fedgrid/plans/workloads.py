"""Stand-in workloads of the experiments on the given tables; each gives named columns and an id."""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fedgrid.functions.columns import TWO60, clip_upper, day_seconds, scale_to_range, week_seconds
from fedgrid.operators.packed import tasks
from fedgrid.sources.tables import load, props_k

DAY = 86_400.0

# Public ranges, wider than every scale of the tables.
RANGES = {
    "l_quantity": (1, 50), "l_extendedprice": (900, 105_000), "l_discount": (0, 0.10), "l_tax": (0, 0.08),
    "l_linenumber": (1, 7), "ship_day": (9_131, 11_687), "flag": (0, 2), "status": (0, 1), "net_price": (800, 115_000),
    "o_totalprice": (1_000, 500_000), "order_day": (9_131, 11_687), "priority": (1, 5), "c_acctbal": (-1_000, 10_000),
    "p_size": (1, 50), "p_retailprice": (900, 1_000), "s_acctbal": (-1_000, 10_000),
}
LOAN = list(RANGES)


def _days(c: str):
    return F.unix_timestamp(F.col(c).cast("timestamp")) / DAY


def loan_raw(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sixteen numeric attributes of the order lines with their orders, customers, parts and suppliers."""
    t = {n: load(spark, sf_dir, n) for n in ("lineitem", "orders", "customer", "part", "supplier")}
    wide = (
        t["lineitem"]
        .join(t["orders"], F.col("l_orderkey") == F.col("o_orderkey"))
        .join(t["customer"], F.col("o_custkey") == F.col("c_custkey"))
        .join(t["part"], F.col("l_partkey") == F.col("p_partkey"))
        .join(t["supplier"], F.col("l_suppkey") == F.col("s_suppkey"))
    )
    key = F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate")
    return wide.select(
        key.alias("id"), "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate",
        "l_quantity", "l_extendedprice", "l_discount", "l_tax",
        _days("l_shipdate").alias("ship_day"),
        F.when(F.col("l_returnflag") == "A", 0).when(F.col("l_returnflag") == "N", 1).otherwise(2).alias("flag"),
        F.when(F.col("l_linestatus") == "F", 0).otherwise(1).alias("status"),
        (F.col("l_extendedprice") * (1 - F.col("l_discount")) * (1 + F.col("l_tax"))).alias("net_price"),
        "o_totalprice", _days("o_orderdate").alias("order_day"),
        F.substring("o_orderpriority", 1, 1).cast("int").alias("priority"),
        "c_acctbal", "p_size", "p_retailprice", "s_acctbal",
    )


def loan(spark: SparkSession, sf_dir: str, clip: bool = True) -> DataFrame:
    """All attributes cut at their 95 % quantiles, then scaled."""
    raw = loan_raw(spark, sf_dir)
    raw = clip_upper(raw, LOAN) if clip else raw
    return scale_to_range(raw, RANGES).select("id", *LOAN)


CUST = {
    "c_acctbal": (-1_000, 10_000), "nation": (0, 24), "segment": (0, 4),
    "n_orders": (0, 40), "order_total": (0, 6e6), "order_mean": (0, 500_000), "last_order": (9_131, 11_687),
    "n_lines": (0, 120), "line_total": (0, 5e6), "mean_discount": (0, 0.1), "mean_quantity": (0, 50),
    "n_events": (0, 150), "event_total": (0, 15_000), "event_mean": (0, 600), "last_week_second": (0, 604_800),
}
CUST_GROUPS = [list(CUST)[:3], list(CUST)[3:7], list(CUST)[7:11], list(CUST)[11:]]


def customers_raw(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four parties' views of the customers: master data, orders, order lines, events."""
    c, o = load(spark, sf_dir, "customer"), load(spark, sf_dir, "orders")
    li, e = load(spark, sf_dir, "lineitem"), load(spark, sf_dir, "events")
    segments = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
    base = c.select(
        F.col("c_custkey").alias("id"), "c_acctbal", F.col("c_nationkey").alias("nation"),
        (F.array_position(F.array(*map(F.lit, segments)), F.col("c_mktsegment")) - 1).alias("segment"),
    )
    orders = o.groupBy(F.col("o_custkey").alias("id")).agg(
        F.count(F.lit(1)).alias("n_orders"), F.sum("o_totalprice").alias("order_total"),
        F.avg("o_totalprice").alias("order_mean"), F.max(_days("o_orderdate")).alias("last_order"),
    )
    lines = li.join(o, F.col("l_orderkey") == F.col("o_orderkey")).groupBy(F.col("o_custkey").alias("id")).agg(
        F.count(F.lit(1)).alias("n_lines"), F.sum("l_extendedprice").alias("line_total"),
        F.avg("l_discount").alias("mean_discount"), F.avg("l_quantity").alias("mean_quantity"),
    )
    events = e.groupBy(F.col("user_id").alias("id")).agg(
        F.count(F.lit(1)).alias("n_events"), F.sum("value").alias("event_total"), F.avg("value").alias("event_mean"),
        F.max_by(week_seconds("ts"), "ts").alias("last_week_second"),
    )
    wide = base.join(orders, "id", "left").join(lines, "id", "left").join(events, "id", "left")
    return wide.select("id", *[F.coalesce(F.col(n).cast("double"), F.lit(float(CUST[n][0]))).alias(n) for n in CUST])


def customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scale_to_range(customers_raw(spark, sf_dir), CUST)


TRIP = {
    "start_week": (0, 604_800), "start_day": (0, 86_400), "value": (0, 600), "props_k": (0, 100),
    "end_week": (0, 604_800), "end_day": (0, 86_400), "gap": (0, 30 * DAY), "mean_value": (0, 600),
}


def trips(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events with their user's next event: start and end attributes that correlate in pairs."""
    user = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = props_k(load(spark, sf_dir, "events")).withColumn("next_ts", F.lead("ts").over(user))
    e = e.withColumn("mean_value", F.avg("value").over(user.rowsBetween(Window.unboundedPreceding, 0)))
    rows = e.where(F.col("next_ts").isNotNull()).select(
        F.col("event_id").alias("id"), week_seconds("ts").alias("start_week"), day_seconds("ts").alias("start_day"),
        "value", "props_k", week_seconds("next_ts").alias("end_week"), day_seconds("next_ts").alias("end_day"),
        (_seconds("next_ts") - _seconds("ts")).alias("gap"), "mean_value",
    )
    return scale_to_range(rows.fillna(0.0), TRIP)


def _seconds(c: str):
    return F.unix_timestamp(F.col(c).cast("timestamp")).cast("double")


def independent(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nearly independent attributes: the first sixteen coordinates of the unit vectors, scaled by their spread."""
    e = load(spark, sf_dir, "embeddings")
    names = {f"e{j}": (-0.4, 0.4) for j in range(16)}
    rows = e.select(F.col("vec_id").alias("id"), *[F.get("embedding", F.lit(j)).cast("double").alias(f"e{j}") for j in range(16)])
    return scale_to_range(rows, names)


DOC = {
    "n_chars": (0, 12_000), "n_words": (0, 2_000), "n_lines": (0, 60), "lang_code": (0, 3),
    "n_digits": (0, 200), "n_upper": (0, 400), "n_punct": (0, 600), "n_distinct": (0, 800),
}


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    d = load(spark, sf_dir, "documents").where(F.col("doc_id").isNotNull())
    t = F.coalesce("text", F.lit(""))
    langs = F.array(*map(F.lit, ["de", "en", "es", "fr"]))
    rows = d.select(
        F.col("doc_id").alias("id"), F.length(t).alias("n_chars"), F.size(F.split(t, r"\s+")).alias("n_words"),
        F.size(F.split(t, "\n")).alias("n_lines"), (F.array_position(langs, F.col("lang")) - 1).alias("lang_code"),
        F.regexp_count(t, F.lit("[0-9]")).alias("n_digits"), F.regexp_count(t, F.lit("[A-Z]")).alias("n_upper"),
        F.regexp_count(t, F.lit("[.,;:!?]")).alias("n_punct"),
        F.size(F.array_distinct(F.split(F.lower(t), r"\s+"))).alias("n_distinct"),
    )
    return scale_to_range(rows.fillna(0), DOC)


PAGE = {"n_html": (0, 20_000), "n_url": (0, 200), "n_tags": (0, 400), "depth": (0, 8)}


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = load(spark, sf_dir, "pages")
    rows = p.select(
        F.col("page_id").alias("id"), F.length("html").alias("n_html"), F.length("url").alias("n_url"),
        F.regexp_count("html", F.lit("<")).alias("n_tags"), (F.size(F.split("url", "/")) - 3).alias("depth"),
    )
    return scale_to_range(rows.fillna(0), PAGE)


CONV = {"turns": (0, 12), "chars": (0, 8_000), "user_chars": (0, 4_000), "reply_chars": (0, 8_000)}


def conversations(spark: SparkSession, sf_dir: str) -> DataFrame:
    n = F.coalesce(F.length("text"), F.lit(0))
    rows = load(spark, sf_dir, "conversations").groupBy(F.col("conv_id").alias("id")).agg(
        F.count(F.lit(1)).alias("turns"), F.sum(n).alias("chars"),
        F.sum(F.when(F.col("role") == "user", n).otherwise(0)).alias("user_chars"),
        F.sum(F.when(F.col("role") == "assistant", n).otherwise(0)).alias("reply_chars"),
    )
    return scale_to_range(rows, CONV)


def _hashed(ids: DataFrame, texts: list[str]) -> DataFrame:
    """(id, h): ``md5_hash60`` of each text and the id, joined by a bar. One Python pass: the engine's ``conv`` of a
    digest's hex digits takes several times as long as the digest."""
    started = [t.encode() for t in texts]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        md5 = hashlib.md5
        for batch in batches:
            own = [b"" if v is None else b"|%d" % v for v in batch.column(0).to_pylist()]
            digests = b"".join([md5(t + v).digest()[:8] for v in own for t in started])
            h = (np.frombuffer(digests, ">u8") >> np.uint64(4)).astype(np.int64)
            cuts = pa.array(np.arange(0, len(h) + 1, len(started)), pa.int32())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(cuts, pa.array(h))], names=["id", "h"])

    return ids.mapInArrow(run, "id bigint, h array<bigint>")


def gaussian_mixture(
    spark: SparkSession, n: int = 20_000, m: int = 8, k: int = 5, sigma: float = 0.1, seed: int = 0, ids: DataFrame | None = None
) -> DataFrame:
    """(id, x1..xm, y): points around k uniform centers, cut to [-1, 1], with their component.

    Every number is a keyed hash of the id, so any engine or partitioning draws the same points.
    """
    centers = np.random.default_rng(seed).uniform(-0.8, 0.8, (k, m)).round(6)
    base = ids if ids is not None else spark.range(n)
    base = base.select(F.col(base.columns[0]).cast("bigint").alias("id"))
    hashed = _hashed(base, [f"c{seed}", *[f"{kind}{seed}_{j}" for j in range(m) for kind in "uv"]])

    def uniform(i: int):
        return (F.get("h", F.lit(i)) + 1) / F.lit(TWO60)

    rows = hashed.withColumn("y", F.floor(uniform(0) * F.lit(k - 1e-9)).cast("int"))
    columns = {}
    for j in range(m):
        u, v = uniform(1 + 2 * j), uniform(2 + 2 * j)
        normal = F.sqrt(-2 * F.ln(u)) * F.cos(2 * math.pi * v)
        center = F.get(F.array(*[F.lit(float(c)) for c in centers[:, j]]), F.col("y"))
        columns[f"x{j + 1}"] = F.least(F.greatest(center + sigma * normal, F.lit(-1.0)), F.lit(1.0))
    return rows.withColumns(columns).drop("h")


GAUSS = [f"x{j}" for j in range(1, 9)]
WORKLOADS = {
    "cust": (customers, [n for g in CUST_GROUPS for n in g]), "loan": (loan, LOAN), "trip": (trips, list(TRIP)),
    "indep": (independent, [f"e{j}" for j in range(16)]), "doc": (documents, list(DOC)), "page": (pages, list(PAGE)),
    "conv": (conversations, list(CONV)),
}


def workload(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, list[str]]:
    if name == "gauss":
        ids = load(spark, sf_dir, "orders").select("o_orderkey").repartition(tasks(spark), "o_orderkey")  # before the numbers are drawn
        return gaussian_mixture(spark, ids=ids), GAUSS
    make, names = WORKLOADS[name]
    return make(spark, sf_dir), names
