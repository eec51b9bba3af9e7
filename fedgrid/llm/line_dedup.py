"""Line dedup by site-relative frequency, in DataFrame functions only.

A line is boilerplate of a host when the share of the host's pages that contain it exceeds a ratio (and
at least ``least`` pages contain it). Lines are compared by a 64-bit hash of their text without outer
spaces; blank lines are neither counted nor dropped.

Shape of the plan: each page sends its distinct line hashes once, counted per (host, line) with map-side
combining; host totals meet these counts on (host, salt), so that a host with a third of all pages is
dealt over many tasks. By definition a host has at most (mean distinct lines a page / ratio) boilerplate
lines, so they go back to the pages as one array per host: broadcast when their counted number is within
``BROADCAST_LINES``, else by a join on (host, salt).

Defined results: null hosts form one host together with the empty name; a null text stays null and has no
lines; repeated rows are pages of their own; a page may end up empty but is never dropped; an empty table
gives no rows; further columns, whatever their names, are kept by ``drop_lines`` (but for those called n_lines and
n_dropped, which it makes) and by the stage, ignored by the query.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fedgrid.llm.common import checkpointed, shielded, table

#: Boilerplate lines (16 bytes each) up to which their arrays are broadcast.
BROADCAST_LINES = 500_000
SALTS = 64


def _lines(text: Column) -> Column:
    return F.split(text, "\n")


def _key(line: Column) -> Column:
    return F.xxhash64(F.trim(line))


def boilerplate(pages: DataFrame, host: str, text: str, ratio: float, least: int) -> DataFrame:
    """(host, line hash) of the lines on more than ``ratio`` of a host's pages, and on ``least`` at least."""
    named = pages.select(F.coalesce(F.col(host), F.lit("")).alias("host"), F.col(text).alias("text"))
    hashes = F.transform(F.filter(_lines(F.col("text")), lambda x: F.trim(x) != ""), _key)
    counts = (
        named.select("host", F.array_distinct(hashes).alias("lines"))
        .select("host", F.explode_outer("lines").alias("line"))
        .where(F.col("line").isNotNull())
        .groupBy("host", "line")
        .agg(F.count(F.lit(1)).alias("pages"))
        .where(F.col("pages") >= least)
        .withColumn("salt", F.pmod(F.col("line"), F.lit(SALTS)).cast("int"))
    )
    totals = named.groupBy("host").agg(F.count(F.lit(1)).alias("total"))
    totals = totals.withColumn("salt", F.explode(F.array(*map(F.lit, range(SALTS)))))
    found = counts.join(totals, ["host", "salt"])
    return found.where(F.col("pages") > F.lit(float(ratio)) * F.col("total")).select("host", "line")


@shielded
def drop_lines(
    pages: DataFrame, host: str = "source", text: str = "text", ratio: float = 0.05, least: int = 3
) -> DataFrame:
    """The pages with ``text`` freed of boilerplate lines, plus ``n_lines`` and ``n_dropped``."""
    found = checkpointed(boilerplate(pages, host, text, ratio, least))
    few = found.count() <= BROADCAST_LINES
    arrays = found.groupBy("host").agg(F.collect_list("line").alias("__drop")).withColumnRenamed("host", "__host")
    keyed = pages.withColumn("__host", F.coalesce(F.col(host), F.lit("")))
    if few:
        joined = keyed.join(F.broadcast(arrays), "__host", "left")
    else:
        salted = arrays.withColumn("__salt", F.explode(F.array(*map(F.lit, range(SALTS)))))
        keyed = keyed.withColumn("__salt", F.pmod(F.xxhash64(F.col(text)), F.lit(SALTS)).cast("int"))
        joined = keyed.join(salted, ["__host", "__salt"], "left").drop("__salt")
    joined = joined.withColumn("__lines", _lines(F.col(text)))
    # the page's own boilerplate first, by one hash set, so that a line is only held against these few
    own = F.array_intersect(F.transform("__lines", _key), "__drop")
    joined = joined.withColumn("__drop", F.when(F.col("__drop").isNotNull(), own))
    kept = F.filter("__lines", lambda x: (F.trim(x) == "") | ~F.array_contains(F.col("__drop"), _key(x)))
    none = F.col("__drop").isNull() | (F.size("__drop") == 0)
    joined = joined.withColumn("__kept", F.when(none, F.col("__lines")).otherwise(kept))
    lines = F.coalesce(F.size("__lines"), F.lit(0))
    cleaned = F.when(F.col(text).isNotNull(), F.concat_ws("\n", "__kept"))
    names = [c for c in pages.columns if c.lower() not in ("n_lines", "n_dropped")]
    return joined.select(
        *[cleaned.alias(c) if c == text else F.col(c) for c in names],
        lines.alias("n_lines"),
        (lines - F.coalesce(F.size("__kept"), F.lit(0))).alias("n_dropped"),
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "documents").select("doc_id", "source", "text")
    return drop_lines(pages).select(
        "doc_id",
        F.col("n_lines").cast("bigint").alias("n_lines"),
        F.col("n_dropped").cast("bigint").alias("n_dropped"),
        "text",
    )


@shielded
def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without their sources' boilerplate lines; n_chars follows the new text."""
    found = docs.select(F.struct(*docs.columns).alias("doc"), "source", "text")  # columns that drop_lines makes stay
    cleaned = drop_lines(found)
    new = {"text": F.col("text"), "n_chars": F.length("text").cast("bigint")}
    return cleaned.select(*[new.get(c, F.col(f"doc.{c}")).alias(c) for c in docs.columns])


SQL = """
WITH pages AS (
  SELECT doc_id, coalesce(source, '') AS host, text, string_split(text, chr(10)) AS lines FROM documents
), counts AS (
  SELECT host, line, count(*) AS pages FROM (
    SELECT host, unnest(list_distinct(list_filter(list_transform(lines, lambda x: trim(x)), lambda x: x <> '')))
             AS line FROM pages) GROUP BY host, line
), totals AS (SELECT host, count(*) AS total FROM pages GROUP BY host
), drops AS (
  SELECT host, list(line) AS dropped FROM counts JOIN totals USING (host)
  WHERE pages >= 3 AND pages > CAST(0.05 AS DOUBLE) * total GROUP BY host
), kept AS (
  SELECT doc_id, text, lines,
         list_filter(lines, lambda x: trim(x) = '' OR NOT list_contains(coalesce(dropped, []), trim(x))) AS rest
  FROM pages LEFT JOIN drops USING (host)
)
SELECT doc_id, CAST(coalesce(len(lines), 0) AS BIGINT) AS n_lines,
       CAST(coalesce(len(lines), 0) - coalesce(len(rest), 0) AS BIGINT) AS n_dropped,
       CASE WHEN text IS NOT NULL THEN coalesce(array_to_string(rest, chr(10)), '') END AS text
FROM kept
"""
