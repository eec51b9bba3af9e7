"""Document fingerprints: a homomorphic multiset hash of paragraphs, in DataFrame functions only.

A paragraph (a line of the text) is hashed to one wide vector, and a document's fingerprint is the sum of
its paragraphs' vectors, each part modulo a power of two. So the order of paragraphs doesn't matter, and
a paragraph is inserted or deleted by adding or subtracting its vector. A vector has two parts:

* four 32-bit words of keyed hashes of the whole paragraph: equal sums mean equal paragraph multisets;
* 64 counters: a paragraph's vector is the sum of the sign vectors of its windows of three words, each
  counter telling for how many windows one hash bit is set, besides the number of windows. Sums of sign
  vectors keep inner products, hence ``likeness``: 2<u,v> / (|u|^2 + |v|^2), cut to 0..1, which estimates
  the share of windows that two documents have in common. A paragraph without spaces to speak of (LONG
  characters a word and more) has windows of eight characters instead.

Counters are added two to a 64-bit column (32 bits each; up to 2^31 windows), with map-side combining per document. ``insert`` and
``delete`` change stored vectors by those of paragraphs, without the documents' texts.

Next document: rows are cut into ranges of doc_id of about RANGE_ROWS rows, whose bounds are quantiles of the
ids; an id that many rows share is a range of its own, cut further by a hash of the text. Each range is
sorted on its own, and only the ranges' first rows are ordered globally.

Defined results: a null text counts as empty; a null doc_id sorts after all others; repeated rows get a
row each, in the order (doc_id descending, hash of text, text); a single document is its own next; an empty table
gives no rows; further columns, whatever their names, are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fedgrid.llm.common import checkpointed, table

WIDTH, COLUMNS = 3, 32
#: Characters a word from which a paragraph has no words, and its windows' characters then.
LONG, CHARACTERS = 40, 8
#: Rows aimed at in a range of doc_id, and the most ranges whatever the size of the table.
RANGE_ROWS, MAX_RANGES = 1500, 100_000
_PAIR = (1 << 32) | 1
_LOW = (1 << 32) - 1
_WORDS = ["w0", "w1", "w2", "w3"]
_SUMS = [f"c{b}" for b in range(COLUMNS)]


def _windows(text: Column) -> Column:
    """Hashes of the word windows of all paragraphs; a shorter paragraph is one window."""

    def of(w: Column, width: int) -> Column:
        places = F.sequence(F.lit(0), F.greatest(F.size(w) - width, F.lit(0)))
        return F.transform(places, lambda i: F.xxhash64(*[F.get(w, i + k) for k in range(width)]))

    def parts(p: Column) -> Column:
        dense = F.length(p) > LONG * F.size(F.split(p, " "))
        return F.struct(dense.alias("dense"), F.split(p, F.when(dense, "").otherwise(" ")).alias("parts"))

    # the parts are a variable of the second function: as an expression they would be split again for every window
    split = F.transform(F.split(text, "\n"), parts)
    return F.flatten(F.transform(split, lambda s: F.when(s["dense"], of(s["parts"], CHARACTERS)).otherwise(of(s["parts"], WIDTH))))


def _exact(text: Column) -> Column:
    """Four sums, modulo 2^32, of the halves of two keyed hashes of each paragraph."""
    half = F.lit((1 << 32) - 1)

    def add(acc: Column, p: Column) -> Column:
        a, b = F.xxhash64(F.lit(1), p), F.xxhash64(F.lit(2), p)
        parts = [a.bitwiseAND(half), F.shiftrightunsigned(a, 32), b.bitwiseAND(half), F.shiftrightunsigned(b, 32)]
        return F.struct(*[((acc[w] + x).bitwiseAND(half)).alias(w) for w, x in zip(_WORDS, parts, strict=True)])

    zero = F.struct(*[F.lit(0).cast("bigint").alias(w) for w in _WORDS])
    return F.aggregate(F.split(text, "\n"), zero, add)


def vectors(rows: DataFrame, keys: list[str], text: str = "text", carried: tuple[str, ...] = ()) -> DataFrame:
    """The fingerprint vector of each row: ``keys`` (unique to the row), ``carried``, windows, words, counters.

    Keys and carried columns are integers, so that the aggregate stays a hash aggregate.
    """
    # everything that reads the text is computed below the explode, once per row; the outer form keeps the
    # optimizer from making the hashes twice (there is always one at least)
    read = rows.select(*keys, *carried, _exact(F.col(text)).alias("exact"), _windows(F.col(text)).alias("hashes"))
    read = read.select(*keys, *carried, *[F.col(f"exact.{w}").alias(w) for w in _WORDS], "hashes")
    exploded = read.select(*keys, *carried, *_WORDS, F.explode_outer("hashes").alias("h"))
    sums = [F.sum(F.shiftright("h", b).bitwiseAND(F.lit(_PAIR))).alias(f"c{b}") for b in range(COLUMNS)]
    firsts = [F.first(c).alias(c) for c in (*carried, *_WORDS)]
    return exploded.groupBy(*keys).agg(*firsts, F.count(F.lit(1)).alias("windows"), *sums)


def _changed(stored: DataFrame, paragraphs: DataFrame, key: str, text: str, sign: int) -> DataFrame:
    rows = paragraphs.select(F.col(key).alias("__key"), F.xxhash64(key, text, F.monotonically_increasing_id()).alias("__row"), F.coalesce(text, F.lit("")).alias("__text"))
    parts = ("windows", *_WORDS, *_SUMS)
    delta = vectors(rows, ["__key", "__row"], "__text").groupBy("__key").agg(*[F.sum(c).alias(f"__{c}") for c in parts])
    joined = stored.join(delta, F.col(key) == F.col("__key"), "left")
    new = {c: F.col(c) + sign * F.coalesce(f"__{c}", F.lit(0)) for c in parts}
    new |= {c: new[c].bitwiseAND(F.lit((1 << 32) - 1)) for c in _WORDS}
    return joined.select(*[new[c].alias(c) if c in new else F.col(c) for c in stored.columns])


def insert(stored: DataFrame, paragraphs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """``stored`` vectors (columns of ``vectors``, one row a key) with the paragraphs' vectors added: the fingerprint of
    the document with these lines more, wherever they stand. Keys without paragraphs stay as they are."""
    return _changed(stored, paragraphs, key, text, 1)


def delete(stored: DataFrame, paragraphs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """The same with the paragraphs' vectors taken off; the paragraphs must be in the documents."""
    return _changed(stored, paragraphs, key, text, -1)


def _hex(c: Column, digits: int) -> Column:
    return F.lower(F.lpad(F.hex(c), digits, "0"))


def fingerprint(prefix: str = "") -> Column:
    """The vector's columns as text: exact words, number of windows, counters."""
    words = [_hex(F.col(prefix + w), 8) for w in _WORDS]
    sums = [_hex(F.col(prefix + c), 16) for c in _SUMS]
    return F.concat(*words, F.lit(":"), _hex(F.col(prefix + "windows"), 8), F.lit(":"), *sums)


def signs(prefix: str = "") -> Column:
    """The sign-vector sums as an array of doubles."""
    n = F.col(prefix + "windows")
    parts = []
    for c in _SUMS:
        s = F.col(prefix + c)
        parts += [(2 * s.bitwiseAND(F.lit(_LOW)) - n).cast("double")]
        parts += [(2 * F.shiftrightunsigned(s, 32) - n).cast("double")]
    return F.array(*parts)


def likeness(a: Column, b: Column) -> Column:
    """2<a,b> / (|a|^2 + |b|^2) of two arrays of sign sums, within 0 and 1; two zero vectors are alike."""

    def dot(x: Column, y: Column) -> Column:
        return F.aggregate(F.zip_with(x, y, lambda p, q: p * q), F.lit(0.0), lambda s, v: s + v)

    norm = dot(a, a) + dot(b, b)
    return F.when(norm == 0, 1.0).otherwise(F.least(F.greatest(2 * dot(a, b) / norm, F.lit(0.0)), F.lit(1.0)))


def range_bounds(ids: DataFrame) -> tuple[list[int], list[int]]:
    """(lowest id of each range, ids that are a range of their own), from quantiles of ``doc_id``.

    Bounded: MAX_RANGES quantiles, and ids that hold a ten-thousandth of all rows and ten ranges' rows at least.
    """
    rows = ids.where(F.col("doc_id").isNotNull())
    n = rows.count()
    ranges = max(1, min(MAX_RANGES, n // RANGE_ROWS))
    if ranges == 1:
        return [], []
    shares = _constant([k / ranges for k in range(1, ranges)], "double")  # the engine takes a constant alone for them
    quantiles = rows.agg(F.percentile_approx("doc_id", shares, F.lit(max(10_000, 10 * ranges)))).first()[0]
    least = max(10 * RANGE_ROWS, n // 10_000)
    hot = [r["doc_id"] for r in rows.groupBy("doc_id").count().where(F.col("count") >= least).collect()]  # 10,000 at most
    return sorted({*quantiles, *hot, *(h + 1 for h in hot if h < (1 << 63) - 1)}), hot


def _constant(values: list, of: str = "bigint") -> Column:
    """An array that the optimizer folds to one literal, however long."""
    return F.split(F.lit(",".join(map(str, values))), ",").cast(f"array<{of}>")


def _range(bounds: list[int]) -> Column:
    """How many bounds are at or below doc_id, found in two steps of about the root of their number."""
    if not bounds:
        return F.lit(0)
    step = math.isqrt(len(bounds) - 1) + 1
    steps = F.size(F.filter(_constant(bounds[::step]), lambda b: b <= F.col("doc_id")))
    part = F.slice(_constant(bounds), F.greatest((steps - 1) * step, F.lit(0)) + 1, F.lit(step))
    return F.when(steps == 0, 0).otherwise((steps - 1) * step + F.size(F.filter(part, lambda b: b <= F.col("doc_id"))))


#: Ranges that one doc_id's rows are cut into by the hash of their texts, and bits for their number.
_CUTS, _CUT_BITS = 4096, 12


def with_next(docs: DataFrame) -> DataFrame:
    """(rng, rn) as a row's key, doc_id, text, the next row's key (next_rng, next_rn) and ``next_text``.

    Next: the following row by doc_id descending (then hash of text, text); the first row after the last.
    """
    rows = docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    bounds, hot = range_bounds(rows.select("doc_id"))
    # rows without an id are cut by hash too; ranges count downwards, as the order does
    cut = F.col("doc_id").isin(hot) if hot else F.lit(False)
    hashed = F.xxhash64("text")
    sub = F.when(F.col("doc_id").isNull() | cut, F.shiftright(hashed, 64 - _CUT_BITS) + _CUTS // 2).otherwise(0)
    place = F.when(F.col("doc_id").isNull(), len(bounds) + 1).otherwise(len(bounds) - _range(bounds)).cast("bigint")
    rows = rows.withColumn("h", hashed).withColumn("rng", place * _CUTS + sub)

    order = Window.partitionBy("rng").orderBy(F.col("doc_id").desc_nulls_last(), "h", "text")
    sorted_rows = rows.select(
        "*",
        F.row_number().over(order).alias("rn"),
        F.lead("text").over(order).alias("lead_text"),
        F.lead(F.lit(1)).over(order).isNull().alias("last"),
    )
    # the first row of each range: MAX_RANGES of them, and _CUTS more for each hot id, so their keys meet in one task
    first = F.struct(F.bitwise_not("doc_id").alias("d"), "h")  # least: the largest id
    heads = rows.groupBy("rng").agg(F.min(first).alias("head"))
    by_range = Window.orderBy("rng")
    start = F.first("rng").over(by_range.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing))
    after = heads.select("rng", F.coalesce(F.lead("rng").over(by_range), start).alias("next_rng"))
    texts = rows.withColumn("own", first).join(F.broadcast(heads.withColumnRenamed("rng", "r")), F.col("rng") == F.col("r"))
    texts = texts.where(F.col("own").eqNullSafe(F.col("head"))).groupBy("rng").agg(F.min("text").alias("head_text"))
    ends = after.join(texts.withColumnRenamed("rng", "next_rng"), "next_rng").select(
        "rng", F.col("next_rng").alias("end_rng"), "head_text"
    )
    joined = sorted_rows.join(ends, "rng", "left")
    return joined.select(
        "rng",
        "rn",
        "doc_id",
        "text",
        F.when(F.col("last"), F.col("end_rng")).otherwise(F.col("rng")).alias("next_rng"),
        F.when(F.col("last"), 1).otherwise(F.col("rn") + 1).alias("next_rn"),
        F.when(F.col("last"), F.col("head_text")).otherwise(F.col("lead_text")).alias("next_text"),
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = with_next(table(spark, sf_dir, "documents"))
    n = F.length("text")
    tail = F.floor(n / 3).cast("int")
    edited = F.concat(F.substring("text", F.lit(1), n - tail), F.substring("next_text", F.lit(1), tail))
    rows = rows.select("rng", "rn", "doc_id", "next_rng", "next_rn", n.cast("bigint").alias("n"), "text", edited.alias("e"))
    both = rows.select(
        *["rng", "rn", "doc_id", "next_rng", "next_rn", "n"],
        F.inline(
            F.array(
                F.struct(F.lit(0).alias("side"), F.col("text").alias("text")),
                F.struct(F.lit(1).alias("side"), F.col("e").alias("text")),
            )
        ),
    )
    # the digest goes along as integers of 13 hex digits (52 bits)
    digest = F.sha2(F.col("text").cast("binary"), 256)
    parts = {f"s{k}": F.conv(F.substring("sha", 13 * k + 1, 13), 16, 10).cast("bigint") for k in range(5)}
    both = both.withColumn("sha", F.when(F.col("side") == 1, digest)).withColumns(parts)
    made = vectors(both, ["rng", "rn", "side"], carried=("doc_id", "next_rng", "next_rn", "n", *parts))
    made = made.withColumn("sha", F.concat(*[_hex(F.col(c), 13 if c != "s4" else 12) for c in parts]))
    vector = F.struct("windows", *_WORDS, *_SUMS)
    kept = ["rng", "rn", "side", "doc_id", "next_rng", "next_rn", "n", "sha"]
    made = checkpointed(made.select(*kept, vector.alias("own")))
    changed = made.where("side = 1").select("rng", "rn", F.col("sha").alias("edited_sha256"), F.col("own").alias("changed"))
    own = made.where("side = 0").drop("sha", "side")
    after = own.select(F.col("rng").alias("next_rng"), F.col("rn").alias("next_rn"), F.col("own").alias("after"))
    out = own.join(changed, ["rng", "rn"]).join(after, ["next_rng", "next_rn"])
    return out.select(
        "doc_id",
        F.col("n").alias("n_chars"),
        "edited_sha256",
        fingerprint("own.").alias("fingerprint"),
        fingerprint("changed.").alias("edited_fingerprint"),
        F.round(likeness(signs("own."), signs("changed.")), 6).alias("near_edited"),
        F.round(likeness(signs("own."), signs("after.")), 6).alias("near_next"),
    )
