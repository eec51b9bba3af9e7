"""Benchmark decontamination by template canonicalisation, in DataFrame functions only.

Texts are brought to token templates: numbers, names (capitalised words) and units after numbers become
typed placeholders, all else is a lower-cased word. As a capital may also come from a sentence's start, each window
of WINDOW tokens has up to three readings: capitalised words as words, those in mid-sentence as names, all as names.
A fourth one, of the tokens' own values, is for item windows of fewer than LEAST_WORDS words beside the
placeholders. The windows of a document are hashed and joined with the hashed windows of the benchmark items. Windows that lie on one
diagonal (document place minus item place) are one alignment of the item; it is a leak when it holds at
least MATCHED windows (or all windows of a shorter item) and its slots are consistent: whatever stands in
a placeholder of the item must be replaced by the same document value wherever it recurs, so a question
asked again with other numbers is caught, but not a chance run of placeholders.

A name or number of several tokens ("Mary Ann", "1 000") may stand for one of another number: in a second form of
each text, runs of names and runs of numbers are folded to one token, and windows of that form (all names as slots)
make alignments of their own. Texts without a number or a name in mid-sentence have no second form.

The benchmark's windows are broadcast when their counted number is within BROADCAST_WINDOWS; beyond it the
join shuffles by hash, and frequent windows are split by the adaptive skew join. The corpus is read once for windows
of all sizes. Each document window is one row before the join and only hits live on, counted per alignment; slots are
read again from the texts of the few documents that hold an alignment.

Defined results: null texts and items have no tokens; items of fewer than WINDOW tokens match as one
window of their own length, those of fewer than 3 tokens only a document of the same tokens; repeated
rows of a document or item count once, texts that share a doc_id are looked at one by one; an empty table (of either)
gives no leaks; further columns, whatever their names, are kept by the stage.
"""

from __future__ import annotations

from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fedgrid.llm.common import checkpointed, shielded, table

WINDOW, MATCHED, LEAST_WORDS = 8, 6, 4
BROADCAST_WINDOWS = 2_000_000

# One control character per placeholder type, and the units that are recognised.
NUMBER, NAME, UNIT, POINT, INITIAL, JOINT = "\x01", "\x02", "\x03", "\x04", "\x05", "\x06"
UNITS = (
    "km|m|cm|mm|nm|mi|miles?|ft|feet|inch(?:es)?|kg|g|mg|t|tons?|lbs?|oz|l|ml|s|ms|min|minutes?|h|hours?|days?|"
    "weeks?|months?|years?|hz|khz|mhz|ghz|w|kw|mw|v|a|j|kj|pa|kpa|bar|mol|k|kb|mb|gb|tb|percent|dollars?|euros?|cents?"
)


def marked(text: Column) -> Column:
    """The text as words in lower case, slot values behind the character of their type, with a space between each two."""
    t = F.translate(text, NUMBER + NAME + UNIT + POINT + INITIAL + JOINT, "      ")
    t = F.regexp_replace(t, r"(?<=\d)[.,](?=\d)", POINT)
    t = F.regexp_replace(t, r"(?<=[\p{L}\p{N},;)] )\p{Lu}\p{Ll}+", NAME + "$0")
    t = F.regexp_replace(t, rf"(?<![\p{{L}}\p{{N}}{NAME}])\p{{Lu}}\p{{Ll}}+", INITIAL + "$0")
    t = F.regexp_replace(t, rf"(?<![\p{{L}}\p{{N}}{POINT}])(\d[\d{POINT}]*)", " " + NUMBER + "$1 ")
    t = F.regexp_replace(t, rf"(?i)(?<=\d )(\s?)({UNITS})(?![\p{{L}}\p{{N}}])", "$1" + UNIT + "$2")
    return F.lower(F.regexp_replace(t, r"[^\p{L}\p{N}\x01-\x05]+", " "))


def tokens(marked_text: Column) -> Column:
    return F.filter(F.split(marked_text, " "), lambda w: w != "")


def folded(marked_text: Column) -> Column:
    """The marked text with runs of names, and of numbers, as one token (parts of up to 100 letters or digits)."""
    t = F.regexp_replace(marked_text, rf" (?=[{NAME}{INITIAL}])(?<=[{NAME}{INITIAL}]\p{{L}}{{1,100}} )[{NAME}{INITIAL}]", JOINT)
    return F.regexp_replace(t, rf" (?={NUMBER})(?<={NUMBER}[\p{{N}}{POINT}]{{1,100}} ){NUMBER}", JOINT)


def value(word: Column) -> Column:
    """A marked token without its type."""
    return F.when(word < JOINT, F.substr(word, F.lit(2))).otherwise(word)


def _reading(slots: str) -> Callable[[Column], Column]:
    """Tokens whose type is in ``slots`` become their type (a sentence's first word a name), all others their value."""

    def read(word: Column) -> Column:
        kind = F.substring(word, 1, 1)
        return F.when(kind.isin(*slots), F.translate(kind, INITIAL, NAME)).otherwise(value(word))

    return read


#: The types that are slots in each reading: numbers and units; also names; also capitalised words elsewhere.
READINGS = (NUMBER + UNIT, NUMBER + UNIT + NAME, NUMBER + UNIT + NAME + INITIAL)


#: Numbers of the reading of all values and of that of the folded form, behind the READINGS.
LITERAL, FOLDED = len(READINGS), len(READINGS) + 1


def windows(
    rows: DataFrame, keys: list[str], sizes: list[int], readings: tuple[int, ...], asked: DataFrame | None = None
) -> DataFrame:
    """Windows of ``__marked`` tokens (``__folded`` ones in that reading) of all ``sizes``: keys, ``reading``, ``size``,
    ``place`` and ``hash``. Where a reading's window is the first reading's it isn't given again.

    With ``asked`` only windows that it has by ``hash``, with its columns: where a window stands is told for hits alone.
    Windows of fewer than 3 tokens are no evidence inside of a longer text: there the whole text must be the window.
    """
    reads = [*map(_reading, READINGS), value, _reading(READINGS[-1])]

    def hashed(k: int) -> Column:
        return F.transform("__folded" if k == FOLDED else "__marked", lambda w: F.xxhash64(reads[k](w)))

    made = rows.withColumns({f"__h{k}": hashed(k) for k in readings})

    def at(k: int, size: int) -> Column:
        n = F.size(f"__h{k}")
        places = F.when(n >= size if size >= 3 else n == size, F.sequence(F.lit(0), n - size))
        # the folded form has hashes of its own, as its places are others
        window = [F.lit(FOLDED)] if k == FOLDED else []
        return F.transform(places, lambda i: F.xxhash64(*window, F.slice(f"__h{k}", i + 1, size)))

    parts = [(s, k) for s in sizes for k in readings if k != FOLDED or s == WINDOW]
    made = made.withColumns({f"__w{s}_{k}": at(k, s) for s, k in parts})
    first = readings[0]

    def new(s: int, k: int) -> Column:
        own = F.col(f"__w{s}_{k}")
        if k not in (first, FOLDED):
            own = F.zip_with(own, f"__w{s}_{first}", lambda a, b: F.when(a != b, a))
        return F.coalesce(own, F.array().cast("array<bigint>"))

    counts = [F.coalesce(F.size(f"__w{s}_{k}"), F.lit(0)).alias(f"__n{i}") for i, (s, k) in enumerate(parts)]
    made = made.select(*keys, *counts, F.concat(*[new(s, k) for s, k in parts]).alias("__w"))
    # the outer form: for the inner one the optimizer adds a filter that makes the whole array once more
    made = made.select(*keys, *[f"__n{i}" for i in range(len(parts))], F.posexplode_outer("__w").alias("__at", "hash"))
    made = made.where(F.col("hash").isNotNull())
    found = [] if asked is None else [c for c in asked.columns if c != "hash"]
    made = made if asked is None else made.join(asked, "hash")
    start, which = F.lit(0), None
    for i, (s, k) in enumerate(parts):  # the arrays lie one behind the other
        stop = start + F.greatest(F.col(f"__n{i}"), F.lit(0))
        here = F.struct(F.lit(k).alias("reading"), F.lit(s).alias("size"), (F.col("__at") - start).alias("place"))
        which = F.when(F.col("__at") < stop, here) if which is None else which.when(F.col("__at") < stop, here)
        start = stop
    told = made.select(*keys, *found, which.alias("__which"), "hash")
    return told.select(*keys, *found, "__which.reading", "__which.size", "__which.place", "hash")


def _forms(rows: DataFrame, *keys: str) -> DataFrame:
    """``keys``, ``__marked`` and ``__folded`` tokens of ``text``; none of these in a text that has no number, nor a name
    but at the start of sentences."""
    rows = rows.select(*keys, marked(F.col("text")).alias("__m"))
    some = F.col("__m").contains(NAME) | F.col("__m").contains(NUMBER)
    fold = F.when(some, tokens(folded(F.col("__m")))).otherwise(F.array().cast("array<string>"))
    return rows.select(*keys, tokens(F.col("__m")).alias("__marked"), fold.alias("__folded"))


def _asked(items: DataFrame, sizes: list[int]) -> DataFrame:
    """(item_id, n, folded, item_place, reading, hash): the items' windows that are looked for."""
    kept = ["item_id", "__marked", "__folded"]
    found = windows(items, kept, sizes, tuple(range(FOLDED + 1)))
    folds = F.col("reading") == FOLDED
    n = F.when(folds, F.size("__folded")).otherwise(F.size("__marked"))
    # an item is asked for by windows of one size, in the folded form by whole windows only
    found = found.withColumn("n", n).where(F.col("size") == F.least("n", F.lit(WINDOW)))
    least = F.least(F.lit(LEAST_WORDS), F.greatest("size", F.lit(3)))

    def words(column: str, slots: str) -> Column:
        stretch = F.slice(column, F.col("place") + 1, F.col("size"))
        return F.size(F.filter(stretch, lambda w: ~F.substring(w, 1, 1).isin(*slots)))

    told = [(F.col("reading") == k) & (words("__marked", slots) >= least) for k, slots in enumerate(READINGS)]
    # too few words for a template: the values themselves must agree
    dense = (F.col("reading") == LITERAL) & (words("__marked", READINGS[0]) < least)
    bare = (F.col("reading") == 0) & (words("__marked", READINGS[0]) == F.col("size"))  # values and template are one
    fold = folds & (words("__folded", READINGS[-1]) >= least)
    found = found.where(reduce(lambda a, b: a | b, [*told, dense, bare, fold]))
    return checkpointed(found.select("item_id", "n", folds.alias("folded"), F.col("place").alias("item_place"), "reading", "hash"))


def leaks(documents: DataFrame, benchmark: DataFrame) -> DataFrame:
    """(doc_id, item_id, windows, first_place, exact) of each item that a document holds.

    first_place counts tokens, in the folded form if the item is found in that alone.
    """
    docs = documents.select("doc_id", "text", F.xxhash64("text").alias("row")).where(F.col("text").isNotNull())
    items = benchmark.select("item_id", F.col("text")).where(F.col("text").isNotNull()).distinct()
    items = checkpointed(_forms(items, "item_id").where(F.size("__marked") > 0))
    sizes = sorted(r[0] for r in items.select(F.least(F.size("__marked"), F.lit(WINDOW))).distinct().collect())  # WINDOW at most
    if not sizes:
        return documents.sparkSession.createDataFrame(
            [], "doc_id bigint, item_id bigint, windows bigint, first_place int, exact boolean"
        )
    asked = _asked(items, sizes)
    readings = tuple(r["reading"] for r in asked.select("reading").distinct().collect())
    asked = asked.drop("reading").distinct()
    if asked.count() <= BROADCAST_WINDOWS:
        asked = F.broadcast(asked)
    rows = _forms(docs, "doc_id", "row")
    found = windows(rows, ["doc_id", "row"], sizes, tuple(sorted({0, *readings})), asked)
    aligned = found.groupBy("doc_id", "row", "item_id", "n", "folded", (F.col("place") - F.col("item_place")).alias("diagonal")).agg(
        F.count_distinct("item_place").alias("windows"),
        F.min("item_place").alias("low"),
        F.max("item_place").alias("high"),
    )
    needed = F.greatest(F.least(F.lit(MATCHED), F.col("n") - WINDOW + 1), F.lit(1))
    return _consistent(checkpointed(aligned.where(F.col("windows") >= needed)), docs, items)


def _consistent(aligned: DataFrame, docs: DataFrame, items: DataFrame) -> DataFrame:
    """The alignments whose slots are replaced alike wherever they recur."""
    few = aligned.count() <= BROADCAST_WINDOWS
    ids = aligned.select(F.col("doc_id").alias("__id")).distinct()
    docs = docs.join(F.broadcast(ids) if few else ids, F.col("doc_id") == F.col("__id"), "left_semi")
    docs = _forms(docs, "doc_id", "row").select("doc_id", "row", F.struct("__marked", "__folded").alias("d"))
    both = aligned.join(items.select("item_id", F.struct("__marked", "__folded").alias("i")), "item_id").join(docs, ["doc_id", "row"])
    length = F.col("high") - F.col("low") + F.least(F.lit(WINDOW), F.col("n"))

    def stretch(form: str, low: Column) -> Column:
        words = F.when(F.col("folded"), F.col(f"{form}.__folded")).otherwise(F.col(f"{form}.__marked"))
        return F.slice(words, low + 1, length)

    pairs = F.zip_with(
        stretch("i", F.col("low")),
        stretch("d", F.col("low") + F.col("diagonal")),
        lambda a, b: F.struct(a.alias("item"), b.alias("doc")),
    )
    kind = _reading(READINGS[-1])
    slot = F.filter(pairs, lambda p: (p["item"] < JOINT) & (p["doc"] < JOINT) & (kind(p["item"]) == kind(p["doc"])))
    both = both.withColumn("pairs", F.array_distinct(slot))
    # a sentence's first word is asked for only where the item has it as a name elsewhere
    names = F.transform(F.filter("pairs", lambda p: F.substring(p["item"], 1, 1) == NAME), lambda p: value(p["item"]))
    both = both.withColumn("names", names)
    asked = F.filter(
        "pairs", lambda p: (F.substring(p["item"], 1, 1) != INITIAL) | F.array_contains("names", value(p["item"]))
    )

    def plain(w: Column) -> Column:
        return F.concat(kind(w), value(w))

    asked = F.transform(asked, lambda p: F.struct(plain(p["item"]).alias("item"), plain(p["doc"]).alias("doc")))
    both = both.withColumn("asked", F.array_distinct(asked))
    items_asked = F.size(F.array_distinct(F.transform("asked", lambda p: p["item"])))
    found = both.where(F.size("asked") == items_asked)
    exact = F.forall("pairs", lambda p: value(p["item"]) == value(p["doc"]))
    return found.groupBy("doc_id", "item_id").agg(
        F.max("windows").alias("windows"),
        F.coalesce(F.min(F.when(~F.col("folded"), F.col("low") + F.col("diagonal"))), F.min(F.col("low") + F.col("diagonal"))).alias("first_place"),
        F.max(exact).alias("exact"),
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


@shielded
def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item. A null doc_id can't be told from others and is kept."""
    found = leaks(docs, table(spark, sf_dir, "benchmark")).select(F.col("doc_id").alias("__doc_id")).distinct()
    return docs.join(found, F.col("doc_id") == F.col("__doc_id"), "left_anti")
