"""Soft-membership mixing to target token shares, in DataFrame functions only.

Domains come from the labelled table: ``toxic``, ``low`` (quality 0) and ``high``. A naive Bayes classifier
over bucketed document features (shares of symbols and capitals, word length, and density of the words that
tell each domain, every occurrence counted) gives every document a posterior over the domains. Rates r >= 0 for the documents are then
fitted so that the expected tokens of each domain, sum of tokens * rate * posterior, match the targets:

    minimise  1/2 sum_c (a_c - w_c)^2 / s_c  +  ridge/2 sum_d (t_d / T) (r_d - 1)^2

with a_c the share reached, w_c the target share, s_c the share at rate 1 and t_d / T a document's share of
all tokens. It is solved by projected gradients in the inner product weighted by t_d / T. There the gradient
of document d is p_d . (a - w) / s + ridge (r_d - 1), so all documents of one posterior keep one rate, and
the Hessian's norm is 1 + ridge, which gives the step; momentum speeds it up. Each round is one aggregate over the distinct feature
cells, of which there are at most the product of the buckets whatever the corpus: the documents are added up
per cell once, before anything moves, and no key can be hot. A round's result is one number per domain, and the
fitted rates go back to the documents as a broadcast table of the cells (MAX_CELLS rows at most).

Defined results: a null text has no tokens and the features of the empty text; labels of other values than
0 and 1 are ignored; a document labelled twice counts with each label; without any label the posteriors are
uniform; with no tokens at all every rate is 1; repeated rows get a rate each; an empty table gives no rows; further
columns, whatever their names, are kept, but for those called tokens, rate, p_<domain> (and, by the stage, copies),
which are replaced. Targets that the fit doesn't reach are warned about.
"""

from __future__ import annotations

import math
import warnings
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from fedgrid.llm.common import checkpointed, hash_share, shielded, table

DOMAINS = ("high", "low", "toxic")
TARGETS = {"high": 0.9, "low": 0.08, "toxic": 0.02}
#: Bound on the labelled documents that words and buckets are learned from (a hashed share of the labels).
MAX_LABELLED = 10_000
#: Telling words kept for each domain, and the least number of labelled documents that hold one.
WORDS, SUPPORT = 40, 4

# Bucket bounds of the features: shares of characters, characters a word, telling words per word.
SHARE_BOUNDS = (0.002, 0.01, 0.03, 0.08, 0.2, 0.5)
LENGTH_BOUNDS = (4.0, 5.0, 6.0, 7.0, 9.0, 14.0)
DENSITY_BOUNDS = (1e-9, 0.004, 0.02, 0.1)


def _bucket(value: Column, bounds: tuple[float, ...]) -> Column:
    return sum((F.when(value >= b, 1).otherwise(0) for b in bounds), F.lit(0))


def _words(text: Column) -> Column:
    """The lower-cased words of a text; the first and the last may be empty."""
    return F.split(F.lower(text), r"[^\p{L}]+")


def _without(text: Column, characters: str) -> Column:
    return F.length(F.translate(text, characters, ""))


@dataclass
class Classifier:
    """Telling words of each domain, log priors, and log likelihoods by (feature, domain, bucket)."""

    words: dict[str, list[str]]
    priors: list[float]
    tables: list[list[list[float]]]


N_FEATURES = 3 + len(DOMAINS)
_SIZES = [len(SHARE_BOUNDS) + 1] * 2 + [len(LENGTH_BOUNDS) + 1] + [len(DENSITY_BOUNDS) + 1] * len(DOMAINS)


def features(docs: DataFrame, text: str, words: dict[str, list[str]]) -> DataFrame:
    """``docs`` with columns __tokens (words, runs of letters) and __f0 .. (bucket codes).

    In layers, as an expression over the text that several others need is computed once that way.
    """
    t = F.coalesce(F.col(text), F.lit(""))
    telling = sorted({w for own in words.values() for w in own})

    def held(column: str, own: list[str]) -> Column:
        """All occurrences of the words, as often as each is there."""
        return F.filter(column, lambda w: w.isin(own))

    out = docs.withColumns(
        {
            "__all": _words(t),
            "__n": F.length(t),
            "__symbols": _without(t, "#$%&*|!<>=_{}[]~^"),
            "__small": _without(t, "ABCDEFGHIJKLMNOPQRSTUVWXYZ"),
        }
    )
    edges = F.when(F.get("__all", F.lit(0)) == "", 1).otherwise(0) + F.when(
        (F.size("__all") > 1) & (F.element_at("__all", -1) == ""), 1
    ).otherwise(0)
    out = out.withColumns({"__tokens": F.size("__all") - edges, "__hits": held("__all", telling)})
    n, tokens = F.greatest("__n", F.lit(1)), F.greatest("__tokens", F.lit(1))
    values = {"__v0": (F.col("__n") - F.col("__symbols")) / n, "__v1": (F.col("__n") - F.col("__small")) / n}
    values["__v2"] = F.col("__n") / tokens
    for k, domain in enumerate(DOMAINS, start=3):
        values[f"__v{k}"] = F.size(held("__hits", words[domain])) / tokens
    out = out.withColumns(values)
    bounds = [SHARE_BOUNDS, SHARE_BOUNDS, LENGTH_BOUNDS] + [DENSITY_BOUNDS] * len(DOMAINS)
    out = out.withColumns({f"__f{k}": _bucket(F.col(f"__v{k}"), b) for k, b in enumerate(bounds)})
    return out.drop("__all", "__n", "__symbols", "__small", "__hits", *values)


def train(documents: DataFrame, labels: DataFrame, bound: int = MAX_LABELLED) -> Classifier:
    """From (doc_id, text) and (doc_id, quality, toxic), on about ``bound`` labelled documents at most."""
    domain = F.when(F.col("toxic") == 1, "toxic").when(F.col("quality") == 0, "low").when(F.col("quality") == 1, "high")
    named = labels.select("doc_id", domain.alias("domain")).where(F.col("doc_id").isNotNull() & F.col("domain").isNotNull())
    share = min(1.0, bound / max(named.count(), 1))
    picked = named.where(hash_share("doc_id", share)).distinct()
    rows = checkpointed(
        documents.select("doc_id", F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(picked), "doc_id")
    )
    totals = {r["domain"]: r["count"] for r in rows.groupBy("domain").count().collect()}
    every = sum(totals.values())
    counts = rows.select("domain", F.array_distinct(_words(F.col("text"))).alias("words"))
    counts = counts.select("domain", F.explode_outer("words").alias("word")).where(F.length("word") > 1)
    counts = counts.groupBy("word").agg(*[F.count_if(F.col("domain") == d).alias(d) for d in DOMAINS])
    words = {}
    for d in DOMAINS:
        own, rest = F.col(d), sum((F.col(x) for x in DOMAINS if x != d), F.lit(0))
        p = (own + 0.5) / (totals.get(d, 0) + 1.0)
        q = (rest + 0.5) / (every - totals.get(d, 0) + 1.0)
        telling = counts.where(own >= SUPPORT).select("word", (p * F.log(p / q)).alias("gain")).where("gain > 0")
        top = telling.orderBy(F.col("gain").desc(), "word").limit(WORDS)
        words[d] = [r["word"] for r in top.collect()]
    cells = features(rows, "text", words)
    names = [f"__f{k}" for k in range(N_FEATURES)]
    codes = F.explode(F.array(*[F.struct(F.lit(k).alias("f"), F.col(c).alias("b")) for k, c in enumerate(names)]))
    seen = cells.select("domain", codes.alias("x")).groupBy("domain", "x.f", "x.b").count().collect()
    tables = [[[1.0] * size for _ in DOMAINS] for size in _SIZES]
    for r in seen:
        tables[r["f"]][DOMAINS.index(r["domain"])][r["b"]] += r["count"]
    logs = [[[math.log(v / sum(row)) for v in row] for row in feature] for feature in tables]
    priors = [math.log((totals.get(d, 0) + 1.0) / (every + len(DOMAINS))) for d in DOMAINS]
    return Classifier(words, priors, logs)


_RADIX = [math.prod(_SIZES[:k]) for k in range(N_FEATURES)]
#: The most feature cells there can be, and so the most rows of the broadcast table of rates.
MAX_CELLS = math.prod(_SIZES)


def with_cells(docs: DataFrame, model: Classifier, text: str = "text") -> DataFrame:
    """``docs`` with columns __tokens and __cell, one number for all bucket codes."""
    names = [f"__f{k}" for k in range(N_FEATURES)]
    cell = sum((F.col(n) * r for n, r in zip(names, _RADIX, strict=True)), F.lit(0))
    return features(docs, text, model.words).withColumn("__cell", cell).drop(*names)


def posteriors(cells: DataFrame, model: Classifier) -> DataFrame:
    """``cells`` with columns __p_<domain>, from __cell."""
    codes = [F.floor(F.col("__cell") / r).cast("int") % size for r, size in zip(_RADIX, _SIZES, strict=True)]
    out = cells.withColumns({f"__f{k}": c for k, c in enumerate(codes)})
    for c, domain in enumerate(DOMAINS):
        logs = F.lit(model.priors[c])
        for k in range(N_FEATURES):
            logs = logs + F.get(F.array(*map(F.lit, model.tables[k][c])), F.col(f"__f{k}"))
        out = out.withColumn(f"__l_{domain}", logs)
    top = F.greatest(*[F.col(f"__l_{d}") for d in DOMAINS])
    total = sum((F.exp(F.col(f"__l_{d}") - top) for d in DOMAINS), F.lit(0.0))
    out = out.withColumns({f"__p_{d}": F.exp(F.col(f"__l_{d}") - top) / total for d in DOMAINS})
    return out.select(*cells.columns, *[f"__p_{d}" for d in DOMAINS])


def rate_of(history: list[list[float]], ridge: float, point: str = "rate") -> Column:
    """The rate after the gradient rounds in ``history``, from rate 1.

    A round is one coefficient per domain and its momentum. ``point='ahead'`` gives the extrapolated point at
    which the next gradient is taken.
    """
    step = 1.0 / (1.0 + ridge)
    start = F.struct(F.lit(1.0).alias("rate"), F.lit(1.0).alias("ahead"))
    if not history:
        return start[point]

    def turn(state: Column, g: Column) -> Column:
        slope = sum((F.col(f"__p_{d}") * F.get(g, F.lit(c)) for c, d in enumerate(DOMAINS)), F.lit(-ridge))
        rate = F.greatest(F.lit(0.0), state["ahead"] * (1.0 - step * ridge) - slope * step)
        ahead = rate + F.get(g, F.lit(len(DOMAINS))) * (rate - state["rate"])
        return F.struct(rate.alias("rate"), ahead.alias("ahead"))

    rounds = F.array(*[F.array(*map(F.lit, map(float, g))) for g in history])
    return F.aggregate(rounds, start, turn)[point]


def fit_rates(
    members: DataFrame, targets: dict[str, float], ridge: float = 1e-3, rounds: int = 40, tolerance: float = 1e-4
) -> list[list[float]]:
    """Gradient history of the fit over (__tokens, __p_<domain>) rows."""
    names = [f"__p_{d}" for d in DOMAINS]
    cells = checkpointed(members.groupBy(*names).agg(F.sum("__tokens").alias("t")).coalesce(8))
    total = sum(targets.values())
    wanted = [targets[d] / total for d in DOMAINS]

    def reached(history: list[list[float]]) -> dict[str, list[float]] | None:
        sums = []
        for point in ("rate", "ahead"):
            rate = rate_of(history, ridge, point)
            sums += [F.sum(F.col("t") * rate * F.col(n)).alias(point + n) for n in names]
        got = cells.agg(F.sum("t").alias("all"), *sums).first()
        return {p: [got[p + n] / got["all"] for n in names] for p in ("rate", "ahead")} if got["all"] else None

    now = reached([])
    if now is None:
        return []
    scale = [max(s, 1e-9) for s in now["rate"]]
    history: list[list[float]] = []
    for k in range(1, rounds + 1):
        slope = [(a - w) / s for a, w, s in zip(now["ahead"], wanted, scale, strict=True)]
        history.append([*slope, (k - 1.0) / (k + 2.0)])
        now = reached(history)
        if max(abs(a - w) for a, w in zip(now["rate"], wanted, strict=True)) < tolerance:
            break
    else:
        warnings.warn(f"after {rounds} rounds the shares are {now['rate']}, the targets {wanted}", stacklevel=2)
    return history


@shielded
def mix(
    docs: DataFrame,
    labels: DataFrame,
    targets: dict[str, float] | None = None,
    ridge: float = 1e-3,
    text_free: bool = False,
) -> DataFrame:
    """``docs`` with columns tokens, p_high, p_low, p_toxic and rate.

    With ``text_free`` the result goes without the texts, and these are read once instead of twice.
    """
    model = train(docs, labels)
    members = with_cells(docs, model)
    if text_free:
        members = checkpointed(members.drop("text"))
    cells = members.groupBy("__cell").agg(F.sum("__tokens").alias("__tokens")).coalesce(8)
    cells = checkpointed(posteriors(cells, model))
    history = fit_rates(cells, targets or TARGETS, ridge)
    rates = checkpointed(cells.withColumn("__rate", rate_of(history, ridge)).drop("__tokens"))
    out = members.join(F.broadcast(rates), "__cell")  # MAX_CELLS rows at most, and every document has its cell
    kept = [c for c in members.columns if c in docs.columns and c.lower() not in {"tokens", "rate", *(f"p_{d}" for d in DOMAINS)}]
    return out.select(
        *kept,
        F.col("__tokens").cast("bigint").alias("tokens"),
        *[F.round(f"__p_{d}", 6).alias(f"p_{d}") for d in DOMAINS],
        F.round("__rate", 6).alias("rate"),
    )


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return mix(docs, table(spark, sf_dir, "labels"), text_free=True)


@shielded
def stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that the mix takes, with their fitted rate and, as ``copies``, how often it takes each.

    copies is the rate rounded up or down by a hash of doc_id and text, so that it is the rate on average; documents
    with no copy go. A document that is taken several times stays one row: readers repeat it.
    """
    mixed = mix(docs, table(spark, sf_dir, "labels"))
    u = F.pmod(F.xxhash64("doc_id", "text"), F.lit(1 << 30)) / float(1 << 30)
    return mixed.withColumn("copies", F.floor(F.col("rate") + u).cast("bigint")).where("copies > 0")
