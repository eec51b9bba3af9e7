"""Substring dedup by sliding sentence spans.

A text is cut into sentences (each with the white space behind it, so that they join to the text again). Of each
STRETCH words in a row that hold no sentence's end, the one of least hash (the last of equal ones) is an end too.
So a cut depends only on the STRETCH - 1 words before and behind it, not on how the sentence around it goes on:
a passage that is repeated in mid-sentence is cut alike everywhere, but for its first and last words, and a
passage of 73 words or more always has a run in common with its copies (one of 51 nearly always; see the README).
From every sentence the shortest run of consecutive sentences is taken that has at least MIN_SENTENCES of
them and MIN_WORDS words; its words, lower-cased, are hashed to 96 bits. Runs of equal hash anywhere in the
corpus are one span. Of each span the first occurrence, by (doc_id, place), stays; sentences covered by any
other occurrence are removed.

Shape of the plan: occurrences are (hash, doc_id, place) rows. First occurrences come from an aggregate with
map-side combining, so a passage that a third of all documents share is one row per task there; only spans
that occur again are joined back to the occurrences, a plain equi-join that the adaptive skew join splits. Texts
are hashed once: occurrences wait in a Parquet table of the shared folder, which goes when they have been used.
Removed sentences go back to their document as one array of places, in one join with the texts.

Defined results: a null text stays null and a text without a repeated span stays as it is; a text may become
empty; rows with one doc_id count as one document (they don't repeat each other, and lose what either
loses); a row with a null doc_id stays as it is and is no occurrence; an empty table gives no rows; further
columns are kept by ``remove_repeats``.
"""

from __future__ import annotations

import re
import zlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pandas as pd
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fedgrid.llm.common import checkpointed, named, shielded, stored, table

MIN_SENTENCES, MIN_WORDS = 2, 20
#: Of so many words in a row one at least is followed by a cut.
STRETCH = 14

_SENTENCE = re.compile(r"[^.!?\n]*(?:[.!?\n]+(?:\s+|(?=[^\s.!?])|\Z)|\Z)")
_WORD = re.compile(r"(\S+)\s*")
_OCCURRENCES = "h1 bigint, h2 int, doc_id bigint, run bigint"
#: A run's number: its first sentence and its length (31 bits each), and whether its hash was in the text before.
_LENGTH = 31


class _Ranks(dict):
    """The rank of each word, by its hash; kept for the words of earlier texts, and bounded."""

    def __missing__(self, word: str) -> int:
        if len(self) >= 200_000:
            self.clear()
        rank = self[word] = zlib.crc32(word.encode("utf-8", "surrogatepass"))
        return rank


_RANKS = _Ranks()
#: Bits of a word's place that go along with its rank.
_PLACE = 24
_LAST = (1 << _PLACE) - 1


def _cut(text: str) -> tuple[list[str], np.ndarray, list[str], np.ndarray]:
    """Sentences by punctuation and their numbers of words, all lower-cased words, and whether a cut is behind each."""
    parts = [s for s in _SENTENCE.findall(text) if s]
    words = [s.lower().split() for s in parts]
    sizes = np.fromiter(map(len, words), np.int64, len(words))
    flat = list(chain.from_iterable(words))
    n = len(flat)
    cut = np.zeros(n, bool)
    cut[np.cumsum(sizes[sizes > 0]) - 1] = True
    if sizes.max(initial=0) > STRETCH:
        ranks = np.array(list(map(_RANKS.__getitem__, flat)), np.int64)
        ranks[cut] = -1
        # the place goes along in the low bits, backwards, as the last of equal ranks is wanted
        least = (ranks << _PLACE) | (_LAST - (np.arange(n) & _LAST))
        wide = 1
        while wide < STRETCH:
            step = min(wide, STRETCH - wide)
            least, wide = np.minimum(least[:-step], least[step:]), wide + step
        start = np.arange(len(least))
        # a place is known up to a multiple of 2^_PLACE, and lies within STRETCH words behind the window's start
        cut[start + ((_LAST - (least & _LAST) - start) & _LAST)] = True
    return parts, sizes, flat, cut


def sentences(text: str) -> list[str]:
    """The sentences of a text, white space included: their concatenation is the text."""
    parts, sizes, _, cut = _cut(text)
    out, at = [], 0
    for s, n in zip(parts, sizes.tolist(), strict=True):
        inner, at = cut[at : at + n - 1], at + n
        start = 0
        if n > STRETCH and inner.any():
            for m, behind in zip(_WORD.finditer(s), inner.tolist(), strict=False):
                if behind:
                    out.append(s[start : m.end()])
                    start = m.end()
        out.append(s[start:])
    return out


def spans(text: str) -> Iterator[tuple[int, int, int]]:
    """(first sentence, sentence behind the last, 96-bit hash) of each shortest run."""
    _, sizes, flat, cut = _cut(text)
    ends = np.flatnonzero(cut) + 1
    if not sizes.all():  # sentences of white space or signs alone, behind those that end at the same word
        blank = np.cumsum(sizes)[sizes == 0]
        ends = np.insert(ends, np.searchsorted(ends, blank, "right"), blank)
    counts = np.concatenate([[0], ends])
    first = np.arange(len(ends))
    behind = np.maximum(np.searchsorted(counts, counts[:-1] + MIN_WORDS), first + MIN_SENTENCES)
    whole = (behind <= len(ends)) & (counts[1:] > counts[:-1])
    first, behind = first[whole], behind[whole]
    joined = " ".join(flat)
    data = joined.encode("utf-8", "surrogatepass")
    if len(data) > len(joined):
        flat = [x.encode("utf-8", "surrogatepass") for x in flat]
    places = np.concatenate([[0], np.cumsum(np.fromiter(map(len, flat), np.int64, len(flat)) + 1)])
    lows, highs = places[counts[first]], places[counts[behind]] - 1
    digest = xxhash.xxh3_128_intdigest
    for i, j, low, high in zip(first.tolist(), behind.tolist(), lows.tolist(), highs.tolist(), strict=True):
        yield i, j, digest(data[low:high]) >> 32


def occurrences(docs: DataFrame) -> DataFrame:
    """(h1, h2, doc_id, run) of all spans of all texts; see ``_LENGTH`` for run."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            rows: list[tuple[int, int, int]] = []
            for doc_id, text in zip(batch["doc_id"], batch["text"], strict=True):
                seen: set[int] = set()
                for i, j, h in spans(text):
                    rows.append((h, doc_id, (i << _LENGTH | j - i) << 1 | (h in seen)))
                    seen.add(h)
                if len(rows) > 50_000:
                    yield _frame(rows)
                    rows = []
            yield _frame(rows)

    rows = docs.select("doc_id", "text").where(F.col("doc_id").isNotNull() & F.col("text").isNotNull())
    return rows.select(F.col("doc_id").cast("bigint").alias("doc_id"), "text").mapInPandas(run, _OCCURRENCES)


def _frame(rows: list[tuple[int, int, int]]) -> pd.DataFrame:
    low = (1 << 32) - 1
    return pd.DataFrame(
        {
            "h1": np.array([h >> 32 for h, *_ in rows], np.uint64).view(np.int64),
            "h2": np.array([h & low for h, *_ in rows], np.uint32).view(np.int32),
            "doc_id": np.array([r[1] for r in rows], np.int64),
            "run": np.array([r[2] for r in rows], np.int64),
        }
    )


def repeats(docs: DataFrame) -> DataFrame:
    """(doc_id, places): the sentences to remove of each document that has any; checkpointed."""
    with stored(occurrences(docs)) as found:
        first = found.groupBy("h1", "h2").agg(F.min("doc_id").alias("least"), F.count(F.lit(1)).alias("n"))
        # cut here, so that the join has two plain exchanges and the adaptive plan can split a frequent span
        again = checkpointed(first.where("n > 1").select("h1", "h2", "least"))
        later = found.join(again, ["h1", "h2"]).where((F.col("doc_id") > F.col("least")) | (F.col("run") % 2 == 1))
        places = later.groupBy("doc_id").agg(F.collect_set(F.shiftright("run", 1)).alias("runs"))

        def sentences_of(r):
            start = F.shiftright(r, _LENGTH).cast("int")
            return F.sequence(start, start + r.bitwiseAND(F.lit((1 << _LENGTH) - 1)).cast("int") - 1)

        covered = F.array_distinct(F.flatten(F.transform("runs", sentences_of)))
        return checkpointed(places.select("doc_id", covered.alias("places")))


def _without(texts: pd.Series, places: pd.Series) -> pd.Series:
    def cut(text: str | None, gone: np.ndarray | None) -> str | None:
        if text is None or gone is None:
            return text
        out = set(gone.tolist())
        return "".join(s for i, s in enumerate(sentences(text)) if i not in out)

    return pd.Series([cut(t, g) for t, g in zip(texts, places, strict=True)], dtype=object)


@shielded
def remove_repeats(docs: DataFrame, removed: str = "n_removed") -> DataFrame:
    """``docs`` with shortened texts, and the number of removed sentences as column ``removed``."""
    key, gone, cut = (named(docs, x) for x in ("id", "places", "cut"))
    found = repeats(docs).toDF(key, gone)
    joined = docs.join(found, F.col("doc_id") == F.col(key), "left")
    # only texts that lose something go to Python
    hit = F.col(gone).isNotNull() & F.col("text").isNotNull()
    shorter = F.pandas_udf(_without, "string")(F.when(hit, F.col("text")), F.when(hit, F.col(gone)))
    out = joined.withColumn(cut, shorter)
    lost = F.when(hit, F.size(gone)).otherwise(0).alias(removed)
    text = F.when(hit, F.col(cut)).otherwise(F.col("text")).alias("text")
    kept = [c for c in docs.columns if c.lower() != removed.lower()]
    return out.select(*[text if c == "text" else F.col(f"`{c}`") for c in kept], lost)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return remove_repeats(docs).select("doc_id", F.col("n_removed").cast("bigint").alias("n_removed"), "text")
