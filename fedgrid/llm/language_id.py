"""Language identification by segmentation-marginalised unigrams.

The pieces of a fixed public vocabulary get one probability per language. A word's probability under a
language is the sum over all its segmentations into pieces, by a forward algorithm over the lattice of
pieces; a text's log probability is the sum over its words, and the score is the posterior of the best
language under equal priors. The piece probabilities are learned by expectation-maximisation (forward
and backward over the same lattices) from the word counts of all labelled texts: the tasks sum up expected uses,
and pieces times languages numbers a round reach the driver.

A word is a letter (Unicode category L) and the letters and marks (M) that follow, lower-cased; so numerals and
signs aren't words, and words of Indic scripts stay whole. A character outside the vocabulary costs one fixed
piece. Every word of the whole text counts, whatever its length: sums are rescaled on the way, so they don't
underflow. Texts labelled ``und`` are left out of the learning.

Defined results: a null text, or one without a letter, gives ``und`` and score 0; so does everything
when no language could be learned; ties go to the language first in name order; repeated rows are scored
one by one; an empty table gives no rows; further columns, whatever their names, are ignored (the stage keeps them).
"""

from __future__ import annotations

import re
import uuid
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, replace
from functools import lru_cache

import numpy as np
import pandas as pd
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fedgrid.llm.common import checkpointed, crc_mod, kept, named, shielded, stored, table, trim

#: Where the public vocabularies lie, and which one is used.
VOCABULARY = "/opt/tokenizers/piece_bpe_32k.model"
#: Words kept in a worker's table of scored words; it is emptied when full.
MAX_WORDS = 500_000

UND = "und"
#: Nats by which a text as a whole may be less likely than the floor: a few letters tell little.
SHORT = 100.0
_WORD = regex.compile(r"\p{L}[\p{L}\p{M}]*+")
#: The same words in texts that have no mark and no numeral but decimal digits: those are all that \w is wrong about.
_PLAIN, _SPECIAL = re.compile(r"[^\W\d_]+"), regex.compile(r"[\p{M}\p{Nl}\p{No}]")
_MARK = "▁"
_UNKNOWN = 1e-9
#: Characters of a piece at most, and words times letters of the longest that share a lattice.
_PIECE, _AREA = 16, 1 << 18
#: Where all sums that later ones are made of are below the first bound they are multiplied by the second, and the
#: logarithm is told. Within _PIECE places sums differ by _UNKNOWN ** _PIECE at most, so none is lost.
_TINY, _UP = 1e-150, 1e150


@lru_cache(maxsize=2)
def vocabulary(path: str = VOCABULARY) -> tuple[str, ...]:
    """The distinct lower-cased pieces of letters, with the word mark where the vocabulary has it."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    pieces = {model.id_to_piece(i).lower() for i in range(model.get_piece_size())}
    return tuple(sorted(p for p in pieces if len(p) <= _PIECE and _WORD.fullmatch(p.removeprefix(_MARK))))


def words_of(text: str | None) -> list[str]:
    text = (text or "").lower()
    return (_PLAIN if text.isascii() or not _SPECIAL.search(text) else _WORD).findall(text)


def batches(words: list[str]) -> Iterator[list[str]]:
    """The words by length, in parts of 4096 at most whose lattices stay small."""
    rest = sorted(words, key=len, reverse=True)
    at = 0
    while at < len(rest):
        n = max(1, min(4096, _AREA // (len(rest[at]) + 1)))
        yield rest[at : at + n]
        at += n


class Pieces:
    """A vocabulary as a trie in arrays: a step from many places at once is one search."""

    def __init__(self, pieces: tuple[str, ...]):
        nodes, chars = {"": 0}, {c: k for k, c in enumerate(sorted({c for p in pieces for c in p}), start=1)}
        for p in pieces:
            for k in range(1, len(p) + 1):
                nodes.setdefault(p[:k], len(nodes))
        self.unknown, self.mark = len(pieces), nodes.get(_MARK, -1)
        #: Of each node its piece's number, -1 for what only begins pieces.
        self.piece = np.full(len(nodes), -1, np.int64)
        self.piece[[nodes[p] for p in pieces]] = np.arange(len(pieces))
        # characters are numbered from 1; 0 is any other
        self.codes = np.zeros(max(map(ord, chars), default=0) + 2, np.int64)
        self.codes[[ord(c) for c in chars]] = list(chars.values())
        self.width = len(chars) + 1
        steps = sorted((nodes[p[:-1]] * self.width + chars[p[-1]], k) for p, k in nodes.items() if p)
        self.steps = np.array([key for key, _ in steps] + [1 << 62], np.int64)  # the last one is never met
        self.stops = np.array([k for _, k in steps] + [-1], np.int64)

    def chars(self, text: str) -> np.ndarray:
        found = np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32)
        return self.codes[np.minimum(found, len(self.codes) - 1)]

    def walk(self, chars: np.ndarray, at: np.ndarray, ends: np.ndarray, node: int) -> list[tuple[np.ndarray, np.ndarray]]:
        """From each place ``at`` of ``chars`` on, up to its end: by length of the way, (indices into ``at``, pieces)."""
        out, own, nodes, d = [], np.arange(len(at)), np.full(len(at), node, np.int64), 0
        while len(own) and node >= 0:
            keys = nodes * self.width + chars[at[own] + d]
            found = np.searchsorted(self.steps, keys)
            there = self.steps[found] == keys
            own, nodes = own[there], self.stops[found[there]]
            pieces = self.piece[nodes]
            told = pieces >= 0
            out.append((own[told], pieces[told]))
            d += 1
            more = at[own] + d < ends[own]
            own, nodes = own[more], nodes[more]
        return out


def prefixes(pieces: tuple[str, ...]) -> Pieces:
    """What a lattice looks its pieces up in; the unknown character's number is the one after the last piece's."""
    return Pieces(pieces)


def _sorted_by(place: np.ndarray, word: np.ndarray) -> np.ndarray:
    """The order by place and then word, ties as they are; numbers of 16 bits are sorted by radix."""
    order = np.argsort(word.astype(np.uint16), kind="stable")
    place = place[order]
    return order[np.argsort(place.astype(np.uint16) if place.max(initial=0) < 1 << 16 else place, kind="stable")]


class Lattice:
    """All pieces of a list of 4096 words at most as edges (word, start, stop, piece), with forward and backward sums."""

    def __init__(self, words: list[str], index: Pieces):
        self.n, self.lengths = len(words), np.array([len(w) for w in words], np.int64)
        chars, first = index.chars("".join(words)), np.cumsum(self.lengths) - self.lengths
        own = np.repeat(np.arange(self.n), self.lengths)
        start = np.arange(len(chars)) - first[own]
        plain = index.walk(chars, np.arange(len(chars)), (first + self.lengths)[own], 0)
        single = np.zeros(len(chars), bool)
        if plain:
            single[plain[0][0]] = True
        lone = np.flatnonzero(~single)
        # (word, start, stop, piece): the longest first, so that a word's edges to one stop begin in order; the marked last
        parts = [(own[at], start[at], start[at] + d, piece) for d, (at, piece) in reversed(list(enumerate(plain, start=1)))]
        parts.append((own[lone], start[lone], start[lone] + 1, np.full(len(lone), index.unknown)))
        whole = np.flatnonzero(self.lengths > 0)
        marked = index.walk(chars, first[whole], (first + self.lengths)[whole], index.mark)
        parts += [(whole[at], np.zeros(len(at), np.int64), np.full(len(at), d), piece) for d, (at, piece) in enumerate(marked, start=1)]
        word, start, stop, piece = (np.concatenate(column) for column in zip(*parts, strict=True))
        order = _sorted_by(stop, word)
        self.edges = word[order], start[order], stop[order], piece[order]

    def logs(self, probs: np.ndarray) -> np.ndarray:
        """Logarithm of each word's sum over all segmentations; probs: pieces by languages, and so is the result."""
        word, start, stop, piece = self.edges
        alpha = np.zeros((int(self.lengths.max(initial=0)) + 1, self.n, probs.shape[1]))
        alpha[0] = 1.0
        taken = np.zeros((self.n, probs.shape[1]))
        cuts = np.searchsorted(stop, np.arange(len(alpha) + 1))
        weight = probs[piece]
        for j in range(1, len(alpha)):
            part = slice(cuts[j], cuts[j + 1])
            own = word[part]  # in order, as edges are made word by word
            if not len(own):
                continue
            first = np.flatnonzero(np.diff(own, prepend=-1))
            sums = np.add.reduceat(weight[part] * alpha[start[part], own], first, axis=0)
            alpha[j, own[first]] = sums
            if sums.min() < _TINY:
                recent = slice(max(0, j - _PIECE + 1), j + 1)
                low = (alpha[recent].max(axis=0) < _TINY) & (alpha[j] > 0)  # a word that has ended has no later sums
                if low.any():
                    alpha[recent, low] *= _UP
                    taken[low] += np.log(_UP)
        return np.log(alpha[self.lengths, np.arange(self.n)]) - taken

    def _sweep(self, logs: np.ndarray, into: np.ndarray, out: np.ndarray, ends: np.ndarray, begin: np.ndarray) -> np.ndarray:
        """Log sums at each place of each word, from where ``begin`` is 0, along edges from ``out`` to ``into``."""
        word = self.edges[0]
        sums = begin.copy()
        order = _sorted_by(into, word)
        cuts = np.searchsorted(into[order], np.arange(len(sums) + 1))
        for j in ends:
            part = order[cuts[j] : cuts[j + 1]]
            if len(part):
                own = word[part]
                first = np.flatnonzero(np.diff(own, prepend=-1))
                value = logs[part] + sums[out[part], own]
                top = np.maximum.reduceat(value, first)
                with np.errstate(invalid="ignore"):
                    rest = np.exp(value - np.repeat(top, np.diff(np.append(first, len(own)))))
                    sums[j, own[first]] = np.where(np.isneginf(top), -np.inf, top + np.log(np.add.reduceat(rest, first)))
        return sums

    def expected(self, probs: np.ndarray, counts: np.ndarray) -> np.ndarray:
        """Expected uses of each piece, for words that occur ``counts`` times; probs: one per piece."""
        word, start, stop, piece = self.edges
        with np.errstate(divide="ignore"):
            logs = np.log(probs)[piece]
        longest = int(self.lengths.max(initial=0))
        begin = np.full((longest + 1, self.n), -np.inf)
        begin[0] = 0.0
        alpha = self._sweep(logs, stop, start, np.arange(1, longest + 1), begin)
        begin = np.full((longest + 1, self.n), -np.inf)
        begin[self.lengths, np.arange(self.n)] = 0.0
        beta = self._sweep(logs, start, stop, np.arange(longest - 1, -1, -1), begin)
        total = alpha[self.lengths, np.arange(self.n)]
        use = counts[word] * np.exp(alpha[start, word] + logs + beta[stop, word] - total[word])
        return np.bincount(piece, use, len(probs))


@dataclass
class Model:
    languages: list[str]
    pieces: Pieces
    probs: np.ndarray  # languages by pieces, the last of which is the unknown character
    #: Of each language the least mean log probability a letter that a text of it is expected to have.
    floors: np.ndarray | None = None


def word_counts(usable: DataFrame) -> DataFrame:
    """(lang, word, n) over all texts; each task adds up its own words first, within MAX_WORDS."""

    def count(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        seen: dict[str, Counter] = {}

        def told() -> Iterator[pd.DataFrame]:
            yield from (pd.DataFrame({"lang": [k] * len(c), "word": list(c), "n": list(c.values())}) for k, c in seen.items() if c)
            seen.clear()

        for frame in frames:
            for lang, text in zip(frame["lang"], frame["text"], strict=True):
                seen.setdefault(lang, Counter()).update(words_of(text))
                if sum(map(len, seen.values())) > MAX_WORDS:
                    yield from told()
        yield from told()
        trim()

    counted = usable.select("lang", "text").mapInPandas(count, "lang string, word string, n bigint")
    return counted.groupBy("lang", "word").agg(F.sum("n").alias("n"))


def fit(counts: DataFrame, languages: list[str], pieces: tuple[str, ...], rounds: int = 4, smoothing: float = 0.05) -> Model:
    """From word counts (lang, word, n) to piece probabilities, by expectation-maximisation; one pass a round."""
    index, n, at = prefixes(pieces), len(pieces), {k: i for i, k in enumerate(languages)}
    context = counts.sparkSession.sparkContext
    sent = context.broadcast(index)
    probs = np.full((len(languages), n + 1), 1.0 / (n + 1))
    probs[:, -1] = _UNKNOWN

    def expectations(told):
        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            p, used = told.value, np.zeros((len(at), n + 1))
            for frame in frames:
                for lang, own in frame.groupby("lang"):
                    times = dict(zip(own["word"], own["n"], strict=True))
                    for part in batches(list(times)):
                        used[at[lang]] += Lattice(part, sent.value).expected(p[at[lang]], np.array([times[w] for w in part], float))
            i, j = np.nonzero(used)
            yield pd.DataFrame({"i": i, "j": j, "used": used[i, j]})
            trim()

        return run

    for _ in range(rounds):
        told = context.broadcast(probs)
        used = np.full(probs.shape, smoothing)
        found = counts.mapInPandas(expectations(told), "i int, j int, used double").groupBy("i", "j").agg(F.sum("used").alias("used")).toPandas()
        used[found["i"], found["j"]] += found["used"]
        told.unpersist()
        # pieces that no language uses more than smoothing does stay in the lattice: their mass is common
        probs = np.full(probs.shape, _UNKNOWN)
        probs[:, :-1] = used[:, :-1] / used[:, :-1].sum(axis=1, keepdims=True)
    sent.unpersist()
    return Model(languages, index, probs)


def train(documents: DataFrame, path: str = VOCABULARY) -> Model:
    """Learned from (text, lang) of all labelled texts."""
    usable = documents.where(F.col("lang").isNotNull() & F.col("text").isNotNull() & (F.col("lang") != UND))
    with stored(word_counts(usable)) as counts:
        languages = sorted(r["lang"] for r in counts.select("lang").distinct().collect())
        return fit(counts, languages, vocabulary(path))


def with_floors(scored: DataFrame, model: Model, found: str = "found", spread: float = 8.0, least: float = 1.5) -> Model:
    """The model with each language's floor: the mean over all its labelled texts of the mean log probability a letter, less
    ``spread`` standard deviations, ``least`` nats at least. ``scored``: (lang, what ``identifier`` found) of every text."""
    floors = np.full(len(model.languages), -np.inf)
    rows = scored.where(F.col("lang").isin(model.languages)).where(F.col(f"{found}.lang_pred") == F.col("lang"))
    seen = F.col(f"{found}.evidence")
    for r in rows.groupBy("lang").agg(F.avg(seen).alias("m"), F.coalesce(F.stddev(seen), F.lit(0.0)).alias("s")).collect():  # a row for each language
        floors[model.languages.index(r["lang"])] = r["m"] - max(least, spread * r["s"])
    return replace(model, floors=floors)


class Scorer:
    """Scores texts; keeps the log probabilities of words it has met, within MAX_WORDS."""

    def __init__(self, model: Model):
        self.model, self.known = model, {}
        self.table = np.zeros((MAX_WORDS, len(model.languages)))

    def _learn(self, words: set[str]) -> None:
        """Takes in the words that aren't known yet."""
        new = list(words - self.known.keys())
        if len(self.known) + len(new) > MAX_WORDS:
            self.known.clear()
            new = list(words)
        for part in batches(new):
            logs = Lattice(part, self.model.pieces).logs(self.model.probs.T)
            first = len(self.known)
            self.table[first : first + len(part)] = logs
            self.known.update(zip(part, range(first, first + len(part)), strict=True))

    def _sum(self, words: list[str]) -> np.ndarray:
        known = self.known
        return self.table[[known[w] for w in words]].sum(axis=0)

    def log_probabilities(self, texts: list[str | None]) -> list[tuple[int, np.ndarray]]:
        """Number of letters and log probability under each language, for some texts at a time."""
        out: list[tuple[int, np.ndarray]] = []
        waiting: list[list[str]] = []
        size = 0

        def flush() -> None:
            self._learn(set().union(*waiting))
            out.extend((sum(map(len, words)), self._sum(words)) for words in waiting)
            waiting.clear()

        for text in texts:
            words = words_of(text)
            if len(words) > MAX_WORDS // 2:  # a very long text, in stretches
                flush()
                size, total = 0, np.zeros(len(self.model.languages))
                for at in range(0, len(words), MAX_WORDS // 2):
                    part = words[at : at + MAX_WORDS // 2]
                    self._learn(set(part))
                    total += self._sum(part)
                out.append((sum(map(len, words)), total))
                continue
            if waiting and size + len(words) > MAX_WORDS // 8:
                flush()
                size = 0
            waiting.append(words)
            size += len(words)
        flush()
        return out

    def predict(self, texts: pd.Series) -> pd.DataFrame:
        langs, scores, evidence, letters = [], [], [], []
        for n, logs in self.log_probabilities(texts.tolist()):
            letters.append(n)
            if not n or not len(logs):
                langs.append(UND), scores.append(0.0), evidence.append(None)
                continue
            best = int(np.argmax(logs))
            langs.append(self.model.languages[best])
            scores.append(float(1.0 / np.exp(np.minimum(logs - logs[best], 0.0)).sum()))
            evidence.append(float(logs[best]) / n)
        return pd.DataFrame({"lang_pred": langs, "score": scores, "evidence": pd.Series(evidence, dtype="float64"),
                             "letters": letters})


def identifier(spark: SparkSession, model: Model):
    """A Column function: text to struct(lang_pred, score, evidence, letters). The model goes out once, by broadcast.

    Evidence is the mean log probability a letter under the language found.

    Its size is fixed by the vocabulary and the number of languages, not by the corpus.
    """
    sent, key = spark.sparkContext.broadcast(model), uuid.uuid4().hex

    def predict(batches):
        scorer = kept(f"language_id {key}", lambda: Scorer(sent.value))
        for texts in batches:
            yield scorer.predict(texts)
        trim()

    predict.__annotations__ = {"batches": Iterator[pd.Series], "return": Iterator[pd.DataFrame]}
    return F.pandas_udf(predict, "lang_pred string, score double, evidence double, letters bigint")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    documents = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    model = train(documents.where(crc_mod("doc_id", 4) != 2))
    found = documents.select(
        "doc_id", (crc_mod("doc_id", 4) == 2).alias("held_out"), identifier(spark, model)("text").alias("found")
    )
    return found.select("doc_id", "held_out", "found.lang_pred", "found.score")


@shielded
def stage(spark: SparkSession, docs: DataFrame, sf_dir: str, least: float = 0.5) -> DataFrame:
    """Keeps the documents that are in some learned language: with a posterior of ``least`` or more, and not less
    likely a letter than the language's floor less SHORT / letters (other languages and noise have a winner too).

    Rejected: texts that are null or have no letter, and texts that no language wins or that no learned language
    explains. Languages are learned from the labels of the given documents themselves.
    """
    model = train(docs.select("text", "lang"))
    found = named(docs, "found")
    # scored once: the floors are told from all scores, and the rows are chosen by them
    rest = checkpointed(docs.withColumn(found, identifier(spark, model)(F.col("text"))))
    model = with_floors(rest, model, found)
    rest = rest.where((F.col(f"{found}.lang_pred") != UND) & (F.col(f"{found}.score") >= least))
    floors = [F.when(F.col(f"{found}.lang_pred") == k, F.lit(float(v))) for k, v in zip(model.languages, model.floors, strict=True)]
    if floors:
        floor = F.coalesce(*floors) - SHORT / F.col(f"{found}.letters")
        rest = rest.where(F.col(f"{found}.evidence") >= floor)
    return rest.drop(found)
