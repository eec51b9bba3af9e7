"""Personal data: base patterns plus a linear-chain conditional random field over word shapes.

The base patterns (e-mail, IP address, payment card, phone) are matched exactly. The random field adds spans that they
can't describe: phones without a plus sign, cards with other separators, masked e-mails and addresses, and secrets
(keys, tokens, passwords). Its tokens are runs of non-space characters, its sequences are lines, its features the
shapes of a token, of the two before it and of the one behind it (a cue word has a shape of its own, a long number
tells whether its check digit fits), its labels O and B/I of each kind. It is trained by gradient steps on the
conditional likelihood (forward-backward) over the small labelled table that ``labelled_table`` makes, and decoded by
Viterbi in numpy, many lines at a time. What it labels is a span; nothing filters it but that an added span may not
overlap a base span.

Defined results: a null text counts as empty and has no spans; whole texts are read whatever their length;
repeated rows are treated one by one; an empty table gives no rows; further columns, whatever their names, are ignored.
"""

from __future__ import annotations

import hashlib
import random
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from fedgrid.llm.common import table

BASE = ("email", "ip", "card", "phone")
KINDS = (*BASE, "secret")
LABELS = ("O", *(f"{p}-{k}" for k in KINDS for p in "BI"))
Span = tuple[int, int, int]  # start, index of the kind, end

# ---- base patterns -----------------------------------------------------------------------------------

_LOCAL = frozenset("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789._%+-")
_DOMAIN = re.compile(r"@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")


def luhn(digits: str) -> bool:
    total = 0
    for k, d in enumerate(reversed(digits)):
        v = int(d) * (1 + k % 2)
        total += v - 9 * (v > 9)
    return total % 10 == 0


def _emails(text: str) -> Iterator[Span]:
    done = 0
    at = text.find("@")
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        match = _DOMAIN.match(text, at) if start < at else None
        if match:
            done = match.end()
            yield start, 0, done
        at = text.find("@", max(at + 1, done))


def _digits(text: str) -> str:
    return "".join(c for c in text if "0" <= c <= "9")


def base_spans(text: str) -> list[Span]:
    """Spans of the base patterns, by start and then kind."""
    found = list(_emails(text))
    for m in _IP.finditer(text):
        if all(len(p.lstrip("0")) < 4 and int(p.lstrip("0") or "0") <= 255 for p in m[0].split(".")):
            found.append((m.start(), 1, m.end()))
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 12 and 12 <= len(d := _digits(m[0])) <= 19 and luhn(d):
            found.append((m.start(), 2, m.end()))
    for m in _PHONE.finditer(text):
        if 9 <= len(_digits(m[0])) <= 15:
            found.append((m.start(), 3, m.end()))
    return sorted(found)


# ---- word shapes -------------------------------------------------------------------------------------

_RUN = re.compile(r"[0-9]+|[^\W\d_]+|.", re.DOTALL)
_NUMBERS = re.compile(r"[0-9]+")
_IP_LIKE = re.compile(r"[0-9]{1,3}(?:(?:\.|\[\.\])[0-9]{1,3}){3}(?::[0-9]+)?")
_REST = ("<word>", "<digits>", "<at>", "<mixed>", "<none>")
_EDGE = ".,;:!?\"'"
_NOISE = _EDGE + "#$%&*"
#: A token of more runs than this has its length and alphabet as its shape.
_RUNS = 8

_CUES = {
    "email": ["mail", "write to", "contact", "e-mail:", "reach me at"],
    "ip": ["host", "from", "server", "login from", "address"],
    "card": ["card", "visa", "card no.", "paid with", "number"],
    "phone": ["call", "phone:", "tel.", "mobile", "fax"],
    "secret": ["token", "api_key", "apikey", "key", "secret", "password", "passwd", "pwd", "bearer", "access_token"],
}
_TELLING = {word.strip(_EDGE): kind for kind in ("phone", "card", "secret") for cue in _CUES[kind] for word in cue.split()}


def shape(word: str) -> str:
    """Runs of letters as x, X or Xx, of digits as d and their number (6 and more as d+), the rest as it is."""
    bare = word.rstrip(_NOISE).lstrip(_EDGE)
    cue = _TELLING.get(bare.lower())
    if cue:
        return f"<{cue}>"
    if bare.isalpha():
        return "x" if bare.islower() else "X" if bare.isupper() else "Xx"
    runs = _RUN.findall(bare)
    if len(runs) > _RUNS:
        if _IP_LIKE.fullmatch(bare):
            return "ip" if all(int(p) < 256 for p in _NUMBERS.findall(bare)[:4]) else "no ip"
        kind = "hex" if all(c in "0123456789abcdef" for c in bare.lower()) else "key" if all(c.isalnum() or c in "+/=_-" for c in bare) else "mix"
        return f"{kind}{min(len(bare) // 8, 8)}"
    if _IP_LIKE.fullmatch(bare):
        return "ip" if all(int(p) < 256 for p in _NUMBERS.findall(bare)[:4]) else "no ip"
    digits = _digits(bare)
    if len(digits) >= 12 and len(digits) + 4 >= len(bare):
        rest = "".join(dict.fromkeys(c for c in bare if not c.isdigit()))
        return f"long{min(len(digits), 20)}{rest}{'ok' if luhn(digits) else ''}"
    out = []
    for run in runs:
        c, n = run[0], len(run)
        if "0" <= c <= "9":
            out.append(f"d{n}" if n < 6 else f"d+{min(n, 20) // 4}")
        elif c.isalpha():
            out.append("x" if run.islower() else "X" if run.isupper() else "Xx")
        else:
            out.append(c)
    return "".join(out)


def _rest(word: str) -> str:
    if "@" in word:
        return "<at>"
    if any("0" <= c <= "9" for c in word):
        return "<mixed>" if any(c.isalpha() for c in word) else "<digits>"
    return "<word>"


# ---- labelled table ----------------------------------------------------------------------------------

def labelled_table(rows: int = 1500, seed: int = 7) -> list[tuple[list[str], list[str]]]:
    """A small table of token sequences with labels, made from patterns of writing by a seeded generator."""
    r = random.Random(seed)

    def digits(n: int) -> str:
        return "".join(r.choice("0123456789") for _ in range(n))

    def word() -> str:
        w = "".join(r.choice("aeioubdfglmnrst") for _ in range(r.randint(2, 9)))
        w = r.choices([w, w.title(), w.upper()], [10, 3, 1])[0]
        return w if r.random() < 0.8 else w + r.choice([",", ".", "!!", "###", "%%%", "$$$", "&&&", "***", ".###", ",***"])

    def check(n: int) -> str:
        """A number of n digits whose last one is its check digit."""
        body = digits(n - 1)
        return next(body + d for d in "0123456789" if luhn(body + d))

    def letters(n: int, alphabet: str) -> str:
        return "".join(r.choice(alphabet) for _ in range(n))

    def secret() -> str:
        low, many = "0123456789abcdef", "abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789"
        n = r.choice([16, 24, 32, 40, 40, 40, 48, 64])
        value = r.choice([letters(n, low), letters(n, low), letters(n, low.upper()), letters(n, many), "sk-" + letters(n, many),
                          letters(16, many).upper() + letters(4, "0123456789"), letters(n, many + "+/") + "="])
        return r.choice([f'"{value}"', value, f"'{value}'"])

    def asked() -> str:
        cue = r.choice([*_CUES["secret"], *[c.upper() for c in _CUES["secret"]]])
        return r.choice([f"{cue} =", f"{cue}:", f"{cue}", f"{cue} ="])

    def email() -> str:
        user = r.choice([word(), f"{word()}.{word()}", f"{word()}{digits(2)}", f"{word()}.{digits(2)}"]).lower()
        site, end = r.choice([word(), f"mail{digits(1)}"]).lower(), r.choice(["com", "org", "net", "example.com"])
        return r.choice([f"{user}@{site}.{end}", f"{user} [at] {site}.{end}", f"{user}(at){site}.{end}",
                         f"{user} [at] {site} [dot] {end}", f"{user} (at) {site} (dot) {end}"])

    def ip() -> str:
        parts = [str(r.randint(0, 255)) for _ in range(4)]
        return r.choice([".".join(parts), ".".join(parts) + ":" + digits(4), "[.]".join(parts)])

    def card() -> str:
        number = check(16)
        groups = [number[k : k + 4] for k in range(0, 16, 4)]
        return r.choice([" ".join(groups), "-".join(groups), "".join(groups), ".".join(groups), "/".join(groups)])

    def phone() -> str:
        a, b, c = digits(3), digits(3), digits(4)
        return r.choice([f"+1 ({a}) {b}-{c}", f"({a}) {b}-{c}", f"{a}-{b}-{c}", f"+{digits(2)} {a} {b} {c}",
                         f"0{a}/{b}{c}", f"{a}.{b}.{c}", f"00{digits(2)} {a} {b} {c}", f"({a}) {b} {c}"])

    def neutral() -> str:
        return r.choice([digits(r.randint(1, 8)), f"{digits(2)}.{digits(2)}", f"v{digits(1)}.{digits(1)}.{digits(1)}",
                         f"20{digits(2)}-{digits(2)}-{digits(2)}", f"{digits(2)}:{digits(2)}", f"${digits(3)}.{digits(2)}",
                         f"{digits(3)}%", f"#{digits(5)}", f"{digits(4)}-{digits(4)}", f"({digits(4)})", f"({digits(1)})",
                         f'"{digits(6)}{word().lower()}{digits(5)}"', f"{digits(1)},{digits(3)}", digits(r.randint(9, 30)),
                         f"@{word()}", f"{word()}###", f"{word()}$$$", f"{word()}%%%", "|", "=", f"{word()}-{word()}",
                         f"{digits(2)}/{digits(2)}/{digits(4)}", f"{word()}{digits(2)}", f"[{word()}]", f"({word()})",
                         wrong(16), wrong(16), wrong(13), f"commit {letters(40, '0123456789abcdef')}", f"ISBN 978-{digits(1)}-{digits(4)}-{digits(4)}-{digits(1)}",
                         f"{r.randint(256, 999)}.{r.randint(256, 999)}.{digits(3)}.{digits(2)}", f"{r.choice(_CUES['secret'])} {word()}",
                         f"{r.choice(_CUES['phone'])} {word()}", f"{r.choice(_CUES['card'])} {word()}", f"{word()}_{word()}_{digits(2)}",
                         f"https://{word().lower()}.org/{word().lower()}/{digits(3)}"])

    def wrong(n: int) -> str:
        while luhn(number := digits(n)):
            pass
        return r.choice([number, number, ".".join(number[k : k + 4] for k in range(0, n, 4))])

    make = {"email": email, "ip": ip, "card": card, "phone": phone, "secret": secret}
    out = []
    for _ in range(rows):
        tokens, labels = [], []

        def add(text: str, kind: str | None = None, tokens: list[str] = tokens, labels: list[str] = labels) -> None:
            for k, t in enumerate(text.split()):
                tokens.append(t)
                labels.append("O" if kind is None else f"{'I' if k else 'B'}-{kind}")

        for _ in range(r.randint(0, 6)):
            add(neutral() if r.random() < 0.25 else word())
        for _ in range(r.choice([0, 1, 1, 2])):
            kind = r.choice(KINDS)
            if kind == "secret":  # the value alone could be any number or digest
                add(asked())
            elif r.random() < 0.5:
                add(r.choice(_CUES[kind]))
            add(make[kind]() + r.choice(["", "", "", ".", ",", "###", "***", "&&&", "!!"]), kind)
            for _ in range(r.randint(1, 5)):
                add(neutral() if r.random() < 0.25 else word())
        if tokens:
            out.append((tokens, labels))
    return out


# ---- the random field --------------------------------------------------------------------------------


#: Places beside a token whose shapes are its features.
OFFSETS = (-2, -1, 0, 1)


@dataclass
class Field:
    """Shape numbers; weights by OFFSETS, shape and label; transition and start weights."""

    shapes: dict[str, int]
    weights: np.ndarray
    moves: np.ndarray
    starts: np.ndarray

    def number(self, word: str) -> int:
        found = self.shapes.get(shape(word))
        return self.shapes[_rest(word)] if found is None else found

    def emissions(self, numbers: np.ndarray, places: np.ndarray, lengths: np.ndarray) -> np.ndarray:
        """Label weights of each token; places and lengths: each token's place in its sequence, and that one's length."""
        none, out = self.shapes["<none>"], 0.0
        for k, offset in enumerate(OFFSETS):
            near = np.roll(numbers, -offset)
            if offset:
                there = places + offset
                near[(there < 0) | (there >= lengths)] = none
            out = out + self.weights[k][near]
        return out


def _pad(rows: list[list[int]]) -> tuple[np.ndarray, np.ndarray]:
    lengths = np.array([len(r) for r in rows])
    out = np.zeros((len(rows), lengths.max(initial=1)), np.int64)
    for k, row in enumerate(rows):
        out[k, : len(row)] = row
    return out, np.arange(out.shape[1]) < lengths[:, None]


@lru_cache(maxsize=2)
def train(rows: int = 1500, seed: int = 7, steps: int = 150, rate: float = 0.15, decay: float = 1e-3) -> Field:
    """Adam on the mean negative log likelihood of the labelled table."""
    data = labelled_table(rows, seed)
    counts = Counter(shape(t) for tokens, _ in data for t in tokens)
    known = [s for s, n in sorted(counts.items()) if n >= 2]
    field = Field({s: i for i, s in enumerate([*_REST, *known])}, np.zeros(0), np.zeros(0), np.zeros(0))
    n_shapes, n_labels = len(field.shapes), len(LABELS)
    x, mask = _pad([[field.number(t) for t in tokens] for tokens, _ in data])
    y, _ = _pad([[LABELS.index(v) for v in labels] for _, labels in data])
    none, (n, length) = field.shapes["<none>"], x.shape
    views = []
    for offset in OFFSETS:
        there = np.arange(length) + offset
        inside = (there >= 0) & (there < mask.sum(1)[:, None])
        views.append(np.where(inside, x[:, there.clip(0, length - 1)], none))
    theta = [np.zeros((len(OFFSETS), n_shapes, n_labels)), np.zeros((n_labels, n_labels)), np.zeros(n_labels)]
    onehot = np.eye(n_labels)[y] * mask[..., None]
    gold = [None, np.einsum("nti,ntj->ij", onehot[:, :-1], onehot[:, 1:]), onehot[:, 0].sum(0)]
    moments = [(np.zeros_like(t), np.zeros_like(t)) for t in theta]
    for step in range(1, steps + 1):
        w, moves, starts = theta
        e = sum(w[k][v] for k, v in enumerate(views))
        expm = np.exp(moves)
        alpha, scale = np.zeros((n, length, n_labels)), np.ones((n, length))
        ee = np.exp(e - e.max(axis=2, keepdims=True)) * mask[..., None]
        a = ee[:, 0] * np.exp(starts)
        for t in range(length):
            if t:
                a = np.where(mask[:, t, None], (alpha[:, t - 1] @ expm) * ee[:, t], alpha[:, t - 1])
            scale[:, t] = a.sum(1)
            alpha[:, t] = a / scale[:, t, None]
        beta = np.ones((n, length, n_labels))
        pairs = np.zeros((n_labels, n_labels))
        for t in range(length - 2, -1, -1):
            live = mask[:, t + 1, None]
            ahead = ee[:, t + 1] * beta[:, t + 1] / scale[:, t + 1, None]
            beta[:, t] = np.where(live, ahead @ expm.T, beta[:, t + 1])
            pairs += np.einsum("ni,nj->ij", alpha[:, t] * live, ahead * live) * expm
        prob = alpha * beta
        prob = prob / prob.sum(axis=2, keepdims=True) * mask[..., None]
        diff = (prob - onehot).reshape(-1, n_labels)
        grad_w = np.zeros_like(w)
        for k in range(len(OFFSETS)):
            for label in range(n_labels):
                grad_w[k][:, label] = np.bincount(views[k].ravel(), diff[:, label], n_shapes)
        grads = [grad_w, pairs - gold[1], prob[:, 0].sum(0) - gold[2]]
        for k, grad in enumerate(grads):
            grad = grad / n + decay * theta[k]
            m, v = moments[k]
            m += 0.1 * (grad - m)
            v += 0.01 * (grad * grad - v)
            theta[k] = theta[k] - rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)
    field.weights, field.moves, field.starts = theta
    return field


def viterbi(field: Field, numbers: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Best labels of the tokens of many sequences, which lie one behind the other."""
    out = np.zeros(len(numbers), np.int8)
    starts = np.concatenate([[0], np.cumsum(lengths)[:-1]])
    places, sizes = np.arange(len(numbers)) - np.repeat(starts, lengths), np.repeat(lengths, lengths)
    order = np.argsort(-lengths, kind="stable")
    starts, lengths = starts[order], lengths[order]
    e = field.emissions(numbers, places, sizes)
    longest = int(lengths[0])
    live = np.searchsorted(-lengths, -np.arange(1, longest + 1), side="right")  # sequences longer than t
    came = np.zeros(e.shape, np.int8)
    score = e[starts] + field.starts
    best = np.zeros(len(starts), np.int8)
    moves = np.ascontiguousarray(field.moves.T)
    for t in range(1, longest + 1):
        n = live[t] if t < longest else 0
        best[n : live[t - 1]] = score[n : live[t - 1]].argmax(axis=1)
        if not n:
            break
        ways = score[:n, None, :] + moves
        at = starts[:n] + t
        back = ways.argmax(axis=2)
        came[at] = back
        score[:n] = np.take_along_axis(ways, back[..., None], 2)[..., 0] + e[at]
    out[starts + lengths - 1] = best
    for t in range(longest - 1, 0, -1):
        at = starts[: live[t]] + t
        out[at - 1] = came[at, out[at]]
    return out


class Finder:
    """All spans of texts; keeps the shape numbers of tokens it has met, within a bound."""

    KEPT = 300_000

    def __init__(self, field: Field):
        self.field, self.known = field, {}

    def _numbers(self, words: list[str]) -> list[int]:
        known, number = self.known, self.field.number
        try:
            return [known[w] for w in words]
        except KeyError:
            if len(known) > self.KEPT:
                known.clear()
            known.update((w, number(w)) for w in set(words) if w not in known)
            return [known[w] for w in words]

    def added(self, texts: list[str]) -> list[list[Span]]:
        """The field's spans of each text."""
        numbers, lengths, lines = [], [], []
        for k, text in enumerate(texts):
            at = 0
            for line in text.split("\n"):
                words = line.split()
                if words:
                    numbers.append(self._numbers(words))
                    lengths.append(len(words))
                    lines.append((k, at, line))
                at += len(line) + 1
        out: list[list[Span]] = [[] for _ in texts]
        if not lines:
            return out
        flat = np.fromiter((v for row in numbers for v in row), np.int64, sum(lengths))
        labels = viterbi(self.field, flat, np.array(lengths))
        cuts = np.concatenate([[0], np.cumsum(lengths)])
        for i in np.unique(np.searchsorted(cuts, np.flatnonzero(labels), side="right") - 1):
            k, at, line = lines[i]
            places = [m.span() for m in re.finditer(r"\S+", line)]
            out[k].extend(self._line(line, at, places, labels[cuts[i] : cuts[i + 1]]))
        return out

    def _line(self, line: str, at: int, places: list[tuple[int, int]], labels: np.ndarray) -> Iterator[Span]:
        t = 0
        while t < len(labels):
            if not labels[t]:
                t += 1
                continue
            kind, u = (int(labels[t]) - 1) // 2, t + 1
            while u < len(labels) and labels[u] == 2 * kind + 2:
                u += 1
            start, stop = places[t][0], places[u - 1][1]
            while stop > start and line[stop - 1] in _NOISE:
                stop -= 1
            while start < stop and line[start] in _EDGE:
                start += 1
            if start < stop:
                yield at + start, kind, at + stop
            t = u

    def spans(self, texts: list[str]) -> list[tuple[list[Span], list[Span]]]:
        """(base spans, all spans) of each text, by start and then kind."""
        out = []
        for text, new in zip(texts, self.added(texts), strict=True):
            base = base_spans(text)
            free = [s for s in new if all(s[2] <= b[0] or b[2] <= s[0] for b in base)]
            out.append((base, sorted({*base, *free})))
        return out


def _joined(spans: list[Span]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans)


SCHEMA = (
    "doc_id bigint, n_email bigint, n_ip bigint, n_card bigint, n_phone bigint, base_sha256 string, spans string, "
    "n_added bigint, n_spans bigint"
)


def span_scores(field: Field, data: list[tuple[list[str], list[str]]]) -> dict[str, tuple[float, float]]:
    """(precision, recall) of whole spans of each kind on labelled sequences."""

    def spans(labels: list[str]) -> set[tuple[str, int, int]]:
        out, t = set(), 0
        while t < len(labels):
            kind, u = labels[t][2:], t + 1
            while kind and u < len(labels) and labels[u] == f"I-{kind}":
                u += 1
            if kind:
                out.add((kind, t, u))
            t = u
        return out

    right, found, there = Counter(), Counter(), Counter()
    for tokens, labels in data:
        got = viterbi(field, np.array([field.number(t) for t in tokens]), np.array([len(tokens)]))
        mine, truth = spans([LABELS[i] for i in got]), spans(labels)
        found.update(k for k, *_ in mine)
        there.update(k for k, *_ in truth)
        right.update(k for k, *_ in mine & truth)
    return {k: (right[k] / max(found[k], 1), right[k] / max(there[k], 1)) for k in KINDS}


def find(docs: DataFrame, field: Field | None = None) -> DataFrame:
    """A row per row of ``docs`` with its counts of base spans, their digest, and all spans."""
    field = field or train()

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        finder = Finder(field)
        for batch in batches:
            for at in range(0, len(batch), 256):
                part = batch.iloc[at : at + 256]
                found = finder.spans([t or "" for t in part["text"]])
                counts = np.array([[sum(s[1] == k for s in base) for k in range(len(BASE))] for base, _ in found])
                out = {"doc_id": part["doc_id"].to_numpy()}
                out |= {f"n_{kind}": counts[:, k] for k, kind in enumerate(BASE)}
                out["base_sha256"] = [hashlib.sha256(_joined(base).encode()).hexdigest() for base, _ in found]
                out["spans"] = [_joined(every) for _, every in found]
                out["n_added"] = [len(every) - len(base) for base, every in found]
                out["n_spans"] = [len(every) for _, every in found]
                yield pd.DataFrame(out).astype({"doc_id": "Int64"})

    return docs.select("doc_id", "text").mapInPandas(run, SCHEMA)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find(table(spark, sf_dir, "documents"))
