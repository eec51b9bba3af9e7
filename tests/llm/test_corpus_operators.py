"""Corpus operators against brute force, exact round trips and held-out accuracy, and their edge cases."""

import collections
import hashlib
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from fedgrid.llm import (
    chat_format,
    decontamination,
    fingerprints,
    jaccard_join,
    language_id,
    line_dedup,
    mixing,
    pii,
    quality,
    registry,
    substring_dedup,
)
from fedgrid.llm.common import crc_mod

DOCS = "doc_id bigint, text string, lang string, source string, n_chars bigint, extra string"


def docs_of(spark, texts):
    rows = [(i, t, "en", "s", None if t is None else len(t), "x") for i, t in texts]
    return spark.createDataFrame(rows, DOCS)


@pytest.fixture(scope="module")
def odd(spark):
    """Null, empty, blank, very long, repeated rows, a null id."""
    long = " ".join(f"word{i % 977} and more." for i in range(60_000))
    return docs_of(spark, [(1, None), (2, ""), (3, " \n \n"), (4, long), (5, "same text here. And again."),
                           (5, "same text here. And again."), (None, "no id. None at all."), (7, "..."), (8, "ß é 漢字 😀 z")])


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], DOCS)


def given(spark, sf, name="documents"):
    return spark.read.parquet(f"{sf}/{name}.parquet")


# ---- 1 language ID


def test_forward_sums_all_segmentations():
    pieces = ("a", "ab", "b", "ba", "▁a")
    lattice = language_id.Lattice(["aba"], language_id.prefixes(pieces))
    p = np.array([0.3, 0.2, 0.25, 0.15, 0.1, 1e-9])
    by_hand = p[0] * p[2] * p[0] + p[1] * p[0] + p[0] * p[3] + p[4] * p[2] * p[0] + p[4] * p[3]
    assert np.exp(lattice.logs(np.array([p, p / 2]).T)[0, 0]) == pytest.approx(by_hand)
    used = lattice.expected(p, np.array([1.0]))
    assert (used[:-1] * [1, 2, 1, 2, 1]).sum() == pytest.approx(3.0)  # letters covered


def test_language_held_out_accuracy_and_edges(spark, sf, odd, none):
    got = language_id.query(spark, sf).join(given(spark, sf).select("doc_id", "lang"), "doc_id")
    row = got.where("held_out").agg(F.avg((F.col("lang_pred") == F.col("lang")).cast("int")), F.count("*")).first()
    assert row[0] > 0.95 and row[1] > 20
    assert got.where((F.col("score") < 0) | (F.col("score") > 1)).count() == 0
    kept = language_id.stage(spark, odd, sf)
    assert kept.columns == odd.columns and {r.doc_id for r in kept.collect()} == {4, 5, None, 8}
    assert language_id.stage(spark, none, sf).count() == 0


# ---- 2 mixing


def test_mixing_reaches_targets(spark, sf, odd, none):
    out = mixing.query(spark, sf)
    reached = out.agg(*[F.sum(F.col("tokens") * F.col("rate") * F.col(f"p_{d}")) for d in mixing.DOMAINS], F.sum("tokens")).first()
    for d, v in zip(mixing.DOMAINS, reached, strict=False):
        assert v / reached[3] == pytest.approx(mixing.TARGETS[d], abs=0.01)
    assert out.where("rate < 0").count() == 0
    labels = given(spark, sf, "labels")
    assert mixing.mix(odd, labels.limit(0)).count() == odd.count()
    assert mixing.mix(none, labels).count() == 0


def test_rates_match_a_dense_solver(spark):
    rng = np.random.default_rng(0)
    p = rng.dirichlet([0.3, 0.3, 0.3], 40)
    t = rng.integers(1, 50, 40)
    rows = [(int(n), *map(float, q)) for n, q in zip(t, p, strict=True)]
    df = spark.createDataFrame(rows, "__tokens int, " + ", ".join(f"__p_{d} double" for d in mixing.DOMAINS))
    history = mixing.fit_rates(df, mixing.TARGETS, rounds=80, tolerance=1e-9)
    got = [r[0] for r in df.select(mixing.rate_of(history, 1e-3)).collect()]
    w, s = np.array(list(mixing.TARGETS.values())), (t[:, None] * p).sum(0) / t.sum()
    by_id = df.select("__tokens", *[f"__p_{d}" for d in mixing.DOMAINS]).collect()
    t, p = np.array([r[0] for r in by_id]), np.array([list(r)[1:] for r in by_id])

    def reached(r):
        return (t[:, None] * r[:, None] * p).sum(0) / t.sum()

    def objective(r):
        return 0.5 * ((reached(r) - w) ** 2 / s).sum() + 5e-4 * (t / t.sum() * (r - 1) ** 2).sum()

    r = np.ones(40)
    for _ in range(20_000):
        r = np.maximum(0, r - (p @ ((reached(r) - w) / s) + 1e-3 * (r - 1)) / (1 + 1e-3))
    assert objective(np.array(got)) <= objective(r) + 1e-4 and min(got) >= 0


def test_posteriors_do_not_sink_with_length(spark):
    clean = "the river runs through a quiet valley where people grow apples and bread is baked each day "
    texts = [(k, clean + f"and year {k} was good") for k in range(20)]
    texts += [(k, clean + "awful vile awful nasty vile") for k in range(20, 40)]
    docs = docs_of(spark, texts + [(50, texts[30][1]), (51, " ".join([texts[30][1]] * 50)), (52, " ".join([texts[3][1]] * 50))])
    labels = spark.createDataFrame([(k, 1, int(k >= 20)) for k in range(40)], "doc_id bigint, quality int, toxic int")
    got = {r.doc_id: r for r in mixing.mix(docs, labels).collect()}
    assert got[51].tokens == 50 * got[50].tokens
    assert got[50].p_toxic > 0.9 and got[51].p_toxic == pytest.approx(got[50].p_toxic, abs=0.02)
    assert got[52].p_toxic == pytest.approx(got[3].p_toxic, abs=0.02)


# ---- 3 decontamination


def test_benchmark_leaks(spark, none):
    item = "Mr Alan had 3 apples and 4 pears, so Alan gave 3 apples to the woman in town over 5 km away today."
    again = "Yes. Mr Bob had 7 apples and 8 pears, so Bob gave 7 apples to the woman in town over 6 km away today. ok"
    wrong = again.replace("gave 7", "gave 8")
    docs = docs_of(spark, [(10, again), (11, wrong), (12, None), (13, "x " + item), (13, "x " + item), (14, item[:30])])
    bench = spark.createDataFrame([(1, item), (1, item), (2, None), (3, "two"), (4, "")], "item_id bigint, text string")
    got = {(r.doc_id, r.item_id, r.exact) for r in decontamination.leaks(docs, bench).collect()}
    assert got == {(10, 1, False), (13, 1, True)}
    assert decontamination.leaks(none, bench).count() == 0
    assert decontamination.leaks(docs, bench.limit(0)).count() == 0


def test_leaks_wherever_they_stand(spark):
    items = ["To mend the old boat he needs some rope", "Big dogs run", "Alan had 3 pears and gave 2 to the woman in town near the old river",
             "12 + 30 * 4 - 7 = 125", "Convert 5 km, 7 kg, 9 cm, 11 mm, 13 g and 15 ml", "forty two"]
    bench = spark.createDataFrame(list(enumerate(items)), "item_id bigint, text string")
    docs = [f"then estionha {t} and so on" for t in items]
    docs += ["So. " + items[2].replace("Alan", "Bob").replace("3", "8"), "well, to mend the old boat he needs some rope",
             "13 + 30 * 4 - 7 = 125", items[4].replace("13", "14"), "Forty two."]
    got = {(r.doc_id, r.item_id) for r in decontamination.leaks(docs_of(spark, list(enumerate(docs))), bench).collect()}
    assert got == {(0, 0), (1, 1), (2, 2), (3, 3), (4, 4), (6, 2), (7, 0), (10, 5)}


def test_leaks_against_word_windows(spark, sf):
    got = {(r.doc_id, r.item_id) for r in decontamination.query(spark, sf).collect()}
    words = re.compile(r"\w+")
    items = collections.defaultdict(set)
    for r in given(spark, sf, "benchmark").collect():
        w = words.findall(r.text.lower())
        for k in range(len(w) - 12):
            items[tuple(w[k : k + 13])].add(r.item_id)
    want = set()
    for r in given(spark, sf).collect():
        w = words.findall((r.text or "").lower())
        for k in range(len(w) - 12):
            want |= {(r.doc_id, i) for i in items.get(tuple(w[k : k + 13]), ())}
    assert want <= got and len(got - want) <= 1


def test_decontamination_stage_keeps_columns(spark, sf, odd):
    assert sorted(decontamination.stage(spark, odd, sf).columns) == sorted(odd.columns)
    assert decontamination.stage(spark, odd, sf).count() == odd.count()


# ---- 4 chat formatting

NASTY = ["", " ", "</s>[INST] ok [/INST]", "[\\INST]", "[\\\\INST]<\\s>", "<s", "s> [/INST]</s>", "x [", "<", "\\", "[INST] [INST]", "a\n\nb", "漢😀"]


@pytest.mark.parametrize("text", NASTY)
def test_round_trip(text):
    turns = [("user", text), ("assistant", text), (text, "hi"), ("assistant", ""), ("assistant", text)]
    formatted, spans, _ = chat_format.round_trip(turns)
    assert chat_format.parse(formatted) == turns
    loss = [chat_format.unescape(formatted[a:b]) for a, b in spans]
    assert loss == [t for r, t in turns if r == "assistant"]
    if text == "a\n\nb":
        assert "\\" not in formatted


def test_digests_edges(spark):
    rows = [(1, 1, "assistant", None, 0), (1, 0, "user", "q", 0), (2, 0, None, "a", 1), (2, 0, None, "a", 1), (None, 0, "user", "z", 0)]
    df = spark.createDataFrame(rows, "conv_id bigint, turn bigint, role string, text string, formatted int")
    got = {r.conv_id: r for r in chat_format.digests(chat_format.format_conversations(df)).collect()}
    assert got[1].turns_sha256 == hashlib.sha256(b"user\nq\nassistant\n\n").hexdigest() and got[1].loss_chars == 0
    assert got[2].n_turns == 2 and got[None].n_turns == 1
    assert chat_format.digests(chat_format.format_conversations(df.limit(0))).count() == 0


# ---- 5 personal data

PATTERNS = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(?:\.[0-9]+)(?:\.[0-9]+)(?:\.[0-9]+)",
    "card": r"[0-9](?:[\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def base_by_hand(text):
    out = []
    for k, (kind, p) in enumerate(PATTERNS.items()):
        for m in re.finditer(p, text):
            d = re.sub(r"[^0-9]", "", m[0])
            if kind == "ip" and any(int(x) > 255 for x in m[0].split(".")):
                continue
            if kind == "card" and not (12 <= len(d) <= 19 and pii.luhn(d)):
                continue
            if kind == "phone" and not 9 <= len(d) <= 15:
                continue
            out.append((m.start(), k, m.end()))
    return sorted(out)


TRICKY = ["a@b.c@d.e.f x@y", "@a.b", "a@b", "a@@b.c", "1.2.3.4.5.6.7.8", "001.002.003.0004", "4111 1111-1111 1111", "+1 (017) 555-7713 1.2.3.4",
          "++12345678 9", "1" * 40, "x.y@z-.a..b@c.d", "256.1.1.1 1.1.1.1", "4111111111111111", "é@b.co é1.2.3.4", ""]


@pytest.mark.parametrize("text", TRICKY)
def test_base_patterns(text):
    assert pii.base_spans(text) == base_by_hand(text)


def test_base_patterns_random():
    r = np.random.default_rng(3)
    for _ in range(400):
        text = "".join(r.choice(list("a1.@+ -(5)\n4b"), 60))
        assert pii.base_spans(text) == base_by_hand(text)


def test_viterbi_is_the_best_path():
    field = pii.train()
    r = np.random.default_rng(0)
    lengths = np.array([3, 1, 4, 2])
    numbers = r.integers(5, len(field.shapes), lengths.sum())
    got = pii.viterbi(field, numbers, lengths)
    at = 0
    for n in lengths:
        e = field.emissions(numbers[at : at + n], np.arange(n), np.full(n, n))
        import itertools

        def score(path, e=e):
            return field.starts[path[0]] + sum(e[i, v] for i, v in enumerate(path)) + sum(field.moves[a, b] for a, b in zip(path, path[1:], strict=False))

        best = max(itertools.product(range(len(pii.LABELS)), repeat=int(n)), key=score)  # up to 11^4 paths
        assert score(tuple(got[at : at + n])) == pytest.approx(score(best))
        at += n


def test_field_on_held_out_spans():
    """Whole spans of a labelled table from another seed: half of its sequences have none, and all kinds of numbers."""
    scores = pii.span_scores(pii.train(), pii.labelled_table(800, seed=1234))
    for kind, (precision, recall) in scores.items():
        assert precision > (0.8 if kind == "email" else 0.95) and recall > (0.75 if kind == "email" else 0.95), (kind, precision, recall)


def test_field_finds_what_patterns_cannot(spark):
    secret = "0f" * 20
    texts = {1: f'and then token = "{secret}" followed', 2: f"the digest {secret} of a file", 3: "call 555.867.5309 now or pay 4111/1111/1111/1111 today",
             4: "an order 4111111111111112 and 1234.5678 of them", 5: f"PASSWORD: {secret.upper()}### end"}
    got = {r.doc_id: r.spans for r in pii.find(docs_of(spark, list(texts.items()))).collect()}
    at = texts[1].index(secret)
    assert got[1] == f"secret:{at}:{at + 40}" and got[2] == "" and got[4] == ""
    assert [x.split(":")[0] for x in got[3].split(",")] == ["phone", "card"]
    at = texts[5].index("0F")
    assert got[5] == f"secret:{at}:{at + 40}"


def test_no_secret_in_the_documents_is_missed(spark, sf):
    got = {r.doc_id: r.spans for r in pii.query(spark, sf).collect()}
    pattern = re.compile(r'token = "([0-9a-f]{40})"', re.I)
    for r in given(spark, sf).collect():
        for m in pattern.finditer(r.text or ""):
            assert f"secret:{m.start(1)}:{m.end(1)}" in got[r.doc_id].split(",")


def test_pii_edges(spark, odd, none):
    got = pii.find(odd).collect()
    assert len(got) == odd.count() and all(r.base_sha256 == hashlib.sha256(b"").hexdigest() for r in got)
    assert pii.find(none).count() == 0
    docs = docs_of(spark, [(1, "call (555) 123-4567 or mail a.b@c.org today")])
    row = pii.find(docs).first()
    assert row.n_email == 1 and row.spans == "phone:5:19,email:28:37" and row.n_added == 1


# ---- 6 quality


def test_quality(spark, sf, odd, none):
    got = quality.query(spark, sf)
    assert got.where((F.col("score") >= 0) & (F.col("score") <= 1)).count() == given(spark, sf).count()
    both = got.join(given(spark, sf, "labels"), "doc_id")
    assert both.agg(F.avg((F.col("predicted") == F.col("quality")).cast("int"))).first()[0] > 0.9
    model = quality.train(given(spark, sf), given(spark, sf, "labels"))
    scores = [r[0] for r in odd.select(quality.scorer(model)("text")).collect()]
    assert all(0 <= s <= 1 for s in scores)
    assert none.select(quality.scorer(model)("text")).count() == 0
    nothing = quality.train(given(spark, sf), given(spark, sf, "labels").limit(0))
    assert nothing.score(np.zeros((2, quality.N_FEATURES))).tolist() == [0.5, 0.5]


def test_discriminant_is_the_gaussian_ratio():
    r = np.random.default_rng(0)
    y = (r.random(4000) < 0.7).astype(int)
    x = np.where(y[:, None] == 1, r.normal(0, 1, (4000, 3)), r.normal(1.0, 2.0, (4000, 3)))
    model = quality.fit(x, y, pooling=0.0, levelling=0.0)
    p = [np.mean(y == c) for c in (0, 1)]
    logs = []
    for c in (0, 1):
        g = x[y == c]
        d = x - g.mean(0)
        cov = np.cov(g, rowvar=False)
        logs.append(np.log(p[c]) - 0.5 * np.linalg.slogdet(cov)[1] - 0.5 * np.einsum("ij,jk,ik->i", d, np.linalg.inv(cov), d))
    assert np.allclose(model.score(x), 1 / (1 + np.exp(logs[0] - logs[1])))


# ---- 7 line dedup


def test_line_dedup(spark, odd, none):
    texts = [(i, f"header\nown line {i}\n\n header \nmore {i}") for i in range(10)] + [(99, None), (100, "")]
    got = {r.doc_id: r for r in line_dedup.drop_lines(docs_of(spark, texts)).collect()}
    assert got[3].text == "own line 3\n\nmore 3" and got[3].n_dropped == 2 and got[3].n_lines == 5
    assert got[99].text is None and got[100].text == ""
    assert line_dedup.drop_lines(none).count() == 0
    assert line_dedup.drop_lines(odd).count() == odd.count()
    old, line_dedup.BROADCAST_LINES = line_dedup.BROADCAST_LINES, 0  # the path for many lines
    try:
        salted = {r.doc_id: r.text for r in line_dedup.drop_lines(docs_of(spark, texts)).collect()}
    finally:
        line_dedup.BROADCAST_LINES = old
    assert salted == {k: r.text for k, r in got.items()}


# ---- 8 substring dedup


def remove_by_hand(rows):
    seen, out = set(), {}
    for doc_id, text in sorted(rows):
        ss = substring_dedup.sentences(text)
        ws = [s.lower().split() for s in ss]
        gone = set()
        for a in range(len(ss)):
            n, b = 0, a
            while b < len(ss) and (b - a < substring_dedup.MIN_SENTENCES or n < substring_dedup.MIN_WORDS):
                n, b = n + len(ws[b]), b + 1
            if b - a < substring_dedup.MIN_SENTENCES or n < substring_dedup.MIN_WORDS or not ws[a]:
                continue
            key = " ".join(w for q in ws[a:b] for w in q)
            if key in seen:
                gone.update(range(a, b))
            seen.add(key)
        out[doc_id] = "".join(s for i, s in enumerate(ss) if i not in gone)
    return out


def test_substring_dedup(spark, sf, odd, none):
    passage = "One two three four five six. Seven eight nine ten eleven. Twelve thirteen fourteen! "
    passage += "Fifteen sixteen seventeen eighteen nineteen. Twenty one and two and three and four and five. "
    docs = [(1, "Start of one here. " + passage + "End one."), (2, passage * 2), (3, "Clean text of its own. Nothing else. At all.")]
    got = {r.doc_id: r.text for r in substring_dedup.remove_repeats(docs_of(spark, docs)).collect()}
    assert got == remove_by_hand(docs) and got[1] == docs[0][1] and got[3] == docs[2][1] and "eleven" not in got[2]
    rows = [(r.doc_id, r.text) for r in given(spark, sf).collect()]
    full = {r.doc_id: r.text for r in substring_dedup.query(spark, sf).collect()}
    assert full == remove_by_hand(rows)
    out = substring_dedup.remove_repeats(odd).collect()
    assert len(out) == odd.count() and sum(r.text == "same text here. And again." for r in out) == 2
    assert substring_dedup.remove_repeats(none).count() == 0


@pytest.mark.parametrize("text", ["", ".", "a", "a.b c.  d!?\n\n e", "\n\n", "x...y", "end. "])
def test_sentences_join_to_the_text(text):
    assert "".join(substring_dedup.sentences(text)) == text


def test_substring_dedup_finds_passages_in_mid_sentence(spark):
    rng = np.random.default_rng(8)

    def prose(n, end=0):
        return " ".join(f"w{rng.integers(10**6)}" + ("." if end and k % end == end - 1 else "") for k in range(n))

    docs, passages = [], []
    # sentences of 20 and of 26 to 40 words, none at all, and the same few words over and over
    made = [prose(n, end) for n in (51, 60, 80) for end in (20, 26, 33, 40, 0)] + ["no yes " * 25 + "no"] + ["spam " * 50 + "spam"]
    for k, passage in enumerate(made):
        passages.append(passage.split())
        docs += [(2 * k + side, f"{prose(30 + 7 * side)} {passage} {prose(40 - 9 * side)}") for side in (0, 1)]
    got = {r.doc_id: r.text.split() for r in substring_dedup.remove_repeats(docs_of(spark, docs)).collect()}
    for k, passage in enumerate(passages):
        words = dict(docs)[2 * k + 1].split()
        left = len(got[2 * k + 1]) - (len(words) - len(passage))
        assert left < len(passage) / 2, (k, left)
        own = set(words) - set(passage)
        assert own <= set(got[2 * k + 1])  # the surroundings stay
    unlike = "one two three. four five six. seven eight nine. ten. " * 3
    assert list(substring_dedup.spans(unlike)) and not list(substring_dedup.spans("one two three. four five."))


# ---- 9 n-gram Jaccard join


def components_by_hand(rows, width, percent):
    def shingles(text):
        low = (text or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))
        w = [y for y in re.split(r"[\x20\x09-\x0D]+", low) if y]
        if not w:
            return frozenset()
        return frozenset(tuple(w[i : i + width]) for i in range(max(len(w) - width + 1, 1)))

    sets = {i: shingles(t) for i, t in rows}
    parent = {i: i for i in sets}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for k, i in enumerate(ids):
        for j in ids[:k]:
            both = len(sets[i] & sets[j])
            if both and 100 * both >= percent * len(sets[i] | sets[j]):
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    return {i: (len(sets[i]), find(i)) for i in sets}


def edited(rng, words, n):
    out = list(words)
    for at in rng.integers(0, len(out), n):
        out[at] = f"new{rng.integers(1000)}"
    return out


@pytest.mark.parametrize("width,percent", [(4, 85), (5, 80), (2, 50)])
def test_jaccard_join_planted(spark, width, percent):
    """Chains of edits around the threshold, exact copies, shared passages, short texts."""
    rng = np.random.default_rng(width)
    vocabulary = [f"w{i}" for i in range(300)]
    common = list(rng.choice(vocabulary, 30))
    rows, n = [], 0
    for family in range(12):
        words = list(rng.choice(vocabulary, int(rng.integers(4, 160)))) + (common if family % 2 else [])
        for _ in range(int(rng.integers(2, 9))):
            rows.append((n, " ".join(words)))
            n += 1
            words = edited(rng, words, int(rng.integers(0, max(2, len(words) // 40))))
    rows += [(n, None), (n + 1, ""), (n + 2, "one"), (n + 3, "ONE"), (n + 4, "one two")]
    got = jaccard_join.similar_documents(docs_of(spark, rows).repartition(3), width, percent)
    assert {r.doc_id: (r.n_shingles, r.component_id) for r in got.collect()} == components_by_hand(rows, width, percent)


def test_jaccard_join_edges(spark, odd, none, sf):
    got = jaccard_join.similar_documents(odd).collect()
    assert len(got) == odd.count()
    assert [r.component_id for r in got if r.doc_id is None] == [None]
    assert all(r.component_id == r.doc_id for r in got if r.doc_id is not None)
    assert jaccard_join.similar_documents(none).count() == 0
    kept = jaccard_join.stage(spark, odd, sf)
    assert sorted(kept.columns) == sorted(odd.columns) and kept.count() == odd.count() - 1


def test_no_similar_pair_escapes_the_segments():
    """Pigeonhole: random pairs at the threshold share a probed key."""
    rng = np.random.default_rng(5)
    with np.errstate(over="ignore"):
        for _ in range(300):
            n = int(rng.integers(2, 400))
            x = np.unique(rng.integers(0, 1 << 63, n).astype(np.uint64))
            drop = int(rng.integers(0, max(1, len(x) // 6) + 1))
            y = np.unique(np.concatenate([x[drop:], rng.integers(0, 1 << 63, int(rng.integers(0, drop + 1))).astype(np.uint64)]))
            both = len(np.intersect1d(x, y))
            if np.array_equal(x, y) or 100 * both < 85 * (len(x) + len(y) - both):
                continue
            bands = jaccard_join.Bands(85)
            kx, px = jaccard_join.signatures(x, bands)
            ky, py = jaccard_join.signatures(y, bands)
            shared = set(kx[px].tolist()) & set(ky.tolist()) | set(ky[py].tolist()) & set(kx.tolist())
            assert shared
            odd = [np.bincount((v >> np.uint64(54)).astype(int), minlength=1024) & 1 for v in (x, y)]
            assert (odd[0] ^ odd[1]).sum() <= len(x) + len(y) - 2 * both


def test_word_hashes_follow_words_not_places():
    with np.errstate(over="ignore"):
        a, b = jaccard_join.shingle_sets(["One  two\tTHREE four", "one two three\x0bfour "], 4)
        assert a.tolist() == b.tolist() and len(a) == 1
        long = "alpha beta gamma delta " * 60_000  # above a block
        short = "alpha beta gamma delta " * 3
        sets = list(jaccard_join.shingle_sets([long, short, "x"], 4))
        assert sets[0].tolist() == sets[1].tolist() and len(sets[2]) == 1


# ---- 10 fingerprints


def test_fingerprints_by_hand(spark, odd, none, sf):
    got = {r.doc_id: r for r in fingerprints.query(spark, sf).collect()}
    rows = sorted(((r.doc_id, r.text or "") for r in given(spark, sf).collect()), reverse=True)
    for k, (i, text) in enumerate(rows):
        following, tail = rows[(k + 1) % len(rows)][1], len(text) // 3
        new = text[: len(text) - tail] + following[:tail]
        assert got[i].n_chars == len(text) and got[i].edited_sha256 == hashlib.sha256(new.encode()).hexdigest()
        if new == text:
            assert got[i].fingerprint == got[i].edited_fingerprint and got[i].near_edited == 1
    same = collections.defaultdict(set)
    for i, text in rows:
        same[text].add(got[i].fingerprint)
    assert all(len(v) == 1 for v in same.values()) and len({next(iter(v)) for v in same.values()}) == len(same)
    assert np.mean([r.near_edited for r in got.values()]) > np.mean([r.near_next for r in got.values()]) + 0.4


def test_fingerprints_are_multisets(spark):
    rows = docs_of(spark, [(1, "a b c\nd e f g"), (2, "d e f g\na b c"), (3, "a b c\nd e f h"), (4, "a b c"), (5, "d e f g")])
    made = fingerprints.vectors(rows, ["doc_id"]).withColumn("print", fingerprints.fingerprint())
    got = {r.doc_id: r for r in made.collect()}
    assert got[1].print == got[2].print != got[3].print
    for c in ["windows", *fingerprints._SUMS]:
        assert got[1][c] == got[4][c] + got[5][c]
    for w in fingerprints._WORDS:
        assert got[1][w] == (got[4][w] + got[5][w]) % (1 << 32)


def test_next_document_edges(spark, odd, none):
    got = fingerprints.with_next(odd).collect()
    assert len(got) == odd.count()
    following = {(r.rng, r.rn): (r.next_rng, r.next_rn) for r in got}
    at, seen = next(iter(following)), set()
    while at not in seen:
        seen.add(at)
        at = following[at]
    assert len(seen) == len(got)  # one circle through all rows
    assert fingerprints.with_next(none).count() == 0
    one = fingerprints.with_next(docs_of(spark, [(4, "abc")])).first()
    assert one.next_text == "abc"


# ---- pipeline and registry


def test_pipeline_stages(spark, sf):
    docs = given(spark, sf)
    counts = []
    for name, step in corpus_pipeline.STAGES:
        out = step(spark, docs, sf)
        if name != corpus_pipeline.STAGES[-1][0]:
            assert sorted(out.columns) == sorted(docs.columns), name
        docs = out.cache()
        counts.append(docs.count())
    assert counts == sorted(counts, reverse=True) and counts[-1] > 0.7 * given(spark, sf).count()
    assert {r.doc_id for r in corpus_pipeline.run(spark, sf).collect()} == {r.doc_id for r in docs.collect()}


def test_registry_names():
    names = registry.queries()
    assert sorted({int(re.match(r"op(\d+)_", n)[1]) for n in names}) == list(range(1, 11))
    assert set(registry.oracle_sql()) <= set(names)


def test_held_out_masks(spark):
    import zlib

    df = spark.range(200).select(F.col("id").alias("doc_id"), crc_mod("id", 5).alias("m"))
    assert all(r.m == zlib.crc32(str(r.doc_id).encode()) % 5 for r in df.collect())
