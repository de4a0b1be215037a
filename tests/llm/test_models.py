"""The learned operators against plain Python: lattices by enumeration, trainers by dense references, whole queries by recomputation."""

import itertools
import math
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from pathtwin.llm import language_id, rule_ensemble, toxicity

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def _out(text, n, rest):
    return zlib.crc32(str(text).encode()) % n == rest


@pytest.fixture(scope="module")
def corpus(spark):
    rng = random.Random(5)
    plain = ["river", "stone", "Music", "été", "Über"] + ["".join(rng.choice("abdegiklnorstu") for _ in range(6)) for _ in range(600)]
    bad = ["moron", "idiot", "m0r0n", "1d10t", "l.o.s.e.r", "loooser"]
    rows, labels = [], []
    for i in range(240):
        toxic, good = int(i % 5 == 0), int(i % 3 > 0)
        words = [rng.choice(plain) for _ in range(rng.randint(5, 40))]
        if toxic:
            words[2:2] = rng.sample(bad, 2)
        if not good:
            words = [w.upper() + "!!" for w in words]
        lang = ("en", "de", None)[i % 3]
        text = (" " if lang != "de" else " und der ").join(words)
        rows.append((i, text, lang, "s", len(text)))
        labels.append((i, good if i % 11 else None, toxic if i % 13 else None))
    rows += [(300, None, "en", "s", 0), (301, "", "de", "s", 0), (302, "12 34 !!", "en", "s", 8)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").repartition(3)
    return rows, labels, docs, spark.createDataFrame(labels, "doc_id long, quality int, toxic int")


@pytest.mark.parametrize("span", ["1d10t", "l.o.s.e.r", "cl0wwwn", "a--b", "$h1t", "x", "88", "so  so", "Ää1a", "****", "a.b|c"])
def test_viterbi_finds_the_best_of_all_paths(span):
    model = toxicity.CharModel(toxicity.char_counts(iter(["the loser is a clown and an idiot, so so shy bats"] * 9)))
    edges, n = list(toxicity.lattice(span)), len(span.lower())

    def ways(at):
        if at == n:
            yield (), 0.0
        for i, j, out, cost in edges:
            if i == at:
                for rest, more in ways(j):
                    yield (*out, *rest), cost + more

    def score(symbols, cost):
        a = c = 0
        total, kept = -cost, []
        for x in symbols:
            if x or c:
                total += model.log[a][c][x]
                a, c = c, x
                kept.append(x)
        return total + (model.log[a][c][0] if c else 0.0), "".join(" " if x == 0 else chr(96 + x) for x in kept).strip()

    best = max(score(*w) for w in ways(0))[0]
    assert toxicity.decode(span, model) in {text for total, text in (score(*w) for w in ways(0)) if abs(total - best) < 1e-9}


def _lexicon(rows):
    """The lexicon by its definition: votes of word sets, one a family and label."""
    sides, votes = {0: set(), 1: set()}, {}
    for words, y in rows:
        family = (min(map(toxicity.hash_word, words), default=0), y)
        sides[y].add(family)
        for w in words:
            for t in (w, *(w[:n] + "-" for n in toxicity.BEGINNINGS if len(w) > n)):
                votes.setdefault(t, set()).add(family)
    out = {}
    for t, families in votes.items():
        bad = sum(y for _, y in families)
        ratio = math.log((bad + 0.5) / (len(sides[1]) + 1)) - math.log((len(families) - bad + 0.5) / (len(sides[0]) + 1))
        if bad >= max(toxicity.VOTES, 0.004 * len(sides[1])) and ratio > 2.5:
            out[t] = ratio
    return out


def test_toxicity_by_recomputation(corpus):
    rows, labels, docs, table = corpus
    toxic = {i: t for i, _, t in labels if t is not None and not _out(i, 5, 0)}
    texts = {i: t for i, t, *_ in rows}
    restorer = toxicity.Restorer(toxicity.char_counts(t for t in texts.values() if t))
    seen = [(restorer.words(texts[i] or ""), y) for i, y in sorted(toxic.items(), key=lambda x: -x[1])]
    lexicon, w = toxicity.learn(seen)
    want = _lexicon(seen)
    assert lexicon.keys() == want.keys() and all(abs(lexicon[t] - want[t]) < 1e-9 for t in want) and {"moron", "idiot"} & want.keys()
    x = np.array([[1.0, *toxicity.evidence(words, lexicon)] for words, _ in seen])
    y = np.array([v for _, v in seen], float)
    p = 1 / (1 + np.exp(-x @ w))
    assert np.abs(x.T @ (p - y) + np.array([1e-3, 0.05, 0.05]) * w).max() < 1e-6  # the penalised loss is at its least
    for r in toxicity.toxicity_scores(docs, table).collect():
        a, b = toxicity.evidence(restorer.words(texts[r.doc_id] or ""), lexicon)
        assert abs(r.score - 1 / (1 + math.exp(-(w[0] + w[1] * a + w[2] * b)))) < 1e-9
        assert r.held_out == _out(r.doc_id, 5, 0) and r.predicted == int(r.score >= 0.5)
    with pytest.raises(ValueError):
        toxicity.learn([({"a"}, 0), ({"b"}, 1)])


def test_ftrl_against_a_dense_reference():
    rng = np.random.default_rng(1)
    model = language_id.Ftrl(3, 16)
    z, n = np.zeros((16, 3)), np.zeros((16, 3))
    for _ in range(200):
        x, y = rng.random(16) * (rng.random(16) < 0.4), int(rng.integers(3))
        at = np.flatnonzero(x)
        model.learn(at, x[at], y)
        w = np.zeros((16, 3))
        for i, k in itertools.product(range(16), range(3)):
            if abs(z[i, k]) > model.l1:
                w[i, k] = -(z[i, k] - math.copysign(model.l1, z[i, k])) / ((model.beta + math.sqrt(n[i, k])) / model.alpha + model.l2)
        logits = [sum(x[i] * w[i, k] for i in range(16)) for k in range(3)]
        top = max(logits)
        p = [math.exp(v - top) / sum(math.exp(u - top) for u in logits) for v in logits]
        for i, k in itertools.product(range(16), range(3)):
            g = x[i] * (p[k] - (k == y))
            z[i, k] += g - (math.sqrt(n[i, k] + g * g) - math.sqrt(n[i, k])) / model.alpha * w[i, k]
            n[i, k] += g * g
    assert np.allclose(model.z, z) and np.allclose(model.n, n)
    assert (model.weights(slice(None)) == 0).any()  # the first penalty leaves weights at zero


def test_temperature_is_the_best_of_the_grid_on_final_weights(corpus):
    rows = [(t, lang) for _, t, lang, *_ in corpus[0] if t and lang]
    idf = np.ones(1 << 15)
    table, temperature = language_id.train(iter(rows), idf, ["de", "en"])
    kept = [r for k, r in enumerate(rows) if k % 10 == 9]
    z = np.stack([(lambda at, x: (x / language_id.GAIN) @ table[at])(*language_id.row_of(t, idf)) for t, _ in kept])
    y = [("de", "en").index(lang) for _, lang in kept]
    losses = []
    for t in language_id.TEMPERATURES:
        losses.append(sum(math.log(sum(math.exp((v - max(r)) / t) for v in r)) - (r[k] - max(r)) / t for r, k in zip(z.tolist(), y, strict=True)) / len(y))
    found = losses[int(np.argmin(np.abs(language_id.TEMPERATURES - temperature)))]
    assert found <= min(losses) + 1e-6


def test_languages_by_recomputation(spark, corpus):
    rows, _, docs, _ = corpus
    known = [(i, t, lang) for i, t, lang, *_ in rows if not _out(i, 4, 2) and lang is not None and t is not None]
    marks = [{int(b) for g in language_id.grams(t) for b in g} if t else set() for _, t, _ in known]
    df = np.zeros(1 << 15)
    for m in marks:
        df[list(m)] += 1
    idf = np.log((1 + len(known)) / (1 + df)) + 0.2
    order = {r.i: r.h for r in spark.createDataFrame([(i,) for i, *_ in known], "i long").select("i", F.xxhash64("i").alias("h")).collect()}
    stream = [(t, lang) for i, t, lang in sorted(known, key=lambda r: order[r[0]])]
    table, temperature = language_id.train(iter(stream), idf, ["de", "en"])
    texts = {i: t for i, t, *_ in rows}
    for r in language_id.identify(docs).collect():
        text = texts[r.doc_id]
        assert r.held_out == _out(r.doc_id, 4, 2)
        if not text or not any(map(str.isalpha, text)):
            assert (r.lang_pred, r.score) == ("und", 1.0)
            continue
        every = np.concatenate(list(language_id.grams(text)))
        p = language_id.softmax(table[every].mean(0) / temperature)
        assert r.lang_pred == ("de", "en")[int(p.argmax())] and abs(r.score - p.max()) < 1e-4


def test_languages_are_never_dropped(spark):
    """More languages than one table is wide: buckets shrink, labels don't."""
    assert language_id.bits_for(256) == 15 and language_id.bits_for(257) == 14 and language_id.bits_for(1025) == 12
    rows = [(i, f"word{i % 300} tail{i % 300}", f"l{i % 300:03d}") for i in range(900)]
    got = language_id.identify(spark.createDataFrame(rows, "doc_id long, text string, lang string")).collect()
    assert len(got) == 900 and len({r.lang_pred for r in got}) > 256


def _features(text):
    t = text or ""
    w = WORD.findall(t)
    lines = [x for x in t.split("\n") if WORD.search(x)]
    grams = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
    many = {g for g in grams if grams.count(g) > 1}
    rep = len({i + k for i, g in enumerate(grams) if g in many for k in range(5)})
    wc, n = sum(map(len, w)), len(w)
    share = lambda a, b: a / b if b else 0.0
    count = lambda ok: sum(1 for c in t if ok(c))
    blank = set(" \t\n\x0b\x0c\r")
    return (
        math.log1p(n), share(wc, n), share(count(lambda c: c in "#*$%&|<>"), wc), share(count(str.isupper), wc), share(count(lambda c: c in "0123456789"), wc),
        share(count(lambda c: not c.isalpha() and not c.isnumeric() and c not in blank), wc), share(len(lines) - len(set(lines)), len(lines)), share(rep, n), share(len(set(w)), n),
        share(n, len(lines)), share(count(lambda c: c in "!?"), wc), share(sum(len(x) > 15 for x in w), n),
    )


def test_quality_by_recomputation(corpus):
    rows, labels, docs, table = corpus
    x = {i: _features(t) for i, t, *_ in rows}
    seen = sorted(i for i, q, _ in labels if q is not None and not _out(i, 3, 1))
    quality = {i: q for i, q, _ in labels}
    model = rule_ensemble.fit_rules(np.array([x[i] for i in seen]), np.array([float(quality[i]) for i in seen]))
    assert model.rules
    want = dict(zip(x, model.predict(np.array(list(x.values()))), strict=True))
    got = rule_ensemble.quality_scores(docs, table).collect()
    for r in got:
        assert np.allclose([r[f] for f in rule_ensemble.FEATURES], x[r.doc_id])
        assert abs(r.score - want[r.doc_id]) < 1e-9 and r.held_out == _out(r.doc_id, 3, 1)
    assert len(got) == len(rows)


def test_rules_compile_to_what_they_predict(spark):
    rng = np.random.default_rng(3)
    x = rng.random((500, len(rule_ensemble.FEATURES)))
    y = ((x[:, 0] > 0.6) & (x[:, 3] <= 0.5) | (x[:, 5] > 0.9)).astype(float)
    model = rule_ensemble.fit_rules(x, y)
    df = spark.createDataFrame([tuple(map(float, r)) for r in x], list(rule_ensemble.FEATURES))
    got = np.array([r[0] for r in df.select(model.column()).collect()])
    assert np.allclose(got, model.predict(x)) and ((got >= 0.5) == (y == 1)).mean() > 0.95
    assert any(len(terms) > 1 for terms, _ in model.rules)
    constant = rule_ensemble.fit_rules(np.zeros((40, 12)), np.array([0.0, 1.0] * 20))
    assert not constant.rules and abs(constant.predict(np.zeros((1, 12)))[0] - 0.5) < 0.05
