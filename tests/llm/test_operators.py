"""The ten operators against plain Python on small tables with nulls, empty texts, copies and clashing columns."""

import hashlib
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest

public_tokenizers = pytest.importorskip("public_tokenizers")

from pathtwin.llm import chat, language_id, packing, quality_rules, rule_ensemble, simhash, suffix_dedup, toxicity, vector_dedup  # noqa: E402
from pathtwin.llm.byte_bpe import TextCodec, encode_documents  # noqa: E402

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, n_words string, score string, th int"


@pytest.fixture(scope="module")
def docs(spark):
    rng = random.Random(9)
    words = ["the", "Loser", "été", "x1", "#%&", "river", "stone", "日本", "a", "of"]
    texts = [None, "", " \n\t", "one", "one two", "a b c d e a b c d e a b c d e", "same line\nsame line\n\n \nother", "x" * 3000, "é" * 700]
    texts += [" ".join(rng.choice(words) for _ in range(rng.randint(1, 80))) for _ in range(60)]
    texts += [texts[20]] * 5 + [texts[21] + " tail"]
    long = " ".join(rng.choice(words) for _ in range(5000))
    texts += [long, long[:9000] + " cut"]
    rows = [(i, t, "en" if i % 3 else None, f"s{i % 4}" if i % 5 else None, len(t or ""), "clash", "clash", 1) for i, t in enumerate(texts)]
    rows += [rows[12], (None, "no id here", None, None, 3, None, None, None)]
    return spark.createDataFrame(rows, SCHEMA).repartition(3)


@pytest.fixture(scope="module")
def labels(spark):
    return spark.createDataFrame([(i, int(i % 2), int(i % 7 == 0)) for i in range(60)] + [(3, 1, 1), (None, 1, 1)], "doc_id long, quality int, toxic int")


def _text(docs):
    return [(r.doc_id, r.text) for r in docs.collect()]


def _n_repeat(words):
    grams = Counter(tuple(words[i : i + 5]) for i in range(len(words) - 4))
    covered = {i + k for i in range(len(words) - 4) if grams[tuple(words[i : i + 5])] > 1 for k in range(5)}
    return len(covered)


def test_quality_rules(docs):
    got = Counter()
    for r in quality_rules.judge(docs).collect():
        got[r.doc_id, r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words, r.base_failed] += 1
        assert not (r.base_failed and r.kept)
    want = Counter()
    for i, t in _text(docs):
        w = WORD.findall(t or "")
        lines = [x for x in (t or "").split("\n") if WORD.search(x)]
        rep = _n_repeat(w)
        want[i, len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t or ""), len(lines) - len(set(lines)), rep, len(w) < 10 or 100 * rep > 20 * len(w)] += 1
    assert got == want


def test_host_with_many_failures_is_rejected_and_a_small_one_is_not(spark):
    rows = [(i, "bad", i >= 95) for i in range(100)] + [(100 + i, f"good{i % 9}", False) for i in range(900)]
    stats = spark.createDataFrame([(i, h, not ok if h == "bad" else False) for i, h, ok in rows] + [(2000, "tiny", True)], "doc_id long, source string, base_failed boolean")
    got = {r.host: r.host_rejected for r in quality_rules.host_verdicts(stats).collect()}
    assert got["bad"] and not got["good1"] and len(got) == 11


def test_chat(spark):
    rows = [(1, 0, "user", "hi"), (1, 1, "assistant", "yo"), (1, 1, "assistant", "yo"), (1, 300, None, None), (None, 2, "user", "x"), (2, None, "a", "q")]
    out = chat.rotations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string"))
    text = {(r.conv_id, r.perspective): r.dialogue for r in chat.render(out).collect()}
    assert text[1, "assistant"] == "<|user:user|>\nhi<|end|>\n<|assistant|>\nyo<|end|>\n<|assistant|>\nyo<|end|>\n<|user:unknown|>\n<|end|>\n"
    assert len(text) == 5
    for r in out.collect():
        whole = text[r.conv_id, r.perspective]
        assert whole[r.start : r.start + r.length] == r.rendered
        if r.unmasked:
            assert whole[r.loss_start : r.loss_start + r.loss_length].endswith("<|end|>")


@pytest.mark.parametrize("band", [7, 1000])
def test_vectors(spark, band):
    rng = np.random.default_rng(2)
    base = rng.normal(size=(12, 8))
    rows = [(i, [float(v) for v in base[i % 12] + rng.normal(size=8) * 0.25]) for i in range(90)]
    rows += [(200 + i, rows[3][1]) for i in range(5)] + [(300, None), (301, [0.0] * 8), (302, [float("nan")] * 8), (303, []), (304, [1.0, 2.0]), (305, [1.0, None]), (None, [1.0] * 8)]
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in vector_dedup.near_duplicates(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), band=band).collect()}
    good = {i: np.array(v) for i, v in rows if i is not None and v and len(v) == 8 and np.isfinite(v).all() and np.any(v)}
    near = {i: {j for j in good if j != i and good[i] @ good[j] / (np.linalg.norm(good[i]) * np.linalg.norm(good[j])) >= 0.95} for i in good}
    for i, _ in rows:
        if i is None:
            continue
        seen, todo = {i}, [i]
        while todo:
            new = near.get(todo.pop(), set()) - seen
            seen |= new
            todo += new
        assert got[i] == (len(near.get(i, ())), min(seen), i == min(seen))
    assert max(n for n, _, _ in got.values()) >= 5


@pytest.mark.parametrize("long_list", [1, 64])
def test_simhash(docs, long_list):
    from xxhash import xxh64_intdigest

    def want(t):
        w = WORD.findall("".join(c.lower() if c.isascii() else c for c in t or ""))
        h = [xxh64_intdigest(" ".join(w[i : i + 3]).encode(), 42) for i in range(max(1, len(w) - 2))] if w else []
        return sum(1 << b for b in range(64) if h and 2 * sum(x >> b & 1 for x in h) > len(h))

    rows = [(i, t) for i, t in _text(docs) if i is not None]
    fp = {i: want(t) for i, t in rows}
    got = {r.doc_id: (r.fingerprint, r.component_id) for r in simhash.near_duplicates(docs.filter("doc_id is not null"), long_list).collect()}
    group = {i: i for i in fp}
    for _ in fp:
        for i in fp:
            group[i] = min(group[j] for j in fp if (fp[i] ^ fp[j]).bit_count() <= 2)
    assert got == {i: (f"{fp[i]:016x}", group[i]) for i in fp}
    one = simhash.one_of_each(docs).collect()
    assert sorted(r.doc_id for r in one if r.doc_id is not None) == sorted(set(group.values())) and len(one[0]) == len(docs.columns)


def test_simhash_keeps_each_group(spark):
    """Unrelated texts under null ids or one repeated id are groups of their own; copies under other ids are not."""
    a, b, c, d = (" ".join(f"{x}{i * i}" for i in range(40)) for x in "abcd")
    rows = [(None, a), (None, b), (None, b), (7, c), (7, d), (7, d), (8, c), (9, a)]
    one = simhash.one_of_each(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect()
    assert Counter((r.doc_id, r.text) for r in one) == Counter([(None, a), (None, b), (7, c), (7, d)])


@pytest.mark.parametrize(("length", "hot"), [(40, 10**6), (40, 3), (25, 2)])
def test_suffix_dedup(docs, length, hot):
    count = Counter(b[i : i + length] for _, t in _text(docs) for b in [(t or "").encode()] for i in range(len(b) - length + 1))
    want = Counter()
    for d, t in _text(docs):
        b = (t or "").encode()
        gone = np.zeros(len(b) + 1, bool)
        for i in range(len(b) - length + 1):
            if count[b[i : i + length]] > 1:
                gone[i : i + length] = True
        kept = bytes(x for x, g in zip(b, gone, strict=False) if not g)
        want[d, len(b), int(gone.sum()), int((gone[:-1] & ~np.concatenate([[False], gone[:-2]])).sum()) if len(b) else 0, hashlib.sha256(kept).hexdigest()] += 1
    got = Counter(tuple(r) for r in suffix_dedup.dedup_digests(docs, length, hot).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256").collect())
    assert got == want
    assert suffix_dedup.without_repeats(docs, length, hot).columns == docs.columns


def test_suffix_order():
    rng = random.Random(1)
    for _ in range(300):
        s = [rng.randint(1, rng.choice([1, 2, 30])) for _ in range(rng.randint(0, 40))]
        assert suffix_dedup.suffix_order(np.array(s, np.int64)).tolist() == sorted(range(len(s)), key=lambda i: s[i:])


def test_byte_bpe(docs):
    tiktoken = pytest.importorskip("tiktoken")
    codec = TextCodec(public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)
    enc = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=codec.bpe.ranks, special_tokens={})
    texts = dict(_text(docs))
    for r in encode_documents(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN).collect():
        ids = enc.encode_ordinary(texts[r.doc_id] or "")
        assert list(r.ids) == ids and r.n_tokens == len(ids)
        assert r.decoded_sha256 == hashlib.sha256((texts[r.doc_id] or "").encode()).hexdigest()
    rng = random.Random(3)
    for _ in range(300):
        s = "".join(rng.choice(rng.choice(["ab", "etaoin", "é日", "=-_", "01"])) for _ in range(rng.randint(1, 200)))
        assert codec.encode(s) == enc.encode_ordinary(s)


def test_packing(docs):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    t.encode_special_tokens = True
    rows = packing.pack_documents(docs, public_tokenizers.path("word_bpe_49k.json"), fan_in=2).toPandas()
    texts = Counter()
    for i, x in _text(docs):
        texts[-1 if i is None else i, x] += 1
    by_doc = rows.fillna({"doc_id": -1}).groupby("doc_id")
    for (i, x), times in texts.items():
        ids = np.array([*t.encode(x or "", add_special_tokens=False).ids, 2], "<u4")
        g = by_doc.get_group(i)
        assert g["length"].sum() == len(ids) * times and (g["doc_tokens"] == len(ids)).all()
        for p in g.itertuples():
            assert p.ids_crc32 == zlib.crc32(ids[p.start : p.start + p.length].tobytes())
    sizes = rows.groupby("sequence_id")["length"].sum()
    assert (sizes <= 4096).all() and all(n == 4096 or n & (n - 1) == 0 for n in sizes)
    s = rows.sort_values(["sequence_id", "offset"])
    assert (s.groupby("sequence_id")["length"].cumsum() - s["length"] == s["offset"]).all()


def test_learned_operators_give_every_row(docs, labels):
    n = docs.count()
    tox = toxicity.toxicity_scores(docs, labels).toPandas()
    lang = language_id.identify(docs).toPandas()
    rules = rule_ensemble.quality_scores(docs, labels).toPandas()
    for got in (tox, rules):
        assert len(got) == n and got["score"].between(0, 1).all() and ((got["score"] >= 0.5) == (got["predicted"] == 1)).all()
    assert len(lang) == n and set(lang["lang_pred"]) <= {"en", "und"} and lang["score"].between(0, 1).all()
    assert (tox["held_out"] == [i == i and zlib.crc32(str(int(i)).encode()) % 5 == 0 for i in tox["doc_id"]]).all()
    kept = toxicity.toxicity_scores(docs, labels, keep_as="__t")
    assert kept.columns == [*docs.columns, "__t"] and kept.count() == n


def test_held_out_accuracy(spark):
    d = "/root/testdata/sf0.1"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    truth = labels.toPandas()
    for got, name in ((toxicity.toxicity_scores(docs, labels), "toxic"), (rule_ensemble.quality_scores(docs, labels), "quality")):
        m = got.toPandas().merge(truth, on="doc_id")
        m = m[m["held_out"]]
        assert (m["predicted"] == m[name]).mean() > 0.97
    m = language_id.identify(docs).toPandas().merge(docs.select("doc_id", "lang").toPandas(), on="doc_id")
    m = m[m["held_out"]]
    assert (m["lang_pred"] == m["lang"]).mean() > 0.98


def test_disguised_words_are_restored():
    counts = toxicity.char_counts(iter(["the idiot is a stupid loser and a clown with a moron and trash "] * 50))
    r = toxicity.Restorer(counts)
    for disguised, plain in {"1d10t": "idiot", "l.o.s.e.r": "loser", "cl0wwwn": "clown", "m0r0n": "moron", "tr4sh": "trash"}.items():
        assert plain in r.words(f"you {disguised} there"), disguised
    assert r.restore("plain words stay, as they are") == "plain words stay, as they are"


def test_empty_tables(spark, docs, labels):
    none, no_labels = docs.limit(0), labels.limit(0)
    assert quality_rules.judge(none).count() == 0 and simhash.near_duplicates(none).count() == 0 and suffix_dedup.dedup_digests(none).count() == 0
    assert packing.pack_documents(none, public_tokenizers.path("word_bpe_49k.json")).count() == 0
    assert toxicity.toxicity_scores(none, no_labels).count() == 0 and language_id.identify(none).count() == 0 and rule_ensemble.quality_scores(none, no_labels).count() == 0
    assert encode_documents(none, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN).count() == 0
    assert chat.rotations(spark.createDataFrame([], "conv_id long, turn long, role string, text string")).count() == 0
    assert vector_dedup.near_duplicates(spark.createDataFrame([], "vec_id long, embedding array<float>")).count() == 0
    assert (toxicity.toxicity_scores(docs, no_labels).toPandas()["score"] == 0.5).all()
