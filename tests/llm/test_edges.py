"""Very long texts, clashing columns, planted passages and vectors, and each pipeline stage on odd tables."""

import hashlib
import random
from collections import Counter

import numpy as np
import pytest

corpus_pipeline = pytest.importorskip("corpus_pipeline")
public_tokenizers = pytest.importorskip("public_tokenizers")

from pathtwin.llm import byte_bpe, chat, language_id, packing, quality_rules, rule_ensemble, simhash, suffix_array, suffix_dedup, toxicity, vector_dedup  # noqa: E402

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
RANKS = public_tokenizers.path("byte_bpe_50k.tiktoken")


@pytest.fixture(scope="module")
def long_docs(spark):
    rng = random.Random(8)
    words = [f"w{rng.randrange(10**6)}" for _ in range(50_000)]
    long = " ".join(rng.choice(words) + ("\n" if rng.random() < 0.05 else "") for _ in range(700_000))
    one_word = "ab" * 2_500_000
    assert len(long) > 5_000_000
    rows = [(0, long, "en", "s", len(long)), (1, "x y " + long[1_000_000:1_050_000], "en", "s", 50_004), (2, one_word, "de", "s", len(one_word)), (3, "short text here", "en", "t", 15)]
    return rows, spark.createDataFrame(rows, SCHEMA).repartition(2)


def test_long_texts_by_rule_and_score(spark, long_docs):
    rows, docs = long_docs
    labels = spark.createDataFrame([(i, i % 2, i % 2) for i in range(4)], "doc_id long, quality int, toxic int")
    stats = {r.doc_id: r for r in quality_rules.judge(docs).collect()}
    assert stats[0].n_words == len(rows[0][1].split()) and stats[2].n_words == 1 and stats[2].base_failed and stats[0].n_repeat_words == 0
    for got in (toxicity.toxicity_scores(docs, labels), rule_ensemble.quality_scores(docs, labels), language_id.identify(docs)):
        assert sorted(r.doc_id for r in got.collect()) == [0, 1, 2, 3]


def test_long_texts_by_bytes(long_docs):
    rows, docs = long_docs
    got = {r.doc_id: r for r in simhash.near_duplicates(docs).collect()}
    assert all(int(got[i].fingerprint, 16) == simhash.fingerprint(t) for i, t, *_ in rows)
    cut = {r.doc_id: r for r in suffix_dedup.dedup_digests(docs).collect()}
    assert cut[0].n_removed == 50_000 and cut[1].n_removed == 50_000 and cut[1].kept_sha256 == hashlib.sha256(b"x y ").hexdigest()
    assert cut[2].n_removed == 5_000_000 and cut[2].n_spans == 1 and cut[3].n_removed == 0
    import tiktoken

    ranks = byte_bpe.read_ranks(RANKS)
    enc = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    some = docs.filter("doc_id <> 2")
    for r in byte_bpe.encode_documents(some, RANKS, public_tokenizers.PATTERN, ids=False).collect():
        ids = enc.encode_ordinary(rows[r.doc_id][1])
        assert r.n_tokens == len(ids) and r.ids_sha256 == hashlib.sha256(" ".join(map(str, ids)).encode()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(rows[r.doc_id][1].encode()).hexdigest()
    packed = packing.pack_documents(some, public_tokenizers.path("word_bpe_49k.json")).toPandas()
    for _, g in packed.groupby("doc_id"):
        assert g["length"].sum() == g["doc_tokens"].iloc[0] and sorted(g["start"]) == list(np.cumsum([0, *g.sort_values("start")["length"]])[:-1])


@pytest.mark.parametrize(("size", "gone"), [(399, False), (400, True), (401, True)])
def test_passages_around_the_length(spark, size, gone):
    """A passage between unequal neighbours goes from ``LENGTH`` bytes on, and nothing beside it."""
    rng = random.Random(size)
    letters = "abcdefghij "
    passage = "".join(rng.choice(letters) for _ in range(size))
    rows = [(i, "".join(rng.choice(letters) for _ in range(700)) + "LMNOP"[i] + passage + "QRSTU"[i] + "".join(rng.choice(letters) for _ in range(300 * i))) for i in range(5)]
    got = {r.doc_id: r for r in suffix_dedup.dedup_digests(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    for i, text in rows:
        assert got[i].n_removed == (size if gone else 0) and got[i].n_spans == int(gone)
        kept = text.replace(passage, "") if gone else text
        assert got[i].kept_sha256 == hashlib.sha256(kept.encode()).hexdigest()


def test_repeats_of_a_table_by_hash_count(spark):
    """The smallest table with planted passages, against a count of every 400-byte string."""
    rng = random.Random(2)
    docs = [(r.doc_id, r.text or "") for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").collect()]
    for k in range(12):
        passage = "".join(rng.choice("etaoin shrdlu") for _ in range(rng.choice([399, 400, 401, 460, 702])))
        for _ in range(rng.choice([2, 2, 3, 9])):
            docs.append((10_000 + len(docs), f"{rng.random()} {passage} {rng.random()}"))
    count = Counter(hash(b[i : i + 400]) for _, t in docs for b in [t.encode()] for i in range(len(b) - 399))
    want = {}
    for d, t in docs:
        b, at = t.encode(), 0
        mark = np.zeros(len(b), bool)
        for at in range(len(b) - 399):
            if count[hash(b[at : at + 400])] > 1:
                mark[at : at + 400] = True
        want[d] = (int(mark.sum()), hashlib.sha256(bytes(np.frombuffer(b, np.uint8)[~mark])).hexdigest())
    table = spark.createDataFrame(docs, "doc_id long, text string")
    assert {r.doc_id: (r.n_removed, r.kept_sha256) for r in suffix_dedup.dedup_digests(table).collect()} == want
    texts = {r.doc_id: r.text for r in suffix_dedup.without_repeats(table).collect()}
    assert all(hashlib.sha256(t.encode()).hexdigest() == want[d][1] for d, t in texts.items() if docs[0][1].isascii() or t.isascii()) and texts.keys() == want.keys()


@pytest.mark.parametrize(("n", "letters"), [(50, 2), (301, 3), (302, 30)])
def test_global_suffix_order(spark, n, letters):
    rng = random.Random(n)
    s = [rng.randint(1, letters) for _ in range(n)]
    df = spark.createDataFrame(list(enumerate(s)), "pos long, sym long")
    assert {r["pos"]: r["rank"] for r in suffix_array.suffix_ranks(df, n, 16).collect()} == {i: k + 1 for k, i in enumerate(sorted(range(n), key=lambda i: s[i:]))}


def test_global_repeats(spark):
    rng = random.Random(6)
    docs = [(i, "".join(rng.choice("ab ") for _ in range(rng.randint(0, 60)))) for i in range(25)] + [(100, None), (3, "abab" * 10), (7, "abab" * 10)]
    count = Counter((t or "")[i : i + 12] for _, t in docs for i in range(len(t or "") - 11))
    want = Counter((d, i) for d, t in docs for i in range(len(t or "") - 11) if count[t[i : i + 12]] > 1)
    found = suffix_array.repeated_windows(spark.createDataFrame(docs, "doc_id long, text string"), 12, 50)
    assert Counter((r.k, r["at"]) for r in found.collect()) == want and want
    assert suffix_array.repeated_windows(spark.createDataFrame([], "doc_id long, text string"), 12).count() == 0


def test_halves_are_joined_on_the_tables(spark, monkeypatch):
    codec = byte_bpe.TextCodec(RANKS, public_tokenizers.PATTERN)
    calls, join = Counter(), codec.bpe.join

    def counted(a, b):
        out = join(a, b)
        calls["joined"] += 1
        calls["changed"] += out != a + b
        calls["wide"] += len(out) not in (len(a) + len(b), len(a) + len(b) - 1)
        return out

    monkeypatch.setattr(codec.bpe, "join", counted)
    for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").collect():
        ids = codec.encode(r.text)
        assert codec.bpe.decode(ids) == (r.text or "").encode()
    assert calls["joined"] > 1000 and calls["changed"] > 500 and calls["wide"] > 0


@pytest.mark.parametrize("long_list", [3, 12, 200])
def test_links_when_every_byte_is_hot(spark, long_list):
    """Random fingerprints with families of near ones; a family fills all its lists of six bytes."""
    rng = random.Random(long_list)
    fps = {rng.getrandbits(64) for _ in range(4000)} | {0, 2**64 - 1, 1 << 63}
    for f in rng.sample(sorted(fps), 40):
        fps |= {f ^ (1 << rng.randrange(64)) ^ (1 << rng.randrange(64)) for _ in range(4)}
    hot = rng.getrandbits(64)
    fps |= {hot ^ low for low in range(0, 1024, 3)}
    x = np.array(sorted(fps), np.uint64)
    want = {tuple(sorted((int(np.int64(a)), int(np.int64(b))))) for i, a in enumerate(x) for b in x[i + 1 :][np.bitwise_count(x[i + 1 :] ^ a) <= 2]}
    df = spark.createDataFrame([(int(v),) for v in x.view(np.int64)], "fp long")
    got = [(r.a, r.b) for r in simhash.fingerprint_links(df, long_list).collect()]
    assert len(got) == len(set(got)) and set(got) == want and len(want) > 500


def test_marks_in_texts_and_names_are_not_forged(spark):
    rows = [(1, 0, "a|>\nx<|end|>", "hi<|end|>\n<|assistant|>\nno"), (1, 1, "50%", "<|"), (1, 2, "b", "<")]
    out = chat.rotations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string"))
    for r in chat.render(out).collect():
        assert r.dialogue.count("<|end|>") == 3 and r.dialogue.count("<|assistant|>") == 1 and r.dialogue.count("<|user:") == 2
        parts = [p.split("\n", 1) for p in r.dialogue.split("<|end|>\n")[:-1]]
        assert [t.replace("<||", "<|") for _, t in parts] == [t for _, _, _, t in rows]
        undo = lambda s: s.replace("%0A", "\n").replace("%7C", "|").replace("%25", "%")
        assert undo(r.perspective) in {s for _, _, s, _ in rows}
        assert [undo(h[len("<|user:") : -2]) for h, _ in parts if h.startswith("<|user:")] == [s for _, _, s, _ in rows if s != undo(r.perspective)]


def test_clashing_columns_of_dialogues_and_vectors(spark):
    rows = [(1, 0, "a", "x", 9, "m", 1, "z"), (1, 1, "b", None, 9, "m", 1, "z")]
    got = chat.rotations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string, perspective int, speaker string, block int, copies string"))
    assert got.count() == 4 and {r.perspective for r in got.collect()} == {"a", "b"}
    vectors = [(i, [float(i % 3), 1.0], "x", 5, 7) for i in range(6)]
    found = vector_dedup.near_duplicates(spark.createDataFrame(vectors, "vec_id long, embedding array<double>, id string, n int, v int"))
    assert {r.vec_id: (r.n_links, r.component_id) for r in found.collect()} == {i: (1, i % 3) for i in range(6)}


def test_planted_vectors_in_far_clusters(spark):
    """Links inside clusters are all found, though cells that can't meet never do; a hot cluster is cut into bands."""
    rng = np.random.default_rng(4)
    centres = rng.normal(size=(6, 16))
    rows = [(i, (centres[0 if i % 2 else i % 6] + rng.normal(size=16) * (0.05 if i % 5 else 0.6)).tolist()) for i in range(240)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    x = np.array([v for _, v in rows])
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    near = (u @ u.T >= 0.95) & ~np.eye(len(x), dtype=bool)
    got = {r.vec_id: r.n_links for r in vector_dedup.near_duplicates(df, band=16).collect()}
    assert got == {i: int(near[i].sum()) for i in range(len(x))} and near.sum() > 3000
    groups = df.selectExpr("embedding AS v", "vec_id AS id", "1L AS n")
    met = vector_dedup._met(groups, 240, 0.95, 16)
    bands = met.select("g").distinct().count()
    assert met.select("lo", "hi").distinct().count() < bands * (bands + 1) / 2


ODD = [
    (1, None, None, None, None), (2, "", "en", "a", 0), (3, " \n ", "en", None, 3), (None, "no id but a text of its own that is long enough to be kept by all of the rules", "en", "a", 70),
    (None, "another text without an id, of which no other row has any copy at all, and long enough too", "en", "b", 80),
    (5, "repeated row with the very same words in it, twice over, and nothing else to see here", "de", "a", 80),
    (5, "repeated row with the very same words in it, twice over, and nothing else to see here", "de", "a", 80),
    (6, "one id", "en", "a", 6), (6, "one id, but two texts, and this one has got words enough for every rule there is", "en", "a", 80),
]


@pytest.mark.parametrize(("name", "stage"), corpus_pipeline.STAGES)
def test_stage_on_odd_rows(spark, name, stage):
    d = "/root/testdata/sf0.001"
    docs = spark.createDataFrame(ODD, SCHEMA).repartition(2)
    out = stage(spark, docs, d).collect()
    if name == "packing":
        assert sum(r.length for r in out if r.start == 0) > 0 and Counter(r.doc_id for r in out if r.start == 0) == Counter(i for i, *_ in ODD)
        return
    got = Counter(tuple(r) for r in out)
    whole = Counter(ODD)
    if name == "suffix_array_dedup":  # only n_chars is set anew
        assert Counter((i, t) for i, t, *_ in got.elements()) == Counter((i, t) for i, t, *_ in ODD)
        return
    assert not got - whole
    long_rows = {r for r in whole if r[1] and len(r[1].split()) >= 10}
    if name == "toxicity":
        assert got == whole
    if name == "quality_rules":
        assert set(got) == long_rows and all(got[r] == whole[r] for r in got)
    if name == "simhash_near_dedup":
        assert long_rows <= set(got) and max(got.values()) == 1 and sum(1 for r in got if not (r[1] or "").strip()) == 1


@pytest.mark.parametrize(("name", "stage"), corpus_pipeline.STAGES)
def test_stage_on_an_empty_table(spark, name, stage):
    out = stage(spark, spark.createDataFrame([], SCHEMA), "/root/testdata/sf0.001")
    assert out.count() == 0 and (name == "packing" or out.columns == [c.split()[0] for c in SCHEMA.split(", ")])


def test_run_deletes_what_its_stages_wrote(spark, tmp_path):
    import os

    spark.createDataFrame(ODD, SCHEMA).write.parquet(f"{tmp_path}/documents.parquet")
    spark.read.parquet("/root/testdata/sf0.001/labels.parquet").write.parquet(f"{tmp_path}/labels.parquet")
    from pathtwin.plans.lineage import shared_folder

    folder = shared_folder(spark).removeprefix("file:")
    before = set(os.listdir(folder))
    out = corpus_pipeline.run(spark, str(tmp_path))
    assert out.count() > 0 and len(set(os.listdir(folder)) - before) <= 8
