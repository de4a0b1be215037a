"""Queries do their whole job: small tables made here, held against plain Python."""

import math
import random

import pytest

from pathtwin.workloads import QUERIES


@pytest.fixture
def made(spark, tmp_path):
    """Writes a table of rows and returns its folder."""

    def write(name, rows, schema):
        spark.createDataFrame(rows, schema).write.parquet(f"{tmp_path}/{name}.parquet")
        return str(tmp_path)

    return write


def _common(a, b):
    row = [0] * (len(b) + 1)
    for x in a:
        new = [0]
        for j, y in enumerate(b):
            new.append(row[j] + 1 if x == y else max(row[j + 1], new[-1]))
        row = new
    return row[-1]


def test_variants_of_long_documents(spark, made):
    from pathtwin.corpus.variants import KINDS, variants

    rows = [(i, "\n".join(f"line {j} of {i}" for j in range(n)), "en", "s", 1) for i, n in enumerate((14, 15, 60, 61, 200))]
    at = made("documents", rows, "doc_id long, text string, lang string, source string, n_chars long")
    corpus = {(r.origin_id, r.kind): r.n_lines for r in QUERIES["var_corpus"](spark, at).collect()}
    assert set(corpus) == {(i, k) for i in (1, 2, 3, 4) for k in KINDS}
    assert corpus[3, "ty1"] == 61 and corpus[4, "embed_head"] == 220 and corpus[4, "shift"] == 201
    pairs = variants(spark.read.parquet(f"{at}/documents.parquet")).collect()
    want = {k: sum(round(1 - _common(r.s, r.v) / max(len(r.s), len(r.v)), 6) < 0.3 for r in pairs if r.kind == k) for k in KINDS}
    assert {r.kind: (r.n_pairs, r.n_found) for r in QUERIES["var_recall_lcs"](spark, at).collect()} == {k: (4, n) for k, n in want.items()}


def test_one_method_for_each_id(spark, made):
    from pathtwin.corpus.methods import FUNCTIONALITIES, KINDS, mutate, template
    from pathtwin.workloads.methods import corpus

    ids = [0, 43 * 5, 43 * 15, 43 * 25, 430, 10**12 + 7, 430, None]
    at = made("documents", [(i,) for i in ids], "doc_id long")
    got = {r.fragment_id: (r.functionality, r.kind, r.content) for r in corpus(spark, at).collect()}
    seeds = set(ids) - {None}
    kind = {i: KINDS[i // FUNCTIONALITIES % len(KINDS)] for i in seeds}
    assert got == {i: (i % FUNCTIONALITIES, kind[i], mutate(template(i % FUNCTIONALITIES), kind[i], i)) for i in seeds}
    assert len({got[i][2] for i in (43 * 5, 43 * 15, 43 * 25)}) == 3
    y = QUERIES["java_yield"](spark, at).first()
    assert (y.n_files, y.n_parsed) == (6, 6)


@pytest.mark.parametrize("block", [(512, 4096), (1, 7)])
def test_cosine_of_every_other_vector(spark, made, monkeypatch, block):
    from pathtwin.workloads import operators

    monkeypatch.setattr(operators, "VEC_BLOCK", block, raising=False)
    rng = random.Random(3)
    rows = [(i, [rng.gauss(0, 1) for _ in range(8)], i % 3 if i % 7 else None) for i in range(120)]
    rows += [(None, rows[5][1], 1), (200, [0.0] * 8, 0), (201, None, 0), (202, [1.0] * 5, 0), (203, [1.0, None] * 4, 0), (2**60 + 1, rows[9][1], None), (7, rows[8][1], 2)]
    at = made("embeddings", rows, "vec_id long, embedding array<float>, label int")
    flat = [(i, v) for i, v, _ in ((r.vec_id, r.embedding, r.label) for r in spark.read.parquet(f"{at}/embeddings.parquet").collect())]

    def cos(x, y):
        if x is None or y is None or len(x) != len(y) or None in x or None in y or not any(x) or not any(y):
            return None
        return sum(p * q for p, q in zip(x, y, strict=True)) / math.sqrt(sum(p * p for p in x) * sum(q * q for q in y))

    key = lambda r: (r[0], r[1] is None, r[1] or 0, r[2] is None, r[2] or 0)
    want = sorted(((i, j, cos(x, y)) for i, x in flat if i is not None and i % 50 == 0 for j, y in flat if i != j), key=key)
    got = sorted((tuple(r) for r in QUERIES["op_vec_cosine"](spark, at).collect()), key=key)
    assert [r[:2] for r in got] == [r[:2] for r in want]
    assert all((g is None) == (w is None) and (g is None or abs(g - w) < 1e-6) for (_, _, g), (_, _, w) in zip(got, want, strict=True))


def test_orders_of_all_lengths_and_classes(spark, made):
    rng = random.Random(5)
    base = [[rng.choice([("A", "F", 5.0), ("N", "O", 20.0), ("R", "F", 40.0)]) for _ in range(n)] for n in (1, 2, 3, 5, 6, 7, 8, 10, 12)]
    seqs = base + base + base[:4] + [s[:-1] for s in base[4:]] + [[*s[:3], ("N", "F", 5.0), *s[4:]] for s in base[4:]] + [s[1:] for s in base[5:]]
    rows = [(k, i, 1, 1, i, 1.0, f, st, q) for k, s in enumerate(seqs) for i, (f, st, q) in enumerate(s)]
    at = made("lineitem", rows, "l_orderkey long, l_linenumber int, l_partkey long, l_suppkey long, l_shipdate int, l_extendedprice double, l_returnflag string, l_linestatus string, l_quantity double")

    def near(metric):
        far = {"lcs": lambda a, b: max(len(a), len(b)) - _common(a, b), "hamming": lambda a, b: sum(x != y for x, y in zip(a, b, strict=False)) + abs(len(a) - len(b))}[metric]
        d = {(i, j): far(seqs[i], seqs[j]) / max(len(seqs[i]), len(seqs[j])) for i in range(len(seqs)) for j in range(i + 1, len(seqs))}
        return {k: round(x, 6) for k, x in d.items() if round(x, 6) < 0.2}

    found = QUERIES["order_seq_clones"](spark, at).collect()
    rep = {r.right_id: r.left_id for r in found if r.row == "member"}
    assert rep == {i: seqs.index(s) for i, s in enumerate(seqs)}
    linked = {(r.left_id, r.right_id): r.distance for r in found if r.row == "pair"}
    whole = {}
    for i in rep:
        for j in range(i + 1, len(seqs)):
            k = tuple(sorted((rep[i], rep[j])))
            if k[0] == k[1] or k in linked:
                whole[i, j] = linked.get(k, 0.0)
    assert whole == near("lcs") and len(whole) > len(linked) > 0
    assert {r.setup: r.n_pairs for r in QUERIES["order_fast_vs_default"](spark, at).collect()} == {"fast": len(near("hamming")), "lcs": len(near("lcs"))}


def test_word_copies_of_all_lengths(spark, made):
    rng = random.Random(11)
    texts = [" ".join(f"w{rng.randrange(60)}" for _ in range(n)) for n in (1, 2, 4, 9, 20, 39, 40, 90, 200)]
    edited = [" ".join(w for i, w in enumerate(t.split()) if i % k) for t in texts[3:] for k in (5, 8, 12)]
    texts = [*texts, *texts[:6], *edited, "", None, "...", texts[4].upper() + "!"]
    at = made("documents", list(enumerate(texts)), "doc_id long, text string")
    words = [[w.strip("!.") for w in (t or "").lower().split() if w.strip("!.")] for t in texts]
    want = {}
    for i, a in enumerate(words):
        for j in range(i + 1, len(words)):
            longer = max(len(a), len(words[j]))
            d = round(1 - _common(a, words[j]) / longer, 6) if longer else 0.0
            if d < 0.3:
                want[i, j] = d
    assert {(r.left_id, r.right_id): r.distance for r in QUERIES["word_near_copies"](spark, at).collect()} == want
    assert any(0.1 < d < 0.3 for d in want.values())


def test_rounds_go_on_to_the_end(spark):
    from pathtwin.flow.dominators import idom_bulk
    from pathtwin.flow.exceptions import propagate

    names = ["entry", *(f"n{i:02d}" for i in range(6))]
    chain = spark.createDataFrame([(1, a, b) for a, b in zip(names, names[1:], strict=False)], "fragment_id long, src string, dst string")
    assert {r.node_id: r.idom for r in idom_bulk(chain).collect()} == dict(zip(names[1:], names, strict=False))
    with pytest.raises(RuntimeError):
        idom_bulk(chain, max_rounds=3)
    calls = spark.createDataFrame([(f"f{i}", f"f{i + 1}") for i in range(5)], "caller string, callee string")
    facts, none = spark.createDataFrame([("f5", "io")], "fn string, exc string"), spark.createDataFrame([], "fn string, exc string")
    assert {r.fn for r in propagate(calls, facts, none).collect()} == {f"f{i}" for i in range(6)}
    with pytest.raises(RuntimeError):
        propagate(calls, facts, none, max_rounds=3)
