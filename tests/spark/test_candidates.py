"""Candidates lose nothing: small random sets of paths against every pair, worked out in plain Python."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from pathtwin.config import DetectorConfig
from pathtwin.match import blocks
from pathtwin.match.candidates import prefix_pairs
from pathtwin.match.detector import against, classes, detect, nearest
from pathtwin.match.sets import encoded_paths
from pathtwin.metrics.kernels import REGISTRY, set_distance

SCHEMA = "fragment_id long, n_lines int, path_no int, nodes array<array<string>>, mult int"
METRICS = [m for m in REGISTRY if m != "exact"]


@pytest.fixture(scope="module")
def corpus():
    """Fragments of one to four paths of up to 40 nodes, with edited, embedded and equal ones among them."""
    rng = random.Random(12)
    symbols = [f"s{min(int(rng.expovariate(0.12)), 40)}" for _ in range(400)]
    made: list[list[list[str]]] = []
    for _ in range(45):
        made.append([[rng.choice(symbols) for _ in range(rng.choice([1, 2, 3, 5, 9, 12, 14, 30]))] for _ in range(rng.choice([1, 1, 1, 2, 3, 4]))])
    for _ in range(45):
        base = [list(p) for p in rng.choice(made)]
        for p in base:
            for _ in range(rng.choice([0, 1, 2])):
                p[rng.randrange(len(p))] = rng.choice(symbols)
            if rng.random() < 0.3:
                p[rng.randrange(len(p)) : 0] = [rng.choice(symbols) for _ in range(rng.randint(1, 25))]
        if rng.random() < 0.3:
            base.append([rng.choice(symbols) for _ in range(3)])
        made.append(base)
    return {i: s for i, s in enumerate(made)}


@pytest.fixture(scope="module")
def paths(spark, corpus):
    rows = [(i, 20, k, [[t] for t in p], 1) for i, s in corpus.items() for k, p in enumerate(s)]
    return spark.createDataFrame(rows, SCHEMA).repartition(3).cache()


def _sets(corpus):
    return {i: [(tuple(p), s.count(p)) for p in map(list, sorted({tuple(q) for q in s}))] for i, s in corpus.items()}


def _distances(corpus, cfg, factor=None):
    sets, out = _sets(corpus), {}
    for i in sets:
        for j in sets:
            n, m = len(corpus[i]), len(corpus[j])
            if i < j and (factor is None or max(n, m) <= factor * min(n, m)):
                out[i, j] = round(set_distance(sets[i], sets[j], cfg.metric, cfg.tau, cfg.tie, cfg.max_len_diff, normalise=cfg.normalise), 6)
    return out


@pytest.mark.parametrize("metric", METRICS)
def test_prefix_finds_every_pair(paths, corpus, metric):
    cfg = DetectorConfig.plain().but(metric=metric, min_lines=1)
    want = {k: d for k, d in _distances(corpus, cfg, 1.7).items() if d < cfg.tau}
    got = {(r.left_id, r.right_id): r.distance for r in detect(paths, cfg).collect()}
    assert got == want and len(want) >= 8


@pytest.mark.parametrize("tau", [0.1, 0.45])
def test_other_thresholds(paths, corpus, tau):
    encoded = encoded_paths(paths, "md5")
    for metric in METRICS:
        cfg = DetectorConfig.plain().but(metric=metric, tau=tau, max_set_factor=None)
        found = {(r.left_id, r.right_id) for r in prefix_pairs(encoded, cfg).collect()}
        assert {k for k, d in _distances(corpus, cfg).items() if d < tau} <= found, metric


@pytest.mark.parametrize(("metric", "cap"), [("lcs_mod", 2), ("hamming_free", 0)])
def test_cap_on_lengths(paths, corpus, metric, cap):
    cfg = DetectorConfig.plain().but(metric=metric, max_len_diff=cap, min_lines=1)
    want = {k: d for k, d in _distances(corpus, cfg, 1.7).items() if d < cfg.tau}
    assert {(r.left_id, r.right_id): r.distance for r in detect(paths, cfg).collect()} == want
    assert want != {k: d for k, d in _distances(corpus, cfg.but(max_len_diff=None), 1.7).items() if d < cfg.tau}


@pytest.mark.parametrize("metric", ["lcs", "lcs_mod", "jaccard"])
def test_nearest_and_against(paths, corpus, metric):
    cfg = DetectorConfig.plain().but(metric=metric)
    every, sized = _distances(corpus, cfg), _distances(corpus, cfg, cfg.max_set_factor)
    new, index = paths.filter(F.col("fragment_id") % 4 == 0), paths.filter(F.col("fragment_id") % 4 > 0)
    sides = {(i, j) for i in corpus for j in corpus if i % 4 == 0 and j % 4}
    of = lambda i, j: every[min(i, j), max(i, j)]
    got = {(r.left_id, r.right_id): r.distance for r in against(new, index, cfg).collect()}
    assert got == {(i, j): of(i, j) for i, j in sides if sized.get((min(i, j), max(i, j)), 1) < cfg.tau} and got
    near = sorted((r.left_id, r["rank"], r.right_id, r.distance) for r in nearest(paths, paths, cfg, 4).collect())
    want = [(i, k + 1, j, d) for i in corpus for k, (d, j) in enumerate(sorted((of(i, j), j) for j in corpus if j != i)[:4])]
    assert near == want


def test_nearest_of_a_small_index(paths):
    few = paths.filter("fragment_id < 3")
    assert nearest(few, few, DetectorConfig.plain().but(metric="lcs"), 5).groupBy("left_id").count().agg(F.min("count"), F.max("count")).first()[:] == (2, 2)
    with pytest.raises(ValueError):
        nearest(few, few, DetectorConfig.plain().but(metric="hamming_free"), 2)


def test_absolute_distances(paths, corpus):
    cfg = DetectorConfig.plain().but(metric="lcs", normalise="none", tau=2.0, min_lines=1)
    want = {k: d for k, d in _distances(corpus, cfg, 1.7).items() if d < 2}
    assert {(r.left_id, r.right_id): r.distance for r in detect(paths, cfg).collect()} == want


def test_no_symbol_pairs_everything(spark):
    """A line in every fragment lists them all, but only lists of rare symbols are joined."""
    rows = [(i, 20, 0, [["common"], *[[f"own{i}_{k}"] for k in range(19)]], 1) for i in range(400)]
    encoded = encoded_paths(spark.createDataFrame(rows, SCHEMA), "md5")
    for metric in METRICS:
        if metric not in ("hamming_free", "jaro_winkler"):
            assert prefix_pairs(encoded, DetectorConfig.plain().but(metric=metric)).count() == 0, metric


@pytest.mark.parametrize(("metric", "tau"), [("lcs", 0.2), ("hamming", 0.2), ("levenshtein", 0.3)])
def test_deletions_lose_nothing(spark, metric, tau):
    """Paths of few symbols, short and longer than lists go, and a fragment of two paths: the same pairs as of every two."""
    rng = random.Random(17)
    seqs = [[rng.choice("abcd") for _ in range(n)] for n in (0, 1, 3, 5, 6, 7, 8, 10, 11, 14, 15, 16, 17, 19, 22) for _ in range(2)]
    seqs += [s[:i] + s[i + 1 :] for s in seqs[6:] for i in (0, len(s) // 2)] + [[*s[:2], "e", *s[3:]] for s in seqs[6:]] + [[*s, "e", "f"] for s in seqs[20:]] + seqs[4:8]
    rows = [(i, len(s), 0, [[x] for x in s], 1) for i, s in enumerate(seqs)] + [(900, 9, k, [[x] for x in seqs[8 + k]], 1) for k in (0, 1)]
    paths = spark.createDataFrame(rows, "fragment_id long, n_lines int, path_no int, nodes array<array<string>>, mult int")
    cfg = DetectorConfig.plain().but(metric=metric, tau=tau, min_lines=0)
    got, want = ({(r.left_id, r.right_id): r.distance for r in detect(paths, cfg.but(candidates=how)).collect()} for how in ("deletions", "all"))
    assert got == want and any(min(len(seqs[i]), len(seqs[j])) > 16 and d for (i, j), d in want.items() if j < 900)


@pytest.mark.parametrize(("metric", "cap", "factor"), [("lcs", None, 1.7), ("lcs_mod", 2, 1.7), ("alignment", None, None), ("hamming", None, 1.7), ("hamming_free", 3, None)])
def test_blocks_compare_every_pair(paths, corpus, metric, cap, factor, monkeypatch):
    monkeypatch.setattr(blocks, "SPLIT_SETS", 7)
    monkeypatch.setattr(blocks, "BATCH", 5)
    cfg = DetectorConfig.plain().but(metric=metric, max_len_diff=cap, max_set_factor=factor, min_lines=1, candidates="blocks")
    want = {k: d for k, d in _distances(corpus, cfg, factor).items() if d < cfg.tau}
    for copy in ("lossless", "off"):
        rows = detect(paths, cfg.but(copy=copy)).collect()
        assert {(r.left_id, r.right_id): r.distance for r in rows} == want and len(rows) == len(want) >= 8
        assert all((r.relation == "strict") == (len(corpus[r.left_id]) == len(corpus[r.right_id])) for r in rows)


def test_blocks_of_long_and_empty_paths(spark):
    """Paths over 64 nodes take several words of bits; a block may hold one set, or none."""
    rng = random.Random(4)
    made = [[f"n{rng.randrange(90)}" for _ in range(n)] for n in (0, 0, 1, 63, 64, 65, 128, 129, 300)]
    made += [[x for x in p if rng.random() > 0.1] for p in made]
    rows = [(i, 9, 0, [[x] for x in p], 1) for i, p in enumerate(made)]
    cfg = DetectorConfig.plain().but(metric="lcs", min_lines=1, copy="off")
    table = spark.createDataFrame(rows, SCHEMA)
    got, want = ({(r.left_id, r.right_id): r.distance for r in detect(table, cfg.but(candidates=c)).collect()} for c in ("blocks", "all"))
    assert got == want and len(got) >= 7
    assert detect(table.filter("false"), cfg.but(candidates="blocks")).count() == 0
    with pytest.raises(ValueError):
        detect(table, cfg.but(candidates="blocks", metric="cosine"))


def test_weeks_are_compared_without_lists_of_pairs(spark):
    """Weeks have fifteen symbols, so lists of candidates held almost every two of them."""
    from pathtwin.workloads.flows import FLOWS

    rng = random.Random(2)
    paths = spark.createDataFrame([(i, 12, k, [[f"e{rng.randrange(5)}"] for _ in range(4)], 1) for i in range(60) for k in range(3)], SCHEMA)
    found = detect(paths, FLOWS)
    assert "applyinarrow" in (plan := found._jdf.queryExecution().toString().lower().replace("flatmapgroupsinarrow", "applyinarrow")) and "nestedloop" not in plan
    assert {tuple(r) for r in found.collect()} == {tuple(r) for r in detect(paths, FLOWS.but(candidates="prefix")).collect()} and found.count() > 5


def test_counts_and_nearest_by_blocks(paths, corpus, monkeypatch):
    """Only pairs with a common symbol count, each as often as its weights say; the nearest of several blocks are ranked together."""
    monkeypatch.setattr(blocks, "SPLIT_SETS", 9)
    monkeypatch.setattr(blocks, "BATCH", 3)
    cfg = DetectorConfig.plain().but(metric="lcs", min_lines=1, max_set_factor=None)
    every = _distances(corpus, cfg)
    _, sets, _ = classes(paths, cfg.but(copy="off"))
    sets = sets.withColumn("one", F.col("fragment_id") + 1)
    want: dict = {}
    for (i, j), d in every.items():
        if d < 1:
            want[d] = want.get(d, 0) + (i + 1) * (j + 1)
    assert {r.distance: r.n for r in blocks.distance_counts(sets, cfg).collect()} == want
    with pytest.raises(ValueError):
        blocks.distance_counts(sets, cfg.but(metric="lcs_mod"))
    found = nearest(paths, paths, cfg, 6)
    assert "flatmapgroupsinarrow" in found._jdf.queryExecution().toString().lower()
    assert sorted((r.left_id, r["rank"], r.right_id, r.distance) for r in found.collect()) == [(i, k + 1, j, d) for i in corpus for k, (d, j) in enumerate(sorted((every[min(i, j), max(i, j)], j) for j in corpus if j != i)[:6])]


def test_blocks_round_as_spark_does(spark):
    values = [k / n for n in (128, 640, 3, 7, 1000) for k in range(n)]
    rows = spark.createDataFrame([(v,) for v in values], "v double").select("v", F.round("v", 6).alias("r")).collect()
    assert blocks.rounded(np.array([r.v for r in rows])).tolist() == [r.r for r in rows]


def test_pairs_of_all_documents_need_no_lists():
    """Hamming without a length penalty reports a share of all pairs; the queries on it and those on every pair go by blocks."""
    from pathtwin.workloads.documents import HAM_FREE

    assert HAM_FREE.candidates == "blocks" and HAM_FREE.metric == "hamming_free" and blocks.can_compare(HAM_FREE)


def test_two_metrics_joined_in_blocks(spark, monkeypatch):
    """Each pair near by either metric is there once, with both distances, and no pair travels on the way."""
    monkeypatch.setattr(blocks, "SPLIT_SETS", 9)
    monkeypatch.setattr(blocks, "BATCH", 3)
    rng = random.Random(6)
    made = [[f"n{rng.randrange(9)}" for _ in range(rng.choice([4, 12, 20, 70]))] for _ in range(30)]
    made += [[x for x in p if rng.random() > 0.1] for p in made] + made[:4]
    paths = spark.createDataFrame([(i, 20, 0, [[x] for x in p], 1) for i, p in enumerate(made)], SCHEMA)
    lcs, free = (DetectorConfig.plain().but(metric=m, min_lines=1, copy="off") for m in ("lcs", "hamming_free"))
    got = blocks.near_by_both(classes(paths, lcs)[1], lcs, free)
    want = [{(r.left_id, r.right_id): r.distance for r in detect(paths, c.but(candidates="all")).collect()} for c in (lcs, free)]
    rows = got.collect()
    assert {(r.left_id, r.right_id): (r.d_one, r.d_other) for r in rows} == {k: (want[0].get(k), want[1].get(k)) for k in want[0].keys() | want[1].keys()}
    assert len(rows) == len(want[0].keys() | want[1].keys()) and want[0].keys() - want[1].keys() and want[1].keys() - want[0].keys()
    assert got._jdf.queryExecution().executedPlan().toString().count("Join") == 0


@pytest.mark.parametrize(("metric", "cap", "factor"), [("lcs", None, 1.7), ("lcs_mod", 2, 1.7), ("lcs_mod", 7, None), ("alignment", None, None)])
def test_tiles_lose_nothing(paths, corpus, spark, metric, cap, factor, monkeypatch):
    """Sets of one path and of several, long, empty and equal ones: the same pairs as of every two, though symbols share columns and tiles are small."""
    monkeypatch.setattr(blocks, "SPLIT_SETS", 30)
    monkeypatch.setattr(blocks, "TILE", 6)
    monkeypatch.setattr(blocks, "AT_ONCE", 50)
    monkeypatch.setattr(blocks, "COLUMNS", 16)
    monkeypatch.setattr(blocks, "SET_COLUMNS", 16)
    cfg = DetectorConfig.plain().but(metric=metric, max_len_diff=cap, max_set_factor=factor, min_lines=1, candidates="tiles")
    want = {k: d for k, d in _distances(corpus, cfg, factor).items() if d < cfg.tau}
    assert {(r.left_id, r.right_id): r.distance for r in detect(paths, cfg.but(copy="off")).collect()} == want and len(want) >= 8
    rng = random.Random(4)
    made = [[f"n{rng.randrange(90)}" for _ in range(n)] for n in (0, 0, 1, 8, 9, 16, 17, 32, 33, 63, 64, 65, 128, 129, 300)]
    made += [[x for x in p if rng.random() > 0.1] for p in made] + [p[3:13] + p for p in made[4:8]] + [p[: len(p) // 2] for p in made[5:]]
    rows = [(i, 9, 0, [[x] for x in p], 1) for i, p in enumerate(made)]
    for table in (rows, rows + [(900 + k, 9, n, [[x] for x in p], 1) for k in range(3) for n, p in enumerate((made[3 + k], made[10], made[0]))]):
        table = spark.createDataFrame(table, SCHEMA)
        got, every = ({(r.left_id, r.right_id): (r.distance, r.relation) for r in detect(table, cfg.but(candidates=c)).collect()} for c in ("tiles", "all"))
        assert got == every and len(got) >= 7
    assert detect(table.filter("false"), cfg).count() == 0
    with pytest.raises(ValueError):
        detect(table, cfg.but(metric="hamming"))


@pytest.mark.parametrize("name", ["LSH_MIN6", "TREES"])
def test_codes_of_few_values_need_no_lists(spark, name):
    """Locality-sensitive codes have 1,200 values, so lists of candidates held a share of all pairs."""
    from pathtwin.workloads import documents

    cfg = getattr(documents, name).but(min_lines=0)
    rng = random.Random(3)
    made = [[f"n{rng.randrange(6)}" for _ in range(rng.choice([3, 5, 12]))] for _ in range(80)]
    paths = spark.createDataFrame([(i // (1 if name == "LSH_MIN6" else 3), 20, i, [[x] for x in p], 1) for i, p in enumerate(made)], SCHEMA)
    found = detect(paths, cfg)
    assert "flatmapgroupsinarrow" in found._jdf.queryExecution().toString().lower()
    assert {tuple(r) for r in found.collect()} == {tuple(r) for r in detect(paths, cfg.but(candidates="prefix")).collect()} and found.count() > 0
