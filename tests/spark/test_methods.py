"""Generated methods through the presets against every pair in plain Python, and the forms that have no SQL."""

import random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from pathtwin import encode, frontends
from pathtwin.baselines.families import runs
from pathtwin.config import DetectorConfig
from pathtwin.corpus.methods import methods
from pathtwin.frontends.java import linear_methods, parse_methods
from pathtwin.frontends.text_lines import line_paths
from pathtwin.match import blocks
from pathtwin.match.detector import classes, detect, detect_among
from pathtwin.match.sets import encoded_paths
from pathtwin.metrics.kernels import set_distance
from pathtwin.workloads import methods as W


@pytest.fixture(scope="module")
def files(spark):
    """Each kind of variant of three functionalities."""
    seeds = [(t + 43 * k,) for t in (0, 1, 2) for k in range(20)]
    return methods(spark.createDataFrame(seeds, "seed long")).cache()


@pytest.mark.parametrize(("form", "preset"), [("source", "default"), ("source", "fast"), ("stack", "stack_ir"), ("register", "register_ir")])
def test_presets_against_every_pair(files, form, preset):
    cfg = getattr(DetectorConfig, preset)()
    paths = parse_methods(files, form).cache()
    sets: dict = {}
    for r in encoded_paths(paths.filter(F.col("n_lines") >= cfg.min_lines), cfg.encoding, cfg.merge).collect():
        sets.setdefault(r.fragment_id, []).append((tuple(r.code), r.mult))
    size = {i: sum(n for _, n in s) for i, s in sets.items()}
    want = {}
    for i in sets:
        for j in sets:
            if i < j and max(size[i], size[j]) <= 1.7 * min(size[i], size[j]):
                d = round(set_distance(sets[i], sets[j], cfg.metric, cfg.tau, cfg.tie, cfg.max_len_diff), 6)
                if d < cfg.tau:
                    want[i, j] = d
    assert {(r.left_id, r.right_id): r.distance for r in detect(paths, cfg).collect()} == want and len(want) > 20


def test_runs_on_stack_form(files):
    w = linear_methods(files, "stack")
    texts = {r.fragment_id: r.w for r in w.collect()}

    def total(a, b):
        """Tokens in maximal runs of at least 15, over all diagonals."""
        n = 0
        for diag in range(-len(b) + 1, len(a)):
            run = 0
            for i in range(max(0, diag), min(len(a), len(b) + diag) + 1):
                if i < min(len(a), len(b) + diag) and a[i] == b[i - diag]:
                    run += 1
                else:
                    n += run if run >= 15 else 0
                    run = 0
        return n

    want = {(i, j) for i in texts for j in texts if i < j and total(texts[i], texts[j]) >= 50}
    got = {(r.left_id, r.right_id) for r in runs(w.select(F.col("fragment_id").alias("id"), "w")).collect()}
    assert got == want and want


def test_frontends_by_name(spark, files):
    docs = spark.createDataFrame([(1, "a b\nc d"), (2, "e")], "doc_id long, text string")
    assert frontends.paths_of("lines", docs).columns == list(frontends.COLUMNS) and "methods" in frontends.names()
    frontends.register("halves", lambda source: line_paths(source).filter("fragment_id < 2"))
    assert frontends.paths_of("halves", docs).count() == 1
    for name in ("halves", "lines"):
        with pytest.raises(ValueError):
            frontends.register(name, line_paths)
    frontends.register("broken", lambda source: source)
    with pytest.raises(ValueError):
        frontends.paths_of("broken", docs)


def test_model_codes(spark):
    """Equal nodes have equal codes, clusters never meet, and similar nodes share codes more often than others."""
    words = [f"t{i}" for i in range(8)]
    nodes = [words[:k] for k in range(1, 9)] + [[*words[:7], f"x{i}"] for i in range(40)] + [[f"y{i}{k}" for k in range(8)] for i in range(40)]
    paths = spark.createDataFrame([(i, 1, 0, [n, n], 1) for i, n in enumerate(nodes)], "fragment_id long, n_lines int, path_no int, nodes array<array<string>>, mult int")
    code = {r.fragment_id: list(r.code) for r in encode.with_model_codes(paths).collect()}
    assert all(len(c) == 2 and c[0] == c[1] for c in code.values())
    assert all(code[i][0] // encode.BUCKETS == max(3, min(8, len(n))) - 3 for i, n in enumerate(nodes))
    alike, others = [code[i][0] for i in range(8, 48)], [code[i][0] for i in range(48, 88)]
    assert len(set(alike)) < len(set(others)) / 2


def test_recall_compares_labelled_pairs_alone(files, monkeypatch):
    """Of given pairs those are reported that the whole detector reports, and no other pair is compared."""
    from pathtwin.match import detector
    from pathtwin.workloads.methods import truth

    paths, known = parse_methods(files).cache(), truth(files).cache()
    asked, compare = [], detector.compare
    monkeypatch.setattr(detector, "compare", lambda pairs, *rest: asked.append(pairs.count()) or compare(pairs, *rest))
    for cfg in (DetectorConfig.default(), DetectorConfig.fast(), DetectorConfig.plain().but(metric="hamming_free", candidates="bands")):
        want = {(r.left_id, r.right_id): r.distance for r in detect(paths, cfg).join(known, ["left_id", "right_id"]).collect()}
        asked.clear()
        assert {(r.left_id, r.right_id): r.distance for r in detect_among(classes(paths, cfg), known, cfg).collect()} == want and want
        assert len(asked) == 1 and asked[0] <= known.count()
    with pytest.raises(ValueError):
        detect_among(classes(paths, cfg), known, cfg.but(candidates="lsh"))
    w = linear_methods(files, "stack").select(F.col("fragment_id").alias("id"), "w")
    some = {(r.left_id, r.right_id) for r in known.collect()}
    assert {tuple(r) for r in runs(w, among=known).collect()} == {tuple(r) for r in runs(w).collect()} & some


def test_different_paths_are_compared_once(monkeypatch):
    """Each path of each set was once compared, however many sets share it."""
    cfg, rng = DetectorConfig().but(min_lines=1), random.Random(2)
    paths = [tuple(rng.randrange(9) for _ in range(rng.choice((0, 4, 12, 14, 70)))) for _ in range(12)]
    sets = [[(p, rng.randint(1, 3)) for p in rng.sample(paths, rng.randint(1, 4))] for _ in range(40)]
    kind = pa.list_(pa.struct([("code", pa.list_(pa.int64())), ("mult", pa.int64())]))
    column = pa.array([[{"code": list(p), "mult": n} for p, n in s] for s in sets], kind)
    side = blocks.Side(pa.table({"id": list(range(40)), "n_paths": [sum(n for _, n in s) for s in sets], "one": [1] * 40, "paths": column}))
    calls, asked = [], blocks._asked
    monkeypatch.setattr(blocks, "_asked", lambda *a: lambda q, of=asked(*a): calls.append(q) or of(q))
    for kept, most in ((1 << 20, 12), (30, 1000)):
        calls.clear()
        monkeypatch.setattr(blocks, "KEPT", kept)
        for y, at, d in blocks.set_distances(side, side, cfg):
            want = [set_distance(sets[x], sets[y], cfg.metric, cfg.tau, cfg.tie, cfg.max_len_diff) for x in at]
            assert np.allclose(d, want, atol=1e-12)
        assert len(set(calls)) <= len(calls) <= most


def test_reported_pairs_are_counted_by_classes(spark):
    """Precision once made a row for every pair of methods; a class may hold several functionalities."""
    of = [(i, i % 3 if i < 6 else 1) for i in range(12)]
    reps = {i: 0 if i < 4 else 4 if i < 7 else 7 if i < 9 else i for i in range(12)}
    near = [(0, 4), (0, 7), (4, 9), (10, 11)]
    pairs, members = spark.createDataFrame(near, "left_id long, right_id long"), spark.createDataFrame(list(reps.items()), "fragment_id long, rep_id long")
    functionality = dict(of)
    all_pairs = [(i, j) for i in reps for j in reps if i < j and (reps[i] == reps[j] or (reps[i], reps[j]) in near or (reps[j], reps[i]) in near)]
    got = W.same_of_reported(pairs, members, spark.createDataFrame(of, "fragment_id long, functionality int")).first()
    assert tuple(got) == (len(all_pairs), sum(functionality[i] == functionality[j] for i, j in all_pairs)) and 0 < got[1] < got[0]


def test_methods_are_dealt_out_whatever_the_partitions(spark):
    """Ids came in one task where the session had as many shuffle partitions as ids were dealt over."""
    before = spark.conf.get("spark.sql.shuffle.partitions")
    spark.conf.set("spark.sql.shuffle.partitions", str(4 * spark.sparkContext.defaultParallelism))
    try:
        seeds = W.spread(spark.range(200).distinct(), "id")
        assert seeds.groupBy(F.spark_partition_id()).count().count() > 4
    finally:
        spark.conf.set("spark.sql.shuffle.partitions", before)
    assert W.BLOCKS["candidates"] == "blocks"
