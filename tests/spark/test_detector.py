import pytest
from pyspark.sql import functions as F

from pathtwin.config import DetectorConfig
from pathtwin.corpus.variants import variants
from pathtwin.evaluation import measures as M
from pathtwin.flow.exceptions import propagate
from pathtwin.frontends import text_lines as T
from pathtwin.match.detector import detect
from pathtwin.plans import connected_components

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


def _rows(df):
    return {tuple(r) for r in df.select("left_id", "right_id", "distance").collect()}


@pytest.mark.parametrize("metric", ["lcs", "lcs_mod", "levenshtein", "hamming"])
def test_prefix_candidates_lose_nothing(docs, metric):
    paths = T.line_paths(docs, "blind", 6)
    cfg = DetectorConfig.plain().but(metric=metric, encoding="md5", min_lines=6)
    assert _rows(detect(paths, cfg)) == _rows(detect(paths, cfg.but(candidates="all", copy="off")))


def test_multi_path_sets(docs):
    cfg = DetectorConfig.plain().but(encoding="md5", min_lines=6)
    paths = T.paragraph_paths(docs)
    assert _rows(detect(paths, cfg)) == _rows(detect(paths, cfg.but(candidates="all", copy="off")))
    assert _rows(detect(paths, cfg)) == _rows(detect(paths, cfg.but(merge="none")))


def test_threshold_is_strict(spark):
    rows = [(i, 10, 0, [[x] for x in s], 1) for i, s in ((1, "abcdefghij"), (2, "abcdefgxyz"))]
    paths = spark.createDataFrame(rows, "fragment_id long, n_lines int, path_no int, nodes array<array<string>>, mult int")
    cfg = DetectorConfig.plain().but(metric="hamming", encoding="md5", min_lines=1)
    assert detect(paths, cfg).count() == 0 and detect(paths, cfg.but(tau=0.31)).count() == 1


def test_variant_recall_order(spark, docs):
    from pathtwin.workloads.variants import QUERIES

    r = {m: {x["kind"]: x["n_found"] for x in QUERIES[f"var_recall_{m}"](spark, "/root/testdata/sf0.01").collect()} for m in ("ham", "lev", "lcs", "lcsmod", "jaccard")}
    n = variants(spark.read.parquet("/root/testdata/sf0.01/documents.parquet")).filter("kind = 'ty1'").count()
    for kind in ("ty1", "ty2"):
        assert all(r[m][kind] == n for m in r)
    for kind in ("vst3", "st3", "mt3", "embed_head"):
        assert r["lcsmod"][kind] >= r["lcs"][kind] >= r["lev"][kind] >= r["ham"][kind]
    assert r["lcsmod"]["embed_head"] == n and r["lcs"]["embed_head"] < n / 10
    assert r["jaccard"]["permute"] > 0.9 * n > r["lcsmod"]["permute"]


def test_components_of_chains_and_loops(spark):
    edges = [(i, i + 1) for i in range(200)] + [(1000, 1000), (2000, 1999), (None, 3)]
    got = {r["node"]: r["component"] for r in connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(201)) and got[1000] == 1000 and got[2000] == got[1999] == 1999
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_exceptions_reach_callers(spark):
    calls = spark.createDataFrame([("a", "b"), ("b", "c"), ("c", "a"), ("d", "a")], "caller string, callee string")
    throws = spark.createDataFrame([("c", "io")], "fn string, exc string")
    catches = spark.createDataFrame([("a", "io")], "fn string, exc string")
    assert {tuple(r) for r in propagate(calls, throws, catches).collect()} == {("c", "io"), ("b", "io")}


def test_measures(spark):
    pairs = spark.createDataFrame([(1, 2), (1, 3), (4, 5)], "left_id long, right_id long")
    truth = spark.createDataFrame([(1, 2, "ty1"), (2, 3, "ty1"), (4, 5, "st3")], "left_id long, right_id long, clone_type string")
    got = {r["clone_type"]: (r["n_pairs"], r["n_found"]) for r in M.recall(pairs, truth).collect()}
    assert got == {"ty1": (2, 1), "st3": (1, 1)}
    assert M.recall(pairs, truth, None).first()["n_found"] == 2 and M.total(pairs).first()[0] == 3
    o = M.overlap(pairs, truth).first()
    assert (o["only_a"], o["only_b"], o["both"]) == (1, 1, 2)
    verdicts = pairs.withColumn("verdict", F.col("left_id") == 1)
    assert M.precision(M.sample_for_judging(pairs, 3), verdicts).first()["precision"] == 0.666667


def test_no_nested_loop_in_detector_plan(docs):
    plan = detect(T.line_paths(docs), DetectorConfig())._jdf.queryExecution().toString()
    assert "CartesianProduct" not in plan and "BroadcastNestedLoopJoin" not in plan
