from pyspark.sql import functions as F

from pathtwin.config import DetectorConfig
from pathtwin.evaluation import sweeps
from pathtwin.frontends import text_lines as T
from pathtwin.frontends.java import parse_file, parse_methods
from pathtwin.match import report
from pathtwin.match.sets import encoded_paths
from pathtwin.sources import index
from pathtwin.sql import functions as sql_functions

SF = "/root/testdata/sf0.001"


def test_method_source_and_index(spark):
    index.register(spark)
    files = spark.read.format("method_files").option("files", 60).load()
    assert files.count() == 60
    encoded = encoded_paths(parse_methods(files), "md5")
    index.write_index(encoded, "pt_index", 4)
    assert index.read_index(spark, "pt_index").count() == encoded.count()


def test_exception_edges_and_bad_files():
    text = "class A { int f(int a) { try { g(a); h(a); } catch (E e) { return 1; } finally { k(); } return a; } }"
    (m,), error = parse_file(text)
    assert error is None and m.name == "f"
    catch = next(n for n, t in m.nodes.items() if t == ["CATCH"])
    assert len([a for a, b in m.edges if b == catch]) == 2
    assert parse_file("int f() { if ( }")[1]


def test_sql_names(spark):
    sql_functions.register(spark)
    assert spark.sql("SELECT path_distance_lcs(array(1L, 2L, 3L, 4L), array(1L, 3L, 4L, 9L)) AS d").first()["d"] == 0.25


def test_sweeps_and_report(spark):
    paths = T.line_paths(spark.read.parquet(f"{SF}/documents.parquet"), "blind", 6)
    cfg = DetectorConfig.plain().but(metric="lcs", encoding="md5", min_lines=6)
    n = {r["tau"]: r["count"] for r in sweeps.sweep_tau(paths, cfg, [0.1, 0.2, 0.4]).groupBy("tau").count().collect()}
    assert n.get(0.1, 0) <= n.get(0.2, 0) <= n[0.4]
    w = sweeps.work(paths, cfg)
    assert w["classes"] <= w["fragments"] and w["merged_paths"] <= w["paths"]
    shares = sweeps.nested_subsets(paths.select("fragment_id", "n_lines"), [0.1, 0.5, 1.0], 1).groupBy("share").agg(F.sum("n_lines").alias("n")).collect()
    assert sum(r["n"] for r in shares) == paths.agg(F.sum("n_lines")).first()[0]
    pairs = spark.createDataFrame([(1, 2)], "left_id long, right_id long")
    frags = spark.createDataFrame([(1, "a", 1, 9), (2, "b", 3, 7)], "fragment_id long, file string, start_line int, end_line int")
    assert report.locate(pairs, frags).first()["right_file"] == "b"
    c = spark.range(1).select(report.category(F.lit(10), F.lit(10), F.lit(40), F.lit(0.2)).alias("x"), report.category(F.lit(5), F.lit(10), F.lit(10), F.lit(0.9)).alias("y")).first()
    assert (c["x"], c["y"]) == ("subclone", "structural")
