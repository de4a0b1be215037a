"""Lossy joins, arriving slices and array metrics on small planted inputs."""

import datetime as dt

import numpy as np
from pyspark.sql import functions as F

from pathtwin.baselines.families import projection_bands
from pathtwin.metrics import columns as C
from pathtwin.streaming import windows as S


def test_projection_bands_find_planted_pairs(spark):
    rng = np.random.default_rng(3)
    base = rng.standard_normal((40, 32))
    rows = [(i, v.tolist()) for i, v in enumerate(base)] + [(100 + i, (v + 0.05 * rng.standard_normal(32)).tolist()) for i, v in enumerate(base)]
    rows += [(200, base[0].tolist()), (201, None), (202, [])]
    got = {(r.left_id, r.right_id): r.cosine for r in projection_bands(spark.createDataFrame(rows, "id long, v array<double>")).collect()}
    x = dict((i, np.array(v)) for i, v in rows if v)
    for (i, j), c in got.items():
        assert abs(x[i] @ x[j] / np.linalg.norm(x[i]) / np.linalg.norm(x[j]) - c) < 1e-5 and c >= 0.9
    assert (0, 200) in got and (100, 200) in got
    assert sum((i, 100 + i) in got for i in range(40)) >= 38


def test_late_rows_are_dropped_and_counted(spark):
    day = dt.datetime(2024, 1, 1)
    rows = [(i, day + dt.timedelta(hours=i), i % 3, "a" if i % 2 else "b", 0.0, "{}") for i in range(24 * 30)]
    events = spark.createDataFrame(rows, S.SCHEMA)
    late = (F.col("event_id") % 10 == 0) & (F.col("event_id") < 240)
    got = S.late_counts(events, late).agg(F.sum("n").alias("n"), F.sum("n_late").alias("late")).first()
    assert (got.n, got.late) == (len(rows) - 24, 24)


def test_empty_stream_has_no_rows(spark, tmp_path):
    at = str(tmp_path / "none")
    spark.createDataFrame([], S.SCHEMA).write.parquet(at)
    assert S.drained(S.windowed(S.event_stream(spark, at), "tumbling")).count() == 0


def test_ngram_edges(spark):
    rows = [(["a"], ["b"]), (["a"], ["a", "b"]), (["a", "b", "a", "b"], ["a", "b"]), ([], [])]
    df = spark.createDataFrame(rows, "a array<string>, b array<string>")
    assert [round(r[0], 6) for r in df.select(C.ngram(F.col("a"), F.col("b"))).collect()] == [0.0, 1.0, 0.5, 0.0]
