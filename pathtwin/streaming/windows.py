"""Streaming over events: windows, duplicates, late rows and per-user state, with batch parity."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from pathtwin.plans.lineage import shared_folder

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str) -> DataFrame:
    """Event files as a stream."""
    return spark.readStream.schema(SCHEMA).parquet(path)


def _timed(events: DataFrame) -> DataFrame:
    """Watermarks need zoned time; times without a zone are taken in the session's."""
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def _plain(c: str):
    return F.col(c).cast("timestamp_ntz")


def _run(stream: DataFrame, at: str, mode: str) -> None:
    """One pass over what there is. A batch that is run again replaces its own rows."""

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{at}/out/{'last' if mode == 'complete' else f'batch-{number}'}")

    stream.writeStream.outputMode(mode).option("checkpointLocation", f"{at}/checkpoint").foreachBatch(keep).trigger(availableNow=True).start().awaitTermination()


def _output(stream: DataFrame, at: str) -> DataFrame:
    return stream.sparkSession.read.schema(stream.schema).parquet(f"{at}/out/*")


def _place(spark: SparkSession) -> str:
    return f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"


def drained(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a stream over what there is and returns its last state (``complete``) or all its rows (``append``)."""
    at = _place(stream.sparkSession)
    stream.sparkSession.createDataFrame([], stream.schema).write.parquet(f"{at}/out/last")
    _run(stream, at, mode)
    return _output(stream, at)


def arriving(slices: list[DataFrame], plan: Callable[[DataFrame], DataFrame], mode: str = "update") -> DataFrame:
    """Rows that ``plan`` sends while ``slices`` of events arrive one after the other; state and watermark carry over."""
    spark = slices[0].sparkSession
    at, fields = _place(spark), [c.split() for c in SCHEMA.split(", ")]
    for s in slices:
        s.select(*[F.col(n).cast(t).alias(n) for n, t in fields]).write.mode("append").parquet(f"{at}/in")
        stream = plan(event_stream(spark, f"{at}/in"))
        _run(stream, at, mode)
    return _output(stream, at)


def late_counts(events: DataFrame, late: Column, slack_days: int = 3) -> DataFrame:
    """Rows ``start, event_type, n, n_late``: events by day that a stream counts, and those it drops, when ``late`` ones come last.

    Old events arrive first, those of the last ``slack_days`` move the watermark, then the late ones come.
    """
    edge = events.agg(F.max("ts").alias("ts")).first()["ts"]
    marked = events.withColumn("__late", late)
    old = F.col("ts") < F.lit(edge).cast("timestamp_ntz") - F.make_dt_interval(F.lit(slack_days)) if edge else F.lit(True)
    sent = arriving([marked.filter(~F.col("__late") & old), marked.filter(~F.col("__late") & ~old), marked.filter("__late")], lambda s: windowed(s, "tumbling"))
    counted = sent.groupBy("start", "event_type").agg(F.max("n").alias("n"))
    total = events.groupBy(F.date_trunc("day", "ts").cast("timestamp_ntz").alias("start"), "event_type").agg(F.count("*").alias("total"))
    n = F.coalesce("n", F.lit(0))
    return total.join(counted, ["start", "event_type"], "left").select("start", "event_type", n.alias("n"), (F.col("total") - n).alias("n_late"))


def windowed(events: DataFrame, kind: str) -> DataFrame:
    """Event counts by window; the same plan for a stream and for a table."""
    w = {"tumbling": F.window("ts", "1 day"), "sliding": F.window("ts", "1 day", "12 hours"), "session": F.session_window("ts", "6 hours")}[kind]
    keys = [w.alias("w"), "user_id"] if kind == "session" else [w.alias("w"), "event_type"]
    return _timed(events).withWatermark("ts", "2 days").groupBy(*keys).agg(F.count("*").alias("n")).select(_plain("w.start").alias("start"), _plain("w.end").alias("stop"), keys[1], "n")


def without_repeats(events: DataFrame, delay: str = "2 days") -> DataFrame:
    """First event of each id within the watermark."""
    return _timed(events).withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"])


def session_sets(events: DataFrame) -> DataFrame:
    """Description sets of sessions: sorted distinct symbols of each user's session."""
    w = F.session_window("ts", "6 hours")
    kinds = F.array_sort(F.collect_set("event_type"))
    return _timed(events).withWatermark("ts", "2 days").groupBy(w.alias("w"), "user_id").agg(F.array_join(kinds, ",").alias("kinds"), F.count("*").alias("n")).select(_plain("w.start").alias("start"), "user_id", "kinds", "n")


def flow_state(events: DataFrame) -> DataFrame:
    """Per-user flow graph carried over batches: a row an edge when it is first seen."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def step(key: tuple, batches, state: GroupState):
        last, known = state.get if state.exists else ("entry", "")
        seen = set(known.split(";")) if known else set()
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        out = []
        for kind in rows["event_type"]:
            edge = f"{last}>{kind}"
            if edge not in seen:
                seen.add(edge)
                out.append((key[0], edge))
            last = kind
        state.update((last, ";".join(sorted(seen))))
        yield pd.DataFrame(out, columns=["user_id", "edge"])

    grouped = events.select("user_id", "ts", "event_id", "event_type").groupBy("user_id")
    return grouped.applyInPandasWithState(step, "user_id long, edge string", "last string, known string", "append", GroupStateTimeout.NoTimeout)
