"""Distributed suffix sorting of a whole table by the difference cover modulo three.

All texts are one string of symbols, each text closed by a symbol of its own, so that no match crosses
texts. The triples at the places of remainder one and two are sorted over the cluster and named by their
order; while names repeat, the string of names is sorted by recursion; the suffixes of remainder zero are
then sorted by their first symbol and the next rank, and merged in. Neighbours in the order whose first
``length`` bytes agree are repeats.

Every sort is a range-partitioned one whose places are partition offsets plus rows; the driver sees one
number a partition. A string of at most ``LOCAL`` symbols is sorted in one task, a fixed bound. The order is
exact at any size, but every level moves its whole string several times, as the README measures;
``suffix_dedup`` narrows the text down first and is what the query and the pipeline run.

A null text is empty. An empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pathtwin.llm.common import map_slices
from pathtwin.llm.suffix_dedup import _TABLE, _mix, _powers, _texts, suffix_order
from pathtwin.plans.lineage import cut, settled

#: Symbols that one task sorts.
LOCAL = 1 << 16
_ROW = (1 << 33) - 1


def numbered(df: DataFrame, *order: str) -> DataFrame:
    """``df`` with ``place``, its rank from one in the order, which must have no ties."""
    laid = cut(df.repartitionByRange(*order).sortWithinPartitions(*order).withColumn("__id", F.monotonically_increasing_id()))
    part = F.shiftright("__id", 33)
    sizes = sorted((r["p"], r["n"]) for r in laid.groupBy(part.alias("p")).agg(F.count("*").alias("n")).collect())
    starts = np.cumsum([0, *(n for _, n in sizes)]).tolist()
    offsets = df.sparkSession.createDataFrame([(p, s) for (p, _), s in zip(sizes, starts, strict=False)], "__p long, __start long")
    placed = laid.withColumn("__p", part).join(F.broadcast(offsets), "__p")
    return placed.withColumn("place", F.col("__start") + F.col("__id").bitwiseAND(F.lit(_ROW)) + 1).drop("__id", "__p", "__start")


def _triples(s: DataFrame) -> DataFrame:
    """Rows ``pos, a, b, c``: each place with its symbol and the two that follow, zero past the end."""
    seen = F.array(*[F.struct((F.col("pos") - k).alias("pos"), F.lit(k).alias("k"), "sym") for k in range(3)])
    rows = s.select(F.explode(seen).alias("x")).select("x.*").filter("pos >= 0")
    at = lambda k: F.coalesce(F.max(F.when(F.col("k") == k, F.col("sym"))), F.lit(0)).alias("abc"[k])
    return rows.groupBy("pos").agg(*[at(k) for k in range(3)])


def suffix_ranks(s: DataFrame, n: int, local: int = LOCAL) -> DataFrame:
    """Rows ``pos, rank`` of the suffixes of ``s(pos, sym)``, places 0 to n - 1, symbols from one on."""
    spark = s.sparkSession
    if n <= max(local, 3):

        def alone(parts: Iterator[dict]) -> Iterator[dict]:
            got = list(parts)
            pos = np.concatenate([np.array(p["pos"], np.int64) for p in got]) if got else np.zeros(0, np.int64)
            sym = np.zeros(n, np.int64)
            if n:
                sym[pos] = np.unique(np.concatenate([np.array(p["sym"], np.int64) for p in got]), return_inverse=True)[1] + 1
            yield {"pos": suffix_order(sym) if n else [], "rank": np.arange(1, n + 1)}

        return cut(map_slices(s.select("pos", "sym").coalesce(1), alone, "pos long, rank long"))
    t = cut(_triples(s))
    sample = t.filter("pos % 3 <> 0")
    if n % 3 == 1:  # a place past the end keeps the two halves apart
        sample = sample.unionByName(spark.createDataFrame([(n, 0, 0, 0)], "pos long, a long, b long, c long"))
    names = numbered(sample.select("a", "b", "c").distinct(), "a", "b", "c")
    named = cut(sample.join(names, ["a", "b", "c"]).select("pos", F.col("place").alias("name")))
    ones, size, kinds = (n + (n % 3 == 1) + 1) // 3, named.count(), names.count()
    if kinds == size:
        rank = named.withColumnRenamed("name", "rank")
    else:
        lower = F.when(F.col("pos") % 3 == 1, F.floor((F.col("pos") - 1) / 3)).otherwise(ones + F.floor((F.col("pos") - 2) / 3))
        inner = suffix_ranks(named.select(lower.cast("long").alias("pos"), F.col("name").alias("sym")), size, local)
        upper = F.when(F.col("pos") < ones, 3 * F.col("pos") + 1).otherwise(3 * (F.col("pos") - ones) + 2)
        rank = inner.select(upper.cast("long").alias("pos"), "rank")
    extra = 1 if n % 3 == 1 else 0
    rank = cut(rank.filter(F.col("pos") < n).withColumn("rank", F.col("rank") - extra))
    ahead = lambda k: rank.select((F.col("pos") - k).alias("pos"), F.col("rank").alias(f"r{k}"))
    keyed = t.join(ahead(1), "pos", "left").join(ahead(2), "pos", "left")
    keyed = cut(keyed.select("pos", "a", "b", F.coalesce("r1", F.lit(0)).alias("r1"), F.coalesce("r2", F.lit(0)).alias("r2"), (F.col("pos") % 3).alias("kind")))
    zero = keyed.filter("kind = 0")
    own = numbered(zero.select("pos", "a", "r1"), "a", "r1").select("pos", F.col("place").alias("own"))
    by_one = numbered(keyed.filter("kind <> 2").select("pos", "kind", "a", "r1"), "a", "r1", "kind").filter("kind = 0")
    by_two = numbered(keyed.filter("kind <> 1").select("pos", "kind", "a", "b", "r2"), "a", "b", "r2", "kind").filter("kind = 0")
    less = own.join(by_one.select("pos", F.col("place").alias("p1")), "pos").join(by_two.select("pos", F.col("place").alias("p2")), "pos")
    less = less.select("pos", (F.col("p1") + F.col("p2") - 2 * F.col("own")).alias("value"), F.lit(0).alias("late"), "own")
    merged = less.unionByName(rank.select("pos", (F.col("rank") - 1).alias("value"), F.lit(1).alias("late"), F.col("rank").alias("own")))
    return numbered(merged, "value", "late", "own").select("pos", F.col("place").alias("rank"))


def _string(docs: DataFrame, length: int) -> tuple[DataFrame, int]:
    """Rows ``pos, sym, k, th, at, window`` of all texts laid end to end, and their number; ``window`` is a digest of the next ``length`` bytes."""
    laid = numbered(_texts(docs).withColumn("tie", F.monotonically_increasing_id()), "k", "th", "tie").withColumn("size", F.octet_length("bytes") + 1)
    laid = cut(laid.withColumn("block", F.shiftright("place", 10)))
    blocks = laid.groupBy("block").agg(F.sum("size").alias("total"))
    before = F.coalesce(F.sum("total").over(Window.orderBy("block").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = blocks.select("block", before.alias("base"))
    inside = F.coalesce(F.sum("size").over(Window.partitionBy("block").orderBy("place").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    laid = laid.withColumn("inside", inside).join(starts, "block").withColumn("start", F.col("base") + F.col("inside"))
    n = laid.agg(F.sum("size")).first()[0] or 0

    def spell(parts: Iterator[dict]) -> Iterator[dict]:
        for p in parts:
            for k, th, text, start, place in zip(p["k"], p["th"], p["bytes"], p["start"], p["place"], strict=True):
                b = np.frombuffer(text, np.uint8)
                up, down = _powers(len(b) + 1)
                total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_TABLE[b] * up[: len(b)])])
                at, fits = np.arange(len(b) + 1), max(0, len(b) - length + 1)
                window = np.zeros(len(b) + 1, np.uint64)
                window[:fits] = _mix((total[length:] - total[:-length])[:fits] * down[:fits]) | np.uint64(1)
                sym = np.append(b.astype(np.int64) + 1, 257 + place)
                yield {"pos": start + at, "sym": sym, "k": np.full(len(at), k), "th": np.full(len(at), th), "at": at, "window": window.view(np.int64)}

    rows = map_slices(laid.select("k", "th", "bytes", "start", "place"), spell, "pos long, sym long, k long, th long, at long, window long")
    return cut(rows), int(n)


def repeated_windows(docs: DataFrame, length: int, local: int = LOCAL) -> DataFrame:
    """Rows ``k, th, at``: places of ``length`` bytes that also start elsewhere, by the global suffix order."""

    def made() -> DataFrame:
        string, n = _string(docs, length)
        ranked = string.filter("window <> 0").join(suffix_ranks(string.select("pos", "sym"), n, local), "pos")
        one = ranked.select("rank", "window")
        near = one.select((F.col("rank") + 1).alias("rank"), "window").unionByName(one.select((F.col("rank") - 1).alias("rank"), "window"))
        return ranked.join(near, ["rank", "window"], "left_semi").select("k", "th", "at")

    return settled(made)
