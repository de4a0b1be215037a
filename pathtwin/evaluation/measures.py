"""Recall, precision and overlap of detectors."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def recall(pairs: DataFrame, truth: DataFrame, by: str | None = "clone_type") -> DataFrame:
    """Truth pairs found, absolute and relative, in each type; ``by=None`` takes them all together."""
    hit = pairs.select("left_id", "right_id").distinct().withColumn("hit", F.lit(1))
    joined = truth.join(hit, ["left_id", "right_id"], "left")
    rows = joined.groupBy(by) if by else joined.groupBy()
    return rows.agg(F.count("*").alias("n_pairs"), F.count("hit").alias("n_found")).withColumn("recall", F.round(F.col("n_found") / F.col("n_pairs"), 6))


def total(pairs: DataFrame) -> DataFrame:
    """Distinct unordered pairs."""
    return pairs.select(F.least("left_id", "right_id").alias("l"), F.greatest("left_id", "right_id").alias("r")).distinct().agg(F.count("*").alias("n_reported"))


def sample_for_judging(pairs: DataFrame, n: int = 400, seed: int = 1) -> DataFrame:
    """The ``n`` pairs of least seeded hash: a repeatable sample."""
    key = F.md5(F.concat_ws("|", F.lit(str(seed)), "left_id", "right_id"))
    return pairs.withColumn("sample_key", key).orderBy("sample_key").limit(n)


def precision(sample: DataFrame, verdicts: DataFrame) -> DataFrame:
    """Share judged true; several verdicts a pair count by majority."""
    vote = verdicts.groupBy("left_id", "right_id").agg((F.avg(F.col("verdict").cast("double")) > 0.5).alias("yes"))
    return sample.join(vote, ["left_id", "right_id"]).agg(F.count("*").alias("n_judged"), F.round(F.avg(F.col("yes").cast("double")), 6).alias("precision"))


def overlap(a: DataFrame, b: DataFrame) -> DataFrame:
    """Sizes of both differences and of the intersection."""
    x, y = (p.select("left_id", "right_id").distinct() for p in (a, b))
    side = x.withColumn("in_a", F.lit(True)).join(y.withColumn("in_b", F.lit(True)), ["left_id", "right_id"], "full")
    in_a, in_b = F.coalesce("in_a", F.lit(False)), F.coalesce("in_b", F.lit(False))
    return side.agg(F.count_if(in_a & ~in_b).alias("only_a"), F.count_if(in_b & ~in_a).alias("only_b"), F.count_if(in_a & in_b).alias("both"))


def exclusive(a: DataFrame, others: list[DataFrame]) -> DataFrame:
    """Pairs of ``a`` that none of ``others`` reports."""
    rest = others[0].select("left_id", "right_id")
    for o in others[1:]:
        rest = rest.unionByName(o.select("left_id", "right_id"))
    return a.join(rest.distinct(), ["left_id", "right_id"], "left_anti")


def band(similarity: Column) -> Column:
    """Similarity bands, lower bound included."""
    return F.when(similarity >= 0.9, "vst3").when(similarity >= 0.7, "st3").when(similarity >= 0.5, "mt3").otherwise("ty4")


def composition(truth: DataFrame) -> DataFrame:
    return truth.groupBy("clone_type").agg(F.count("*").alias("n_pairs"))
