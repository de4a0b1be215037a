"""Pairs mapped back to files and lines, and the kinds of pairs that one detector alone reports."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def locate(pairs: DataFrame, fragments: DataFrame) -> DataFrame:
    """``pairs`` with file and lines of both sides; ``fragments(fragment_id, file, start_line, end_line)``."""
    out = pairs
    for side in ("left", "right"):
        named = fragments.select(F.col("fragment_id").alias(f"{side}_id"), *[F.col(c).alias(f"{side}_{c}") for c in ("file", "start_line", "end_line")])
        out = out.join(named, f"{side}_id")
    return out


def category(common: Column, len_a: Column, len_b: Column, overlap: Column) -> Column:
    """``subclone`` where the shorter path lies almost whole in a much longer one, ``structural`` where the nodes agree but not their order."""
    shorter, longer = F.least(len_a, len_b), F.greatest(len_a, len_b)
    sub = (common >= 0.9 * shorter) & (shorter < 0.7 * longer)
    structural = (overlap >= 0.7) & (common < 0.7 * longer)
    return F.when(sub, "subclone").when(structural, "structural").otherwise("other")
