"""From paths to encoded description sets, classes of equal sets, and back."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathtwin import encode


def encoded_paths(paths: DataFrame, how: str, merge: str = "identical") -> DataFrame:
    """Rows ``fragment_id, n_lines, code, mult``; equal paths of a fragment are merged and their times added.

    With ``merge='one_node'`` a path that differs from an earlier one (in sorted order) in one node joins it.
    """
    coded = paths.select("fragment_id", "n_lines", F.transform("nodes", lambda t: encode.code(t, how)).alias("code"), "mult")
    if merge == "none":
        return coded
    merged = coded.groupBy("fragment_id", "n_lines", "code").agg(F.sum("mult").cast("long").alias("mult"))
    return merged if merge == "identical" else merge_one_node(merged)


def one_node_apart(paths: list[tuple[tuple, int]]) -> list[tuple[tuple, int]]:
    """Greedy in sorted order: a path joins the first kept path of its length that differs from it in one node."""
    kept: list[list] = []
    by_hole: dict = {}
    for code, times in sorted(paths):
        holes = [(i, code[:i], code[i + 1 :]) for i in range(len(code))]
        hit = min((by_hole[h] for h in holes if h in by_hole), default=None)
        if hit is not None:
            kept[hit][1] += times
            continue
        for h in holes:
            by_hole.setdefault(h, len(kept))
        kept.append([code, times])
    return [(code, times) for code, times in kept]


_PATHS = "array<struct<code: array<bigint>, mult: bigint>>"


def merge_one_node(paths: DataFrame) -> DataFrame:
    """``paths`` with those merged that differ in one node; fragments of one path pass by on the JVM."""

    @F.arrow_udf(_PATHS)
    def merged(column: pa.Array) -> pa.Array:
        out = [[{"code": list(c), "mult": m} for c, m in one_node_apart([(tuple(p["code"]), p["mult"]) for p in s])] for s in column.to_pylist()]
        return pa.array(out, pa.list_(pa.struct([("code", pa.list_(pa.int64())), ("mult", pa.int64())])))

    sets = paths.groupBy("fragment_id").agg(F.first("n_lines").alias("n_lines"), F.collect_list(F.struct("code", "mult")).alias("paths"))
    many = sets.filter(F.size("paths") > 1).withColumn("paths", merged("paths"))
    return sets.filter(F.size("paths") == 1).unionByName(many).select("fragment_id", "n_lines", F.explode("paths").alias("p")).select("fragment_id", "n_lines", "p.code", "p.mult")


def description_sets(encoded: DataFrame) -> DataFrame:
    """Rows ``fragment_id, n_lines, paths, n_paths, n_nodes, set_key``, one a fragment."""
    one = F.struct("code", F.col("mult").cast("long").alias("mult"))
    sets = encoded.groupBy("fragment_id").agg(F.first("n_lines").alias("n_lines"), F.array_sort(F.collect_list(one)).alias("paths"), F.sum("mult").alias("n_paths"), F.sum(F.size("code") * F.col("mult")).alias("n_nodes"))
    return sets.withColumn("set_key", F.md5(F.to_json("paths")))


def collapse(sets: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Representatives of the classes of equal sets, and all members ``fragment_id, rep_id``.

    Classes can be huge, so members stay rows.
    """
    reps = sets.groupBy("set_key").agg(F.min("fragment_id").alias("rep_id"), F.count("*").alias("class_size"))
    members = sets.select("fragment_id", "set_key").join(reps, "set_key").select("fragment_id", "rep_id", "class_size")
    return sets.join(reps.select(F.col("rep_id").alias("fragment_id"), "class_size"), "fragment_id"), members


def expand(pairs: DataFrame, members: DataFrame) -> DataFrame:
    """Pairs of class members: results of representatives are copied, members of one class are at distance zero."""
    m = members.filter("class_size > 1")
    a = members.select(F.col("fragment_id").alias("x"), F.col("rep_id").alias("left_id"), F.col("class_size").alias("na"))
    b = members.select(F.col("fragment_id").alias("y"), F.col("rep_id").alias("right_id"), F.col("class_size").alias("nb"))
    via = F.when((F.col("x") == F.col("left_id")) & (F.col("y") == F.col("right_id")), "compared").otherwise("copied")
    across = pairs.join(a, "left_id").join(b, "right_id").select(F.least("x", "y").alias("left_id"), F.greatest("x", "y").alias("right_id"), "distance", "relation", via.alias("via"))
    inside = m.alias("p").join(m.alias("q"), "rep_id").filter(F.col("p.fragment_id") < F.col("q.fragment_id"))
    inside = inside.select(F.col("p.fragment_id").alias("left_id"), F.col("q.fragment_id").alias("right_id"), F.lit(0.0).alias("distance"), F.lit("strict").alias("relation"), F.lit("copied").alias("via"))
    return across.unionByName(inside)
