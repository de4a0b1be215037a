"""Connected components by repeated contraction towards the neighbour of least hash."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathtwin.plans.lineage import cut, drop


def connected_components(edges: DataFrame, left: str = "a", right: str = "b") -> DataFrame:
    """Rows ``(node, component)`` for every end of an edge; ``component`` is the smallest node reachable.

    Each round points every node at the node of least hash in its closed neighbourhood and contracts
    along the pointers; hashing makes pointer chains short whatever the ids, so the number of edges
    falls by a constant share a round. Nothing is collected; each round is a written table. Self
    loops and repeated edges are allowed, null ends are ignored, no edge gives no row.
    """
    e = edges.select(F.col(left).cast("long").alias("a"), F.col(right).cast("long").alias("b")).dropna()
    first = e = cut(e)
    hashed = lambda c: F.struct(F.xxhash64(c).alias("h"), c.alias("v"))
    nodes = e.select(F.explode(F.array("a", "b")).alias("node")).distinct()
    e = e.filter("a <> b")
    chain, old = None, None
    while not e.isEmpty():
        both = e.unionByName(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
        point = both.groupBy("a").agg(F.min(hashed(F.col("b"))).alias("m"))
        point = cut(point.select("a", F.least(F.col("m"), hashed(F.col("a")))["v"].alias("to")).filter("a <> to"))
        by_a = point.select("a", F.col("to").alias("to_a"))
        by_b = point.select(F.col("a").alias("b"), F.col("to").alias("to_b"))
        moved = e.join(by_a, "a", "left").join(by_b, "b", "left")
        moved = moved.select(F.coalesce("to_a", "a").alias("a"), F.coalesce("to_b", "b").alias("b"))
        nxt = cut(moved.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).filter("a <> b").distinct())
        step = point.select(F.col("a").alias("root"), F.col("to"))
        if chain is None:
            follow = cut(nodes.withColumn("root", F.col("node")).join(step, "root", "left").select("node", F.coalesce("to", "root").alias("root")))
        else:
            follow = cut(chain.join(step, "root", "left").select("node", F.coalesce("to", "root").alias("root")))
        for x in (chain, old, point):
            if x is not None:
                drop(x)
        chain, old, e = follow, nxt, nxt
    if chain is None:
        return nodes.withColumn("component", F.col("node"))
    drop(first)
    least = chain.groupBy("root").agg(F.min("node").alias("component"))
    return chain.join(least, "root").select("node", "component")
