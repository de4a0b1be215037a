"""Candidate pairs of fragments.

``prefix`` is lossless wherever a metric bounds what two paths must share, and every way to it is an equi-join
of posting lists that starts from the rarest symbols:

* Metrics whose distance is at least the longer length less the common symbols (the LCS and edit families). The mean
  distance of a set is then at least the weight of its symbols that the other set lacks, where a path's nodes
  weigh alike and paths by their times. So the smaller set has a symbol of the other among the rarest ones
  that weigh ``tau`` together; two sets of one path each have it there both ways.
* The subclone branch of the modified LCS needs nine tenths of the shorter path in the longer, so one of the shorter
  path's rarest tenth of numbered nodes is a node of the longer.
* Jaccard on symbols, n-gram on numbered pairs of neighbours and Jaro-Winkler on numbered symbols need a known share of
  either path in common; for the cosine the rarest symbols that leave a vector's rest too short must be hit.
* Hamming without a length penalty needs an equal symbol at an equal place, or lengths so unlike that the
  distance is below ``tau`` whatever the symbols.

``deletions`` is lossless too, for fragments of few different symbols: short paths meet by what is left of them, see ``deletion_pairs``.

``shared`` takes pairs with any common symbol, ``bands`` pairs of similar size, ``lsh`` pairs with an equal band of
MinHash values (lossy), ``all`` everything (tests, and absolute distances from one on, which bound nothing). ``blocks`` makes no
candidates: every pair is compared; ``tiles`` compares what a bound on every pair leaves, without loss; see ``blocks.py`` for both.
"""

from __future__ import annotations

import math
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pathtwin.config import DetectorConfig
from pathtwin.metrics.kernels import REGISTRY
from pathtwin.plans.lineage import cut

EPS = 1e-9


def _paths(paths: DataFrame) -> DataFrame:
    """Distinct paths with ``pid`` and ``len``."""
    p = paths.select("fragment_id", "code", F.col("mult").cast("long").alias("mult"))
    return p.withColumn("pid", F.xxhash64("code")).withColumn("len", F.size("code"))


def numbered_nodes(paths: DataFrame) -> DataFrame:
    """Rows ``fragment_id, pid, len, node``: node is the hash of a symbol and its running number in the path."""
    n = _paths(paths).select("fragment_id", "pid", "len", F.explode("code").alias("c"))
    nth = F.row_number().over(Window.partitionBy("fragment_id", "pid", "c").orderBy(F.lit(0)))
    return n.select("fragment_id", "pid", "len", F.xxhash64("c", nth).alias("node"))


def _ratio_ok(a: Column, b: Column, cfg: DetectorConfig) -> Column:
    if cfg.max_set_factor is None:
        return F.lit(True)
    return F.greatest(a, b) <= F.least(a, b) * F.lit(cfg.max_set_factor)


def _pairs(x: Column, y: Column) -> list[Column]:
    return [F.least(x, y).alias("left_id"), F.greatest(x, y).alias("right_id")]


# --- weighted symbols of whole sets ------------------------------------------------------------------------


def weighted_symbols(paths: DataFrame) -> DataFrame:
    """Rows ``fragment_id, n_paths, single, node, w``: the weights of a fragment's symbols add up to one."""
    p = _paths(paths)
    size = p.groupBy("fragment_id").agg(F.sum("mult").alias("n_paths"), (F.count("*") == 1).alias("single"))
    nodes = F.when(F.col("len") == 0, F.array(F.lit(0).cast("long"))).otherwise(F.transform("code", lambda c: F.xxhash64(c)))
    rows = p.select("fragment_id", (F.col("mult") / F.greatest("len", F.lit(1))).alias("w"), F.explode(nodes).alias("node"))
    rows = rows.groupBy("fragment_id", "node").agg(F.sum("w").alias("w"))
    return rows.join(size, "fragment_id").select("fragment_id", "n_paths", "single", "node", (F.col("w") / F.col("n_paths")).alias("w"))


#: How much more weight than ``tau`` the listed symbols have: with it pairs are told apart by what they share in the lists.
REACH = 0.15


def ranked_symbols(symbols: DataFrame, index: DataFrame, tau: float) -> DataFrame:
    """``symbols`` with ``freq``, their number of fragments in ``index``, and ``rare``: whether the rarer ones before weigh less than ``tau`` and ``REACH``.

    ``listed`` is the weight of a fragment's rare symbols, ``last`` the greatest ``(freq, node)`` of them.
    """
    often = index.groupBy("node").agg(F.count("*").alias("freq"))
    ranked = symbols.join(often, "node", "left").withColumn("freq", F.coalesce("freq", F.lit(0)))
    whole = Window.partitionBy("fragment_id")
    before = F.coalesce(F.sum("w").over(whole.orderBy("freq", "node").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0.0))
    ranked = ranked.withColumn("rare", before < F.lit(tau + REACH + EPS))
    listed = F.sum(F.when(F.col("rare"), F.col("w"))).over(whole)
    return ranked.withColumns({"listed": listed, "last": F.max(F.when(F.col("rare"), F.struct("freq", "node"))).over(whole)})


def _ids() -> list[Column]:
    return [F.col("a.fragment_id").alias("x"), F.col("b.fragment_id").alias("y")]


def _covered(few: DataFrame, many: DataFrame, cfg: DetectorConfig) -> DataFrame:
    """Pairs ``x, y`` where ``y`` has enough of the rare symbols of ``x``, the set that is not larger; all of ``many`` is listed."""
    near = few.filter("rare").alias("a").join(many.select("fragment_id", "n_paths", "node").alias("b"), "node")
    near = near.filter((F.col("a.fragment_id") != F.col("b.fragment_id")) & (F.col("a.n_paths") <= F.col("b.n_paths")) & _ratio_ok(F.col("a.n_paths"), F.col("b.n_paths"), cfg))
    got = near.groupBy(*_ids()).agg(F.sum("w").alias("got"), F.first("listed").alias("listed"))
    return got.filter(F.col("got") > F.col("listed") - F.lit(cfg.tau + EPS)).select("x", "y")


def _alike(left: DataFrame, right: DataFrame, cfg: DetectorConfig, once: bool) -> DataFrame:
    """Pairs ``x, y`` of sets of one path, which must have enough of each other: rare symbols of both meet.

    Up to the end of the shorter list every common symbol is in both lists, so that side's weight decides.
    """
    near = left.filter("rare").alias("a").join(right.filter("rare").alias("b"), "node")
    near = near.filter(F.col("a.fragment_id") < F.col("b.fragment_id") if once else F.col("a.fragment_id") != F.col("b.fragment_id"))
    near = near.filter(_ratio_ok(F.col("a.n_paths"), F.col("b.n_paths"), cfg))
    first = F.col("a.last") <= F.col("b.last")
    spare = F.when(first, F.col("a.listed")).otherwise(F.col("b.listed"))
    got = near.groupBy(*_ids()).agg(F.sum(F.when(first, F.col("a.w")).otherwise(F.col("b.w"))).alias("got"), F.first(spare).alias("listed"))
    return got.filter(F.col("got") > F.col("listed") - F.lit(cfg.tau + EPS)).select("x", "y")


def cover_pairs(left: DataFrame, right: DataFrame | None, cfg: DetectorConfig) -> list[DataFrame]:
    """Pairs ``x, y`` by weighted symbols, of one corpus (``right`` is None) or between two."""
    a = weighted_symbols(left)
    b = a if right is None else weighted_symbols(right)
    index = a if right is None else b
    a = cut(ranked_symbols(a, index, cfg.tau))
    b = a if right is None else cut(ranked_symbols(b, index, cfg.tau))
    out = [_alike(a.filter("single"), b.filter("single"), cfg, right is None)]
    out += [_covered(a.filter("not single"), b, cfg), _covered(a.filter("single"), b.filter("not single"), cfg)]
    if right is not None:
        back = [_covered(b.filter("not single"), a, cfg), _covered(b.filter("single"), a.filter("not single"), cfg)]
        out += [f.select(F.col("y").alias("x"), F.col("x").alias("y")) for f in back]
    return out


# --- short paths by what is left of them -------------------------------------------------------------------

#: Ways to leave symbols out of a path up to which a length counts as short.
WAYS = 120


def left_out(tau: float) -> list[int]:
    """For each short length from 0 on, how many symbols of the longer path a distance below ``tau`` can lack."""
    out: list[int] = []
    while len(out) < 64:
        n = len(out)
        k = max((k for k in range(n + 1) if not k or round(k / n, 6) < tau), default=0)
        if math.comb(n, k) > WAYS:
            break
        out.append(k)
    return out


def deletion_pairs(paths: DataFrame, cfg: DetectorConfig) -> list[DataFrame]:
    """Pairs ``x, y`` of one corpus. Two single paths, of which the longer is short, meet in a common subsequence as long as the threshold asks for.

    If the longer has ``n`` symbols and may lack ``k``, both hold a subsequence of ``n - k``, so both are listed under every one
    they have, with ``n``. Pairs with a longer path, or with sets of several paths, go by weighted symbols.
    """
    if cfg.metric not in ("lcs", "levenshtein", "alignment", "hamming") or cfg.normalise != "longer" or cfg.tau >= 1:
        raise ValueError("the metric bounds no common subsequence")
    lacks = left_out(cfg.tau)
    top = len(lacks) - 1
    one = paths.groupBy("fragment_id").agg(F.count("*").alias("n"), F.first("code").alias("code")).filter("n = 1").select("fragment_id", "code", F.size("code").alias("len"))
    # equal paths are one class by now, unless classes are off
    lengths = [(n, k) for n, k in enumerate(lacks) if k or cfg.copy == "off"]
    under = F.array(*[F.struct(F.lit(n).alias("longer"), F.lit(n - k).alias("keep")) for n, k in lengths]) if lengths else F.expr("array()").cast("array<struct<longer: int, keep: int>>")
    rows = one.select("fragment_id", "code", "len", F.explode(F.filter(under, lambda u: (u["longer"] >= F.col("len")) & (u["keep"] <= F.col("len")))).alias("u"))
    left = F.array(F.struct(F.col("code").alias("s"), F.lit(0).alias("at")))

    def drop_one(s: Column) -> Column:
        """Each way to leave out one more symbol, not before the last one left out."""
        n = F.size(s["s"])
        at = F.filter(F.sequence(s["at"], F.greatest(s["at"], n - 1)), lambda i: i < n)
        return F.transform(at, lambda i: F.struct(F.concat(F.slice(s["s"], 1, i), F.slice(s["s"], i + 2, n)).alias("s"), i.alias("at")))

    listed = None
    for k in range(max((k for _, k in lengths), default=0) + 1):
        posts = rows.filter(F.col("len") - F.col("u.keep") == k).select("fragment_id", "len", F.col("u.longer").alias("longer"), F.explode(F.transform(left, lambda s: s["s"])).alias("s"))
        listed = posts if listed is None else listed.unionByName(posts)
        left = F.flatten(F.transform(left, drop_one))
    listed = cut(listed.select("fragment_id", "len", F.xxhash64("longer", "s").alias("node"), "longer").distinct())
    met = listed.filter("len = longer").alias("a").join(listed.alias("b"), "node").filter((F.col("a.fragment_id") != F.col("b.fragment_id")) & (F.col("a.longer") == F.col("b.longer")))
    out = [met.select(F.col("a.fragment_id").alias("x"), F.col("b.fragment_id").alias("y"))]

    symbols = weighted_symbols(paths)
    ranked = cut(ranked_symbols(symbols, symbols, cfg.tau).join(one.select("fragment_id", "len"), "fragment_id", "left"))
    single, several = ranked.filter("single"), ranked.filter("not single")
    some = single.filter(F.col("len") >= math.floor((1 - cfg.tau) * (top + 1)))
    out.append(_alike(some.filter(F.col("len") > top), some, cfg, False))
    return [*out, _covered(several, ranked, cfg), _covered(single, several, cfg)]


# --- single paths ------------------------------------------------------------------------------------------


def sub_pairs(left: DataFrame, right: DataFrame | None, cfg: DetectorConfig) -> list[DataFrame]:
    """Pairs ``x, y`` with a path that may lie in a path of the other, too long for the plain distance."""
    long_enough = lambda p: p.filter(F.size("code") >= cfg.sub_min_len)
    a = numbered_nodes(long_enough(left))
    b = a if right is None else numbered_nodes(long_enough(right))

    def inside(few: DataFrame, many: DataFrame) -> DataFrame:
        often = many.groupBy("node").agg(F.count("*").alias("freq"))
        pos = F.row_number().over(Window.partitionBy("fragment_id", "pid").orderBy(F.coalesce("freq", F.lit(0)), "node"))
        part = few.join(often, "node", "left").withColumn("pos", pos).filter(F.col("pos") <= F.floor(F.col("len") * F.lit(cfg.sub_slack + EPS)) + 1)
        posts = lambda n: n.select("fragment_id", "len", "node").distinct()
        met = posts(part).alias("a").join(posts(many).alias("b"), "node").filter(F.col("a.fragment_id") != F.col("b.fragment_id"))
        met = met.filter(F.col("a.len") * F.lit(1 - cfg.sub_slack) <= F.col("b.len") * F.lit(1 - cfg.tau) + 1)
        return met.select(F.col("a.fragment_id").alias("x"), F.col("b.fragment_id").alias("y"))

    if right is None:
        return [inside(a, a)]
    return [inside(a, b), inside(b, a).select(F.col("y").alias("x"), F.col("x").alias("y"))]


def _least_jaro(tau: float) -> float:
    """Jaro similarity that a distance below ``tau`` needs, with the full bonus for equal beginnings above 0.7."""
    return max(0.7, 1 - tau / 0.6) if tau <= 0.3 else 1 - tau


def elements(paths: DataFrame, metric: str, tau: float) -> tuple[DataFrame, float]:
    """Rows ``fragment_id, pid, n, node`` of what a metric counts, and the share of either path's that a distance below ``tau`` needs in common."""
    p = _paths(paths)
    if metric == "jaccard":
        rows = p.select("fragment_id", "pid", F.explode(F.array_distinct(F.when(F.col("len") == 0, F.array(F.lit(0).cast("long"))).otherwise(F.col("code")))).alias("node"))
        share = 1 - tau
    elif metric == "ngram":
        pair = lambda x, i: F.xxhash64(x, F.get("code", i + 1))
        grams = F.when(F.col("len") < 2, F.array(F.xxhash64(F.lit("whole"), "pid"))).otherwise(F.transform(F.slice("code", 1, F.greatest(F.col("len") - 1, F.lit(0))), pair))
        n = p.select("fragment_id", "pid", F.explode(grams).alias("c"))
        nth = F.row_number().over(Window.partitionBy("fragment_id", "pid", "c").orderBy(F.lit(0)))
        rows, share = n.select("fragment_id", "pid", F.xxhash64("c", nth).alias("node")), (1 - tau) / (1 + tau)
    else:
        rows, share = numbered_nodes(paths).select("fragment_id", "pid", "node"), 3 * _least_jaro(tau) - 2
    n = rows.groupBy("fragment_id", "pid").agg(F.count("*").alias("n"))
    return rows.join(n, ["fragment_id", "pid"]), share


def overlap_pairs(left: DataFrame, right: DataFrame | None, cfg: DetectorConfig) -> list[DataFrame]:
    """Pairs with two paths that may have the needed share in common: both have a common element among their rarest."""
    a, share = elements(left, cfg.metric, cfg.tau)
    b = a if right is None else elements(right, cfg.metric, cfg.tau)[0]
    often = b.groupBy("node").agg(F.count("*").alias("freq"))
    order = Window.partitionBy("fragment_id", "pid").orderBy(F.coalesce("freq", F.lit(0)), "node")

    def rarest(x: DataFrame) -> DataFrame:
        keep = F.col("n") - F.ceil(F.round(F.col("n") * F.lit(max(share, 0.0)), 9)) + 1
        x = x.join(often, "node", "left").withColumn("pos", F.row_number().over(order)).filter(F.col("pos") <= keep)
        return x.select("fragment_id", "n", "node").distinct()

    near = rarest(a).alias("a").join(rarest(b).alias("b"), "node").filter(F.col("a.fragment_id") != F.col("b.fragment_id"))
    near = near.filter(F.least("a.n", "b.n") >= F.greatest("a.n", "b.n") * F.lit(share) - EPS)
    return [near.select(F.col("a.fragment_id").alias("x"), F.col("b.fragment_id").alias("y"))]


def cosine_pairs(left: DataFrame, right: DataFrame | None, cfg: DetectorConfig) -> list[DataFrame]:
    """Pairs with two paths that have a common symbol among those that leave each vector's rest long enough."""

    def counts(paths: DataFrame) -> DataFrame:
        return _paths(paths).select("fragment_id", "pid", F.explode("code").alias("node")).groupBy("fragment_id", "pid", "node").agg(F.count("*").alias("c"))

    a = counts(left)
    b = a if right is None else counts(right)
    often = b.groupBy("node").agg(F.count("*").alias("freq"))
    whole = Window.partitionBy("fragment_id", "pid")
    order = whole.orderBy(F.coalesce("freq", F.lit(0)), "node").rowsBetween(Window.currentRow, Window.unboundedFollowing)
    least = F.lit((1 - cfg.tau) ** 2 - EPS)

    def rarest(x: DataFrame) -> DataFrame:
        square = F.col("c") * F.col("c")
        kept = x.join(often, "node", "left").withColumns({"rest": F.sum(square).over(order), "all": F.sum(square).over(whole)})
        return kept.filter(F.col("rest") >= F.col("all") * least).select("fragment_id", "node").distinct()

    near = rarest(a).alias("a").join(rarest(b).alias("b"), "node").filter(F.col("a.fragment_id") != F.col("b.fragment_id"))
    return [near.select(F.col("a.fragment_id").alias("x"), F.col("b.fragment_id").alias("y"))]


def place_pairs(left: DataFrame, right: DataFrame | None, cfg: DetectorConfig) -> list[DataFrame]:
    """For Hamming without a length penalty: equal symbols at equal places, or one path shorter than ``tau`` of the other.

    The second kind are clones by that metric, whatever they hold, so their number is that of the result.
    """

    def posts(paths: DataFrame) -> DataFrame:
        return _paths(paths).select("fragment_id", F.posexplode("code").alias("i", "c")).select("fragment_id", F.xxhash64("i", "c").alias("node")).distinct()

    def lengths(paths: DataFrame) -> DataFrame:
        band = lambda c: F.floor(F.log2(c + F.lit(1.0)))
        p = _paths(paths).select("fragment_id", "len").distinct()
        return p.withColumns({"band": band(F.col("len")), "top": band(F.col("len") * F.lit(cfg.tau))})

    def unlike(short: DataFrame, far: DataFrame) -> DataFrame:
        far = far.select("fragment_id", "len", F.explode(F.sequence(F.lit(0).cast("long"), "top")).alias("band"))
        met = short.alias("a").join(far.alias("b"), "band").filter((F.col("a.fragment_id") != F.col("b.fragment_id")) & (F.col("a.len") < F.col("b.len") * F.lit(cfg.tau) + EPS))
        return met.select(F.col("a.fragment_id").alias("x"), F.col("b.fragment_id").alias("y"))

    a, la = posts(left), lengths(left)
    b, lb = (a, la) if right is None else (posts(right), lengths(right))
    same = a.alias("a").join(b.alias("b"), "node").filter(F.col("a.fragment_id") != F.col("b.fragment_id"))
    out = [same.select(F.col("a.fragment_id").alias("x"), F.col("b.fragment_id").alias("y")), unlike(la, lb)]
    return out if right is None else [*out, unlike(lb, la).select(F.col("y").alias("x"), F.col("x").alias("y"))]


def _prefix(left: DataFrame, right: DataFrame | None, cfg: DetectorConfig) -> DataFrame:
    if cfg.metric == "hamming_free":
        parts = place_pairs(left, right, cfg)
    elif REGISTRY[cfg.metric][2] or cfg.metric == "exact":
        parts = cover_pairs(left, right, cfg)
        if cfg.metric == "lcs_mod":
            parts += sub_pairs(left, right, cfg)
    elif cfg.metric == "cosine":
        parts = cosine_pairs(left, right, cfg)
    else:
        parts = overlap_pairs(left, right, cfg)
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def prefix_pairs(paths: DataFrame, cfg: DetectorConfig) -> DataFrame:
    """Pairs ``left_id < right_id`` of one corpus that may be within ``tau``."""
    return _prefix(paths, None, cfg).select(*_pairs(F.col("x"), F.col("y"))).distinct()


def prefix_pairs_between(left: DataFrame, right: DataFrame, cfg: DetectorConfig) -> DataFrame:
    """Pairs ``left_id`` of ``left`` and ``right_id`` of ``right`` that may be within ``tau``."""
    return _prefix(left, right, cfg).select(F.col("x").alias("left_id"), F.col("y").alias("right_id")).distinct()


def shared_pairs(paths: DataFrame) -> DataFrame:
    nodes = paths.select("fragment_id", F.explode(F.array_distinct("code")).alias("node")).distinct()
    pairs = nodes.alias("a").join(nodes.alias("b"), "node").filter(F.col("a.fragment_id") < F.col("b.fragment_id"))
    return pairs.select(F.col("a.fragment_id").alias("left_id"), F.col("b.fragment_id").alias("right_id")).distinct()


def band_pairs(sets: DataFrame, cfg: DetectorConfig) -> DataFrame:
    """Fragments whose numbers of paths, and of nodes a path, fall into the same or neighbouring logarithmic bands.

    The second band is a filter of its own only where the metric bounds lengths; elsewhere sizes alone decide.
    """
    factor = cfg.max_set_factor or 1.7
    s = sets.select("fragment_id", "n_paths", F.floor(F.round(F.log("n_paths") / math.log(factor), 9)).alias("band"))
    near = s.withColumn("band", F.explode(F.array("band", F.col("band") + 1)))
    pairs = s.alias("a").join(near.alias("b"), "band").filter((F.col("a.fragment_id") != F.col("b.fragment_id")) & _ratio_ok(F.col("a.n_paths"), F.col("b.n_paths"), cfg))
    return pairs.select(*_pairs(F.col("a.fragment_id"), F.col("b.fragment_id"))).distinct()


def lsh_band_pairs(paths: DataFrame, bands: int = 16, rows: int = 3) -> DataFrame:
    """Lossy: MinHash over the symbols of a fragment, equal in all rows of a band."""
    nodes = paths.select("fragment_id", F.explode("code").alias("c")).distinct()
    least = nodes.groupBy("fragment_id").agg(*[F.min(F.xxhash64("c", F.lit(i))).alias(f"h{i}") for i in range(bands * rows)])
    keys = F.array(*[F.xxhash64(F.lit(b), *[F.col(f"h{b * rows + r}") for r in range(rows)]) for b in range(bands)])
    k = least.select("fragment_id", F.explode(keys).alias("key"))
    pairs = k.alias("a").join(k.alias("b"), "key").filter(F.col("a.fragment_id") < F.col("b.fragment_id"))
    return pairs.select(F.col("a.fragment_id").alias("left_id"), F.col("b.fragment_id").alias("right_id")).distinct()


def all_pairs(sets: DataFrame) -> DataFrame:
    """Every pair; quadratic, for small tests."""
    s = sets.select("fragment_id")
    return s.alias("a").join(s.alias("b"), F.col("a.fragment_id") < F.col("b.fragment_id")).select(F.col("a.fragment_id").alias("left_id"), F.col("b.fragment_id").alias("right_id"))


def candidates(paths: DataFrame, sets: DataFrame, cfg: DetectorConfig) -> DataFrame:
    how = cfg.candidates
    if how == "prefix" and cfg.normalise == "none" and cfg.tau >= 1:
        how = "all"
    joined = lambda parts: reduce(DataFrame.unionByName, parts).select(*_pairs(F.col("x"), F.col("y"))).distinct()
    ways = {
        "prefix": lambda: prefix_pairs(paths, cfg), "shared": lambda: shared_pairs(paths), "bands": lambda: band_pairs(sets, cfg),
        "deletions": lambda: joined(deletion_pairs(paths, cfg)), "lsh": lambda: lsh_band_pairs(paths), "all": lambda: all_pairs(sets),
    }
    return ways[how]()
