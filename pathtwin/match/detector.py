"""End-to-end detection: paths in, clone pairs out."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pathtwin.config import DetectorConfig
from pathtwin.match import blocks as B
from pathtwin.match import candidates as C
from pathtwin.match import sets as S
from pathtwin.metrics import set_distance_udf
from pathtwin.metrics.columns import may_be_near
from pathtwin.metrics.kernels import REGISTRY
from pathtwin.plans.components import connected_components
from pathtwin.plans.lineage import cut


def compare(pairs: DataFrame, sets: DataFrame, cfg: DetectorConfig, cutoff: float | None = None) -> DataFrame:
    """``pairs`` with ``distance`` (exact below ``cutoff``) and ``relation``, set-size short circuit applied, no threshold yet."""
    a = sets.select(F.col("fragment_id").alias("left_id"), F.col("paths").alias("pa"), F.col("n_paths").alias("na"))
    b = sets.select(F.col("fragment_id").alias("right_id"), F.col("paths").alias("pb"), F.col("n_paths").alias("nb"))
    joined = pairs.join(a, "left_id").join(b, "right_id")
    if cfg.max_set_factor is not None:
        joined = joined.filter(F.greatest("na", "nb") <= F.least("na", "nb") * F.lit(cfg.max_set_factor))
    if cutoff is not None:
        joined = joined.filter(may_be_near(cfg, F.col("pa"), F.col("pb"), F.col("na"), F.col("nb")))
    relation = F.when(F.col("na") == F.col("nb"), "strict").otherwise("partial")
    return joined.select("left_id", "right_id", F.round(set_distance_udf(cfg, cutoff)("pa", "pb"), 6).alias("distance"), relation.alias("relation"))


def classes(paths: DataFrame, cfg: DetectorConfig) -> tuple[DataFrame, DataFrame, DataFrame | None]:
    """Encoded paths and sets of the representatives, and the members ``fragment_id, rep_id, class_size``; with ``copy='off'`` of all fragments, and no members.

    Codes and sets are written once, since every list of candidates reads them.
    """
    encoded = cut(S.encoded_paths(paths.filter(F.col("n_lines") >= cfg.min_lines), cfg.encoding, cfg.merge))
    sets, members = S.description_sets(encoded), None
    if cfg.copy != "off":
        sets, members = S.collapse(cut(sets))
        sets = cut(sets)
        encoded = encoded.join(sets.select("fragment_id"), "fragment_id", "left_semi")
    return encoded, sets, members


def detect_classes(paths: DataFrame, cfg: DetectorConfig, made: tuple | None = None) -> tuple[DataFrame, DataFrame | None]:
    """Clone pairs of representatives ``left_id, right_id, distance, relation``, and the members ``fragment_id, rep_id, class_size``.

    With ``copy='off'`` every fragment stands for itself and there are no members. ``made`` is what ``classes`` gives, if it is at hand.
    """
    encoded, sets, members = made or classes(paths, cfg)
    if cfg.candidates == "blocks":
        return B.near_pairs(sets, cfg), members
    if cfg.candidates == "tiles":
        return B.near_in_tiles(sets, cfg), members
    return compare(C.candidates(encoded, sets, cfg), sets, cfg, cfg.tau).filter(F.col("distance") < F.lit(cfg.tau)), members


def detect_among(made: tuple[DataFrame, DataFrame, DataFrame | None], pairs: DataFrame, cfg: DetectorConfig) -> DataFrame:
    """Those of ``pairs(left_id, right_id)`` that ``detect`` reports, with their distance; ``made`` is what ``classes`` gives.

    Candidates that lose nothing say only which pairs are worth a look, so of given pairs each is compared and no other.
    """
    _, sets, members = made
    if members is None or cfg.copy == "lossy" or cfg.candidates == "lsh":
        raise ValueError("pairs are taken by classes of equal sets and without lossy candidates")
    at = members.select("fragment_id", "rep_id")
    p = pairs.select("left_id", "right_id").distinct().join(at.toDF("left_id", "p"), "left_id").join(at.toDF("right_id", "q"), "right_id")
    p = cut(p.select("left_id", "right_id", F.least("p", "q").alias("p"), F.greatest("p", "q").alias("q")))
    far = p.filter("p <> q").select(F.col("p").alias("left_id"), F.col("q").alias("right_id")).distinct()
    near = compare(far, sets, cfg, cfg.tau).filter(F.col("distance") < F.lit(cfg.tau)).select(F.col("left_id").alias("p"), F.col("right_id").alias("q"), "distance")
    return p.join(near, ["p", "q"]).select("left_id", "right_id", "distance").unionByName(p.filter("p = q").select("left_id", "right_id", F.lit(0.0).alias("distance")))


def detect(paths: DataFrame, cfg: DetectorConfig | None = None, made: tuple | None = None) -> DataFrame:
    """Rows ``left_id, right_id, distance, relation, via`` of clone pairs, ``left_id < right_id``; ``made`` as in ``detect_classes``.

    Fragments with equal sets are matched once. Every distance is of whole sets, so far paths keep their
    true distance; candidates only say which pairs are worth it.
    """
    cfg = cfg or DetectorConfig()
    pairs, members = detect_classes(paths, cfg, made)
    if members is None or cfg.copy == "lossy":
        return pairs.withColumn("via", F.lit("compared"))
    return S.expand(pairs, members)


#: Thresholds at which the nearest are looked for in turn.
STEPS = (0.3, 0.6)


def _sides(query: DataFrame, index: DataFrame, cfg: DetectorConfig) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """Encoded paths and description sets of both sides."""
    q, i = (cut(S.encoded_paths(x, cfg.encoding, cfg.merge)) for x in (query, index))
    return q, i, cut(S.description_sets(q)), cut(S.description_sets(i))


def compare_between(pairs: DataFrame, left: DataFrame, right: DataFrame, cfg: DetectorConfig, cutoff: float | None = None) -> DataFrame:
    """``pairs`` of sets of two sides with ``distance``, exact below ``cutoff``, set-size short circuit applied."""
    a = left.select(F.col("fragment_id").alias("left_id"), F.col("paths").alias("pa"), F.col("n_paths").alias("na"))
    b = right.select(F.col("fragment_id").alias("right_id"), F.col("paths").alias("pb"), F.col("n_paths").alias("nb"))
    joined = pairs.join(a, "left_id").join(b, "right_id")
    if cfg.max_set_factor is not None:
        joined = joined.filter(F.greatest("na", "nb") <= F.least("na", "nb") * F.lit(cfg.max_set_factor))
    if cutoff is not None:
        joined = joined.filter(may_be_near(cfg, F.col("pa"), F.col("pb"), F.col("na"), F.col("nb")))
    return joined.select("left_id", "right_id", F.round(set_distance_udf(cfg, cutoff)("pa", "pb"), 6).alias("distance"))


def nearest(query: DataFrame, index: DataFrame, cfg: DetectorConfig, k: int = 5) -> DataFrame:
    """The ``k`` nearest fragments of ``index`` for each fragment of ``query`` (both PATHS), ties by id; fewer only where ``index`` has fewer.

    Where blocks can be compared, every query meets every fragment there, and the ``k`` nearest of each block are ranked. For other
    metrics queries with ``k`` fragments within the first of ``STEPS`` are done, since none is missed below a threshold; the others go
    on to the next, and at last to all fragments with a common symbol. Fragments without one are at distance one, so
    for them the smallest ids will do. A query is not its own neighbour.
    """
    if not REGISTRY[cfg.metric][2] and cfg.metric not in ("jaccard", "cosine", "ngram", "jaro_winkler") or cfg.normalise != "longer":
        raise ValueError("the metric gives fragments without a common symbol no fixed distance")
    free = cfg.but(max_set_factor=None)
    if B.can_compare(free):
        qs, ix = (S.description_sets(S.encoded_paths(x, free.encoding, free.merge)) for x in (query, index))
        return _first(B.nearest_in_blocks(cut(qs), cut(ix), free, k), k)
    q, i, qs, ix = _sides(query, index, free)
    done, todo = [], qs.select("fragment_id")
    for tau in STEPS:
        step = free.but(tau=tau)
        some = q.join(todo, "fragment_id", "left_semi")
        # the modified LCS looks at its own threshold, so distances keep it and only candidates widen
        found = compare_between(C.prefix_pairs_between(some, i, step), qs, ix, free, None).filter(F.col("distance") < tau)
        best = cut(_first(found, k))
        enough = best.groupBy(F.col("left_id").alias("fragment_id")).agg(F.count("*").alias("n")).filter(F.col("n") >= k).select("fragment_id")
        done.append(best.join(enough.withColumnRenamed("fragment_id", "left_id"), "left_id", "left_semi"))
        todo = cut(todo.join(enough, "fragment_id", "left_anti"))
    symbols = lambda s: s.select("fragment_id", F.explode(F.array_distinct("code")).alias("c")).distinct()
    rest = symbols(q.join(todo, "fragment_id", "left_semi")).withColumnRenamed("fragment_id", "left_id")
    pairs = rest.join(symbols(i).withColumnRenamed("fragment_id", "right_id"), "c").filter("left_id <> right_id").select("left_id", "right_id").distinct()
    first = [r["fragment_id"] for r in ix.orderBy("fragment_id").limit(2 * k + 1).collect()]
    fill = todo.select(F.col("fragment_id").alias("left_id"), F.explode(F.array(*[F.lit(x).cast("long") for x in first])).alias("right_id")) if first else pairs
    pairs = pairs.unionByName(fill.filter("left_id <> right_id")).distinct()
    done.append(_first(compare_between(pairs, qs, ix, free), k))
    out = done[0]
    for d in done[1:]:
        out = out.unionByName(d)
    return out


def _first(scored: DataFrame, k: int) -> DataFrame:
    rank = F.row_number().over(Window.partitionBy("left_id").orderBy("distance", "right_id"))
    return scored.withColumn("rank", rank).filter(F.col("rank") <= k)


def against(new: DataFrame, index: DataFrame, cfg: DetectorConfig) -> DataFrame:
    """Pairs of new fragments with indexed ones within ``tau``; the index is not matched with itself."""
    q, i, qs, ix = _sides(new, index, cfg)
    found = compare_between(C.prefix_pairs_between(q, i, cfg), qs, ix, cfg, cfg.tau)
    return found.filter(F.col("distance") < F.lit(cfg.tau))


def groups(pairs: DataFrame) -> DataFrame:
    """Clone groups: components of the pairs."""
    return connected_components(pairs, "left_id", "right_id").select(F.col("node").alias("fragment_id"), F.col("component").alias("group_id"))
