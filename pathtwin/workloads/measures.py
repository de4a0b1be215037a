"""Measures over several detectors: recall of the rival families, composition, categories, incremental matching."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathtwin.baselines import families as B
from pathtwin.config import DetectorConfig
from pathtwin.evaluation import measures as M
from pathtwin.evaluation.sweeps import run_times
from pathtwin.frontends import text_lines as T
from pathtwin.match.detector import against, detect
from pathtwin.match.report import category
from pathtwin.metrics import columns as C
from pathtwin.metrics import distance_udf
from pathtwin.plans.lineage import cut
from pathtwin.sources.io import read_table
from pathtwin.sql import oracles as O
from pathtwin.workloads import variants as V
from pathtwin.workloads.documents import PLAIN, _docs

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
FAMILIES = {"bag": B.token_bag, "set": B.token_set, "line": B.line_lcs, "win": B.line_windows, "run": B.token_runs, "gram": B.ngram_index}


FIRST, OWN = " UNION ALL ", "a.id // 16 = b.id // 16"


def _recall(spark: SparkSession, sf_dir: str, min_lines: int, rivals: dict, setups: dict, mode: str = "blind") -> DataFrame:
    """Pairs of an original and its variant that each detector finds, by kind."""
    docs = V.family(spark, sf_dir, min_lines)
    truth, out = V.family_truth(docs), None
    found = {k: lambda f=f: f(docs, min_lines) for k, f in rivals.items()}
    found |= {k: lambda c=c: detect(T.line_paths(docs, mode), c.but(min_lines=min_lines)) for k, (c, _) in setups.items()}
    for name, find in found.items():
        part = M.recall(find(), truth, "kind").withColumn("detector", F.lit(name))
        out = part if out is None else out.unionByName(part)
    return out.select("detector", "kind", "n_pairs", "n_found", "recall")


def _recall_sql(min_lines: int, rivals: dict, setups: dict, mode: str = "blind") -> str:
    def own(sql: str) -> str:
        """A detector's SQL on the variants, kept to pairs of one origin: recall needs no others."""
        if min_lines != 15:
            sql = sql.replace(O.fragments(15), O.fragments(min_lines)).replace(O.fragments(15, "blind"), O.fragments(min_lines, "blind")).replace(O.fragments(15, "keep_head"), O.fragments(min_lines, "keep_head"))
        return sql.replace("FROM documents", "FROM fam").replace("a.id < b.id", f"a.id < b.id AND {OWN}").replace("a.id <> b.id", f"a.id <> b.id AND {OWN}")

    queries = {k: own(V.ORACLES[f"base_{k}"]) for k in rivals} | {k: own(V.setup_sql(k, min_lines, mode)) for k in setups}
    parts = [
        f"SELECT '{k}' AS detector, kind, count(*) AS n_pairs, count(hit.right_id) AS n_found, round(count(hit.right_id) / count(*), 6) AS recall "
        f"FROM (SELECT doc_id // 16 * 16 AS l, doc_id AS r, kind FROM fam WHERE kind <> 'origin') LEFT JOIN ({q}) hit ON hit.left_id = l AND hit.right_id = r GROUP BY kind"
        for k, q in queries.items()
    ]
    return f"WITH {V.family_sql(min_lines)} " + FIRST.join(parts)


QUERIES["var_recall_baselines"] = lambda s, d: _recall(s, d, 15, FAMILIES, {})
ORACLES["var_recall_baselines"] = _recall_sql(15, FAMILIES, {})
QUERIES["var_recall_detector"] = lambda s, d: _recall(s, d, 15, {}, V.SETUPS)
ORACLES["var_recall_detector"] = _recall_sql(15, {}, V.SETUPS)
SMALL = {k: FAMILIES[k] for k in ("bag", "set", "line", "win", "gram")}
QUERIES["var_recall_min6"] = lambda s, d: _recall(s, d, 6, SMALL, {"default": V.SETUPS["default"]})
ORACLES["var_recall_min6"] = _recall_sql(6, SMALL, {"default": V.SETUPS["default"]})


def var_recall_learned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall of the learned family by kind, trained on half of the origins and scored on the others."""
    v, docs = V._var(spark, sf_dir), V.family(spark, sf_dir)
    half = F.pmod(F.xxhash64("origin_id"), F.lit(2)) == 0
    found = V.learned_pairs(v.filter(half), docs.filter(F.pmod(F.xxhash64(F.floor(F.col("doc_id") / 16)), F.lit(2)) == 1))
    truth = V.family_truth(docs.filter(F.pmod(F.xxhash64(F.floor(F.col("doc_id") / 16)), F.lit(2)) == 1))
    return M.recall(found, truth, "kind")


QUERIES["var_recall_learned"] = var_recall_learned

#: Sweeps of the default set-up over the labelled variants: thresholds, least sizes, caps on the difference of lengths.
TAUS, LEAST, CAPS = (0.1, 0.2, 0.3, 0.4), tuple(range(6, 21, 2)), (0, 3, 7, 15)


def _score(found: DataFrame, truth: DataFrame) -> list:
    """One row of recall and precision."""
    same = F.floor(F.col("left_id") / 16) == F.floor(F.col("right_id") / 16)
    reported = found.agg(F.count("*").alias("n_reported"), F.count_if(same).alias("n_same_origin")).withColumn("one", F.lit(1))
    hit = M.recall(found, truth, None).withColumn("one", F.lit(1))
    return hit.join(reported, "one").drop("one").withColumn("precision", F.round(F.col("n_same_origin") / F.col("n_reported"), 6))


def _swept(name: str, rows: dict) -> DataFrame:
    out = None
    for value, row in rows.items():
        row = row.withColumn(name, F.lit(value))
        out = row if out is None else out.unionByName(row)
    return out


def _score_sql(name: str, kind: str, rows: dict[object, str], truth: str = "TRUE") -> str:
    """Recall and precision for each value from SQL of its pairs; ``truth`` may name the value as ``$``."""
    parts = []
    for value, sql in rows.items():
        t = f"(SELECT doc_id // 16 * 16 AS l, doc_id AS r FROM fam WHERE kind <> 'origin' AND {truth.replace('$', str(value))})"
        parts.append(
            f"SELECT CAST({value} AS {kind}) AS {name}, n_pairs, n_found, round(n_found / n_pairs, 6) AS recall, n_reported, n_same_origin, round(n_same_origin / n_reported, 6) AS precision FROM "
            f"(SELECT count(*) AS n_reported, count(*) FILTER (left_id // 16 = right_id // 16) AS n_same_origin FROM ({sql})), "
            f"(SELECT count(*) AS n_pairs, count(h.left_id) AS n_found FROM {t} LEFT JOIN ({sql}) h ON h.left_id = l AND h.right_id = r)"
        )
    return f"WITH {V.family_sql(15 if name != 'min_lines' else 6)} " + FIRST.join(parts)


def var_tau_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall and precision of the default set-up at each threshold."""
    docs = V.family(spark, sf_dir)
    paths, truth = T.line_paths(docs), V.family_truth(docs)
    return _swept("tau", {t: _score(detect(paths, DetectorConfig(tau=t)), truth) for t in TAUS})


QUERIES["var_tau_sweep"] = var_tau_sweep
ORACLES["var_tau_sweep"] = _score_sql("tau", "DOUBLE", {t: V.setup_sql("default", tau=t) for t in TAUS})


def var_cap_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall and precision of the default set-up at each greatest difference of lengths."""
    docs = V.family(spark, sf_dir)
    paths, truth = T.line_paths(docs), V.family_truth(docs)
    return _swept("cap", {c: _score(detect(paths, DetectorConfig(max_len_diff=c)), truth) for c in CAPS})


QUERIES["var_cap_sweep"] = var_cap_sweep
ORACLES["var_cap_sweep"] = _score_sql("cap", "INTEGER", {c: V.setup_sql("default", cap=c) for c in CAPS})


def var_min_size_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall and precision of the default set-up at each least size: one run at the smallest, truth and pairs of which both sides are large enough."""
    docs = V.family(spark, sf_dir, min(LEAST))
    n = T.fragments(docs).select("fragment_id", "n_lines")
    sized = lambda df: df.join(n.toDF("left_id", "na"), "left_id").join(n.toDF("right_id", "nb"), "right_id").withColumn("k", F.least("na", "nb"))
    found = cut(sized(detect(T.line_paths(docs), DetectorConfig(min_lines=min(LEAST)))).select("left_id", "right_id", "k"))
    truth = cut(sized(V.family_truth(docs)).select("left_id", "right_id", "k"))
    return _swept("min_lines", {m: _score(found.filter(F.col("k") >= m), truth.filter(F.col("k") >= m)) for m in LEAST})


QUERIES["var_min_size_sweep"] = var_min_size_sweep


def _min_size_sql() -> str:
    sized = f"sz AS MATERIALIZED (SELECT id, n FROM (WITH {O.fragments(1).replace('FROM documents', 'FROM fam')} SELECT id, n FROM f)), found AS MATERIALIZED (SELECT left_id, right_id, least(a.n, b.n) AS k FROM ({V.setup_sql('default', min(LEAST))}) JOIN sz a ON a.id = left_id JOIN sz b ON b.id = right_id)"
    truth = "least((SELECT n FROM sz WHERE id = doc_id), (SELECT n FROM sz WHERE id = doc_id // 16 * 16)) >= $"
    rows = {m: f"SELECT left_id, right_id FROM found WHERE k >= {m}" for m in LEAST}
    return _score_sql("min_lines", "INTEGER", rows, truth).replace(V.family_sql(6), f"{V.family_sql(6)}, {sized}")


ORACLES["var_min_size_sweep"] = _min_size_sql()


def var_composition(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Labelled pairs by kind and band of similarity, with subtotals."""
    similarity = F.round(1 - distance_udf("lcs")("s", "v"), 6)
    rows = V._codes(V._var(spark, sf_dir), "md5").select("kind", M.band(similarity).alias("band"))
    return rows.rollup("kind", "band").agg(F.count("*").alias("n_pairs"))


QUERIES["var_composition"] = var_composition
ORACLES["var_composition"] = (
    f"WITH {V._variants_sql()}, m AS (SELECT kind, s AS sa, v AS sb, {O.lcs('s', 'v')} AS z FROM x), d AS (SELECT kind, round(1 - {O.distance('lcs', 'sa', 'sb')}, 6) AS s FROM m), "
    "b AS (SELECT kind, CASE WHEN s >= 0.9 THEN 'vst3' WHEN s >= 0.7 THEN 'st3' WHEN s >= 0.5 THEN 'mt3' ELSE 'ty4' END AS band FROM d) SELECT kind, band, count(*) AS n_pairs FROM b GROUP BY ROLLUP (kind, band)"
)


def doc_exclusive_categories(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs that only the modified LCS on blind lines or only the set family reports, by category."""
    docs = _docs(spark, sf_dir)
    ours, sets = detect(T.line_paths(docs, "blind"), DetectorConfig.plain().but(max_set_factor=None)).select("left_id", "right_id"), B.token_set(docs)
    alone = M.exclusive(ours, [sets]).withColumn("side", F.lit("ours")).unionByName(M.exclusive(sets, [ours]).withColumn("side", F.lit("set")))
    f = T.fragments(docs, min_lines=15).select("fragment_id", F.transform("nodes", lambda x: F.xxhash64(x)).alias("s"))
    both = alone.join(f.toDF("left_id", "a"), "left_id").join(f.toDF("right_id", "b"), "right_id")
    longer = F.greatest(F.size("a"), F.size("b"))
    common = longer - distance_udf("lcs", DetectorConfig.plain().but(normalise="none"))("a", "b")
    overlap = C.common_items(F.col("a"), F.col("b")) / longer
    named = both.withColumn("common", common).withColumn("category", category(F.col("common"), F.size("a"), F.size("b"), overlap))
    return named.groupBy("side", "category").agg(F.count("*").alias("n_pairs"))


QUERIES["doc_exclusive_categories"] = doc_exclusive_categories
ORACLES["doc_exclusive_categories"] = (
    f"WITH {O.fragments(15)}, l AS (SELECT left_id, right_id FROM ({O.clones('lcs_mod', 15, 'blind')})), t AS ({V.ORACLES['base_set']}), e AS (SELECT 'ours' AS side, * FROM (SELECT * FROM l EXCEPT SELECT * FROM t) UNION ALL SELECT 'set', * FROM (SELECT * FROM t EXCEPT SELECT * FROM l)), "
    f"m AS (SELECT side, a.s AS sa, b.s AS sb, {O.lcs('a.s', 'b.s')} AS z, coalesce(list_sum(list_transform(list_distinct(a.s), lambda k: least({O.times('a.s', 'k')}, {O.times('b.s', 'k')}))), 0) AS o FROM e JOIN f a ON a.id = left_id JOIN f b ON b.id = right_id), "
    "n AS (SELECT side, z, o, least(len(sa), len(sb)) AS lo, greatest(len(sa), len(sb)) AS hi FROM m) "
    "SELECT side, CASE WHEN z >= 0.9 * lo AND lo < 0.7 * hi THEN 'subclone' WHEN o / hi >= 0.7 AND z < 0.7 * hi THEN 'structural' ELSE 'other' END AS category, count(*) AS n_pairs FROM n GROUP BY ALL"
)


def doc_exclusive_rivals(spark: SparkSession, sf_dir: str) -> DataFrame:
    """For each rival: pairs that only the modified LCS on blind lines, or only the rival reports, by category."""
    docs = _docs(spark, sf_dir)
    ours = cut(detect(T.line_paths(docs, "blind"), PLAIN.but(max_set_factor=None, candidates="tiles")).select("left_id", "right_id"))
    alone = None
    for name, find in FAMILIES.items():
        theirs = cut(find(docs))
        part = M.exclusive(ours, [theirs]).withColumn("side", F.lit("ours")).unionByName(M.exclusive(theirs, [ours]).withColumn("side", F.lit("rival")))
        part = part.withColumn("rival", F.lit(name))
        alone = part if alone is None else alone.unionByName(part)
    f = T.fragments(docs, min_lines=15).select("fragment_id", F.transform("nodes", lambda x: F.xxhash64(x)).alias("s"))
    both = alone.join(f.toDF("left_id", "a"), "left_id").join(f.toDF("right_id", "b"), "right_id")
    longer = F.greatest(F.size("a"), F.size("b"))
    common = longer - distance_udf("lcs", PLAIN.but(normalise="none"))("a", "b")
    overlap = C.common_items(F.col("a"), F.col("b")) / longer
    named = both.withColumn("common", common).withColumn("category", category(F.col("common"), F.size("a"), F.size("b"), overlap))
    return named.groupBy("rival", "side", "category").agg(F.count("*").alias("n_pairs"))


QUERIES["doc_exclusive_rivals"] = doc_exclusive_rivals
_RIVALS = FIRST.join(
    f"SELECT '{k}' AS rival, 'ours' AS side, * FROM (SELECT * FROM l EXCEPT SELECT left_id, right_id FROM ({V.ORACLES[f'base_{k}']})) UNION ALL SELECT '{k}', 'rival', * FROM (SELECT left_id, right_id FROM ({V.ORACLES[f'base_{k}']}) EXCEPT SELECT * FROM l)" for k in FAMILIES
)
ORACLES["doc_exclusive_rivals"] = (
    f"WITH {O.fragments(15)}, l AS MATERIALIZED (SELECT left_id, right_id FROM ({O.clones('lcs_mod', 15, 'blind')})), e AS ({_RIVALS}), "
    f"m AS (SELECT rival, side, a.s AS sa, b.s AS sb, {O.lcs('a.s', 'b.s')} AS z, coalesce(list_sum(list_transform(list_distinct(a.s), lambda k: least({O.times('a.s', 'k')}, {O.times('b.s', 'k')}))), 0) AS o FROM e JOIN f a ON a.id = left_id JOIN f b ON b.id = right_id), "
    "n AS (SELECT rival, side, z, o, least(len(sa), len(sb)) AS lo, greatest(len(sa), len(sb)) AS hi FROM m) "
    "SELECT rival, side, CASE WHEN z >= 0.9 * lo AND lo < 0.7 * hi THEN 'subclone' WHEN o / hi >= 0.7 AND z < 0.7 * hi THEN 'structural' ELSE 'other' END AS category, count(*) AS n_pairs FROM n GROUP BY ALL"
)


def doc_incremental(spark: SparkSession, sf_dir: str) -> DataFrame:
    """New documents (ids divisible by five) against all others as the index; the index is not matched with itself."""
    paths = T.line_paths(_docs(spark, sf_dir), "exact", 15)
    cfg = DetectorConfig.plain().but(metric="lcs", max_set_factor=None)
    return against(paths.filter("fragment_id % 5 = 0"), paths.filter("fragment_id % 5 <> 0"), cfg).select(F.col("left_id").alias("new_id"), F.col("right_id").alias("index_id"), "distance")


QUERIES["doc_incremental"] = doc_incremental
ORACLES["doc_incremental"] = (
    f"SELECT CASE WHEN left_id % 5 = 0 THEN left_id ELSE right_id END AS new_id, CASE WHEN left_id % 5 = 0 THEN right_id ELSE left_id END AS index_id, distance FROM ({O.clones('lcs', 15)}) WHERE (left_id % 5 = 0) <> (right_id % 5 = 0)"
)

QUERIES["vec_lsh_join"] = lambda spark, sf_dir: B.projection_bands(read_table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("v")))


def run_time_by_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of the default and the fast set-up and of the rival families on nested subsets of the documents, least size 6; ``speedup`` is against the default."""
    own = {"default": DetectorConfig(min_lines=6), "fast": DetectorConfig.fast().but(min_lines=6)}
    ways = {k: lambda docs, c=c: detect(T.line_paths(docs), c) for k, c in own.items()} | {k: lambda docs, f=f: f(docs, 6) for k, f in FAMILIES.items()}
    rows = run_times(_docs(spark, sf_dir), ways, (10, 100))
    base = {p: s for n, p, _, _, s, _ in rows if n == "default"}
    schema = "setup string, percent int, n_lines long, n_reported long, seconds double, lines_per_second double, speedup double"
    return spark.createDataFrame([(*r, round(base[r[1]] / max(r[4], 1e-3), 3)) for r in rows], schema)


QUERIES["run_time_by_size"] = run_time_by_size
