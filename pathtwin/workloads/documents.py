"""Detection workloads on ``documents``."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathtwin.config import DetectorConfig
from pathtwin.frontends import text_lines as T
from pathtwin.functions import windows
from pathtwin.match import sets as S
from pathtwin.match.blocks import distance_counts
from pathtwin.match.detector import classes, detect, detect_classes, groups, nearest
from pathtwin.metrics import distance_udf
from pathtwin.metrics.columns import as_characters
from pathtwin.sources.io import read_table
from pathtwin.sql import oracles as O

METRICS = ("hamming", "hamming_free", "levenshtein", "damerau", "alignment", "lcs", "lcs_mod", "jaccard", "cosine", "ngram", "jaro_winkler")
SHORT = {"hamming": "ham", "hamming_free": "ham_free", "levenshtein": "lev", "damerau": "dam", "alignment": "nw", "lcs": "lcs", "lcs_mod": "lcsmod", "jaccard": "jaccard", "cosine": "cosine", "ngram": "ngram", "jaro_winkler": "jaro"}

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def _docs(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_table(spark, sf_dir, "documents", "doc_id", "text")


def _pairs(df: DataFrame) -> DataFrame:
    return df.select("left_id", "right_id", "distance")


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


@query("doc_fragments", f"WITH {O.fragments(15)} SELECT id AS fragment_id, n AS n_lines, md5(array_to_string(s, chr(10))) AS digest FROM f")
def doc_fragments(spark: SparkSession, sf_dir: str) -> DataFrame:
    f = T.fragments(_docs(spark, sf_dir), min_lines=15)
    return f.select("fragment_id", F.col("n_lines").cast("long").alias("n_lines"), F.md5(F.array_join("nodes", "\n")).alias("digest"))


def _class_sql(mode: str) -> str:
    return f"WITH {O.fragments(6, mode)}, c AS (SELECT s, min(id) AS k, count(*) AS n FROM f GROUP BY s) SELECT id AS fragment_id, k AS class_id, c.n AS class_size FROM f JOIN c ON f.s = c.s WHERE c.n > 1"


@query("doc_t1_exact", _class_sql("exact"))
def doc_t1_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _equal(spark, sf_dir, "exact")


@query("doc_t2_blind", _class_sql("blind"))
def doc_t2_blind(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _equal(spark, sf_dir, "blind")


def _equal(spark: SparkSession, sf_dir: str, mode: str) -> DataFrame:
    """Every document that equals another, with its class: no pairs, so a class may be of any size."""
    f = T.fragments(_docs(spark, sf_dir), mode, 6).select("fragment_id", F.md5(F.array_join("nodes", "\n")).alias("key"))
    classes = f.groupBy("key").agg(F.min("fragment_id").alias("class_id"), F.count("*").alias("class_size")).filter("class_size > 1")
    return f.join(classes, "key").select("fragment_id", "class_id", "class_size")


def clone_rows(paths: DataFrame, cfg: DetectorConfig) -> DataFrame:
    """Rows ``pair`` of the first documents of two classes of equal sets, and rows ``member`` of a class's first and each other document.

    Together they hold every clone pair, though a class of any size gives one row a document.
    """
    pairs, members = detect_classes(paths, cfg)
    rest = members.filter("fragment_id <> rep_id").select(F.lit("member").alias("row"), F.col("rep_id").alias("left_id"), F.col("fragment_id").alias("right_id"), F.lit(0.0).alias("distance"))
    return pairs.select(F.lit("pair").alias("row"), "left_id", "right_id", "distance").unionByName(rest)


def _detector(cfg: DetectorConfig, mode: str = "exact"):
    return lambda spark, sf_dir: clone_rows(T.line_paths(_docs(spark, sf_dir), mode), cfg)


PLAIN = DetectorConfig.plain()
CAP = DetectorConfig().max_len_diff
#: Without a length penalty the result is a share of all pairs, so lists of candidates save nothing.
HAM_FREE = PLAIN.but(metric="hamming_free", candidates="blocks")
for _m in METRICS:
    QUERIES[f"doc_clones_{SHORT[_m]}"] = _detector(HAM_FREE if _m == "hamming_free" else PLAIN.but(metric=_m))
    ORACLES[f"doc_clones_{SHORT[_m]}"] = O.clones(_m, by_class=True)
for _mode in ("blind", "keep_head"):
    QUERIES[f"doc_clones_lcsmod_{_mode}"] = _detector(PLAIN, _mode)
    ORACLES[f"doc_clones_lcsmod_{_mode}"] = O.clones("lcs_mod", 15, _mode, by_class=True)
QUERIES["doc_clones_min6"] = _detector(PLAIN.but(min_lines=6))
ORACLES["doc_clones_min6"] = O.clones("lcs_mod", 6, by_class=True)
QUERIES["doc_clones_prime4"] = _detector(DetectorConfig.legacy())
ORACLES["doc_clones_prime4"] = O.clones("lcs", cap=CAP, by_class=True)
QUERIES["doc_clones_none"] = _detector(PLAIN.but(encoding="none"))
ORACLES["doc_clones_none"] = O.clones("lcs_mod", by_class=True)
QUERIES["doc_clones_fast"] = _detector(DetectorConfig.fast())
ORACLES["doc_clones_fast"] = O.clones("hamming", cap=CAP, by_class=True)

#: LSH bucket of a line in DuckDB: clamped word count, then the least seeded digest of placed words.
_LSH = (
    "(greatest(3, least(8, len(string_split(x, ' ')))) - 3) * 200 + CAST('0x' || substr(list_min(list_transform(string_split(x, ' '), "
    "lambda t, i: md5('a' || CAST((i - 1) % 4 AS VARCHAR) || ' ' || t))), 1, 8) AS BIGINT) % 200"
)


def _lsh_fragments(min_lines: int) -> str:
    return f"f0 AS ({O.fragments(min_lines)[6:-1]}), f AS (SELECT id, n, list_transform(s, lambda x: CAST({_LSH} AS VARCHAR)) AS s FROM f0)"


def _lsh_sql(min_lines: int) -> str:
    return O.clones("lcs_mod", min_lines, cap=CAP, source=_lsh_fragments(min_lines), by_class=True)


QUERIES["doc_clones_lsh"] = _detector(DetectorConfig())
ORACLES["doc_clones_lsh"] = _lsh_sql(15)
#: Locality-sensitive codes have few values, so lists of them hold a share of all pairs and are longer than the result by far.
LSH_MIN6 = DetectorConfig(min_lines=6, candidates="tiles")
QUERIES["doc_clones_lsh_min6"] = _detector(LSH_MIN6)
ORACLES["doc_clones_lsh_min6"] = _lsh_sql(6)


@query("doc_clones_lev_characters", O.clones("levenshtein", 15, source=_lsh_fragments(15)))
def doc_clones_lev_characters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Levenshtein on locality-sensitive codes, one character a code: the kernel finds the pairs, Spark's own function gives their distance."""
    paths = T.line_paths(_docs(spark, sf_dir), "exact", 15)
    pairs = detect(paths, PLAIN.but(metric="levenshtein", encoding="lsh"))
    text = S.encoded_paths(paths, "lsh").select("fragment_id", as_characters(F.col("code")).alias("t"), F.size("code").alias("n"))
    both = pairs.join(text.toDF("left_id", "a", "na"), "left_id").join(text.toDF("right_id", "b", "nb"), "right_id")
    return both.select("left_id", "right_id", F.round(F.levenshtein("a", "b") / F.greatest("na", "nb"), 6).alias("distance"))


def _merge_sql() -> str:
    """Greedy merging: in sorted order a path joins the first kept one of its length that differs in one node."""
    differ = "len(list_filter(range(1, len(k.q) + 1), lambda i: k.q[i] <> x[1].q[i]))"
    first = f"coalesce(list_min(list_transform(range(1, len(acc) + 1), lambda n: CASE WHEN len(acc[n].q) = len(x[1].q) AND {differ.replace('k.q', 'acc[n].q')} = 1 THEN n END)), 0)"
    joined = f"list_transform(acc, lambda k, n: {{'q': k.q, 'm': CASE WHEN n = {first} THEN k.m + x[1].m ELSE k.m END}})"
    return f"list_reduce(list_sort(list(DISTINCT [{{'q': q, 'm': m}}])), lambda acc, x: CASE WHEN {first} = 0 THEN list_concat(acc, x) ELSE {joined} END)"


def _para_paths_sql(encoded: bool, merge: bool) -> str:
    """CTEs up to ``w(id, q, mult)``: trees of paragraphs, one path a line, root first."""
    code = f"list_transform(q, lambda x: {_LSH})" if encoded else "q"
    merged = f"h AS (SELECT id, unnest({_merge_sql()}) AS k FROM w0 GROUP BY id), w AS (SELECT id, k.q AS q, k.m AS mult FROM h)" if merge else "w AS (SELECT id, q, m AS mult FROM w0)"
    return f"""WITH {O.fragments(15)},
g AS (SELECT id, n, list_filter(list_transform(string_split(unnest(s), '. '), lambda x: trim(x)), lambda x: x <> '') AS q, trim(string_split(s[1], '. ')[1]) AS root FROM f),
g2 AS (SELECT id, list_concat([root], q) AS q FROM g), g3 AS (SELECT id, {code} AS q FROM g2),
w0 AS (SELECT id, q, count(*) AS m FROM g3 GROUP BY ALL), {merged}"""


def _para_sql(encoded: bool, merge: bool, cap: int | None) -> str:
    return O.set_clones(_para_paths_sql(encoded, merge), "lcs_mod", cap)


#: The published set-up on trees, also of locality-sensitive codes.
TREES = DetectorConfig(candidates="tiles")


@query("doc_clones_default", _para_sql(True, True, CAP))
def doc_clones_default(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The published set-up on trees of paragraphs, pairs of class members included."""
    return _pairs(detect(T.paragraph_paths(_docs(spark, sf_dir)), TREES))


@query("doc_clones_trees_md5", _para_sql(False, False, None))
def doc_clones_trees_md5(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same trees with collision-free codes, only equal paths merged and no cap."""
    return _pairs(detect(T.paragraph_paths(_docs(spark, sf_dir)), PLAIN))


@query("doc_copy_strategy", O.clones("lcs_mod"))
def doc_copy_strategy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Without classes of equal sets; must equal the run with them."""
    return _pairs(detect(T.line_paths(_docs(spark, sf_dir)), PLAIN.but(copy="off")))


@query("doc_copy_lossy", O.clones("lcs_mod", by_class=True).replace("SELECT 'pair' AS \"row\", * FROM", "SELECT * FROM").split(" UNION ALL ")[0])
def doc_copy_lossy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rival's copy strategy: one of equal fragments is compared, its copies' pairs are lost."""
    return _pairs(detect(T.line_paths(_docs(spark, sf_dir)), PLAIN.but(copy="lossy")))


@query("doc_brute_force", O.clones("lcs").replace(O.shared("c"), O.every("c")))
def doc_brute_force(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every pair compared, in blocks, classes off: the reference for candidates and copies."""
    return _pairs(detect(T.line_paths(_docs(spark, sf_dir)), PLAIN.but(metric="lcs", copy="off", candidates="blocks")))


@query("doc_copy_classes", f"WITH {O.fragments(6)} SELECT min(id) AS rep_id, count(*) AS class_size FROM f GROUP BY s HAVING count(*) > 1")
def doc_copy_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    sets = S.description_sets(S.encoded_paths(T.line_paths(_docs(spark, sf_dir), "exact", 6), "md5"))
    reps, _ = S.collapse(sets)
    return reps.filter("class_size > 1").select(F.col("fragment_id").alias("rep_id"), "class_size")


_SWEEP = ", ".join(f"({t})" for t in (0.1, 0.2, 0.3, 0.4))


@query("doc_tau_sweep", f"WITH x AS ({O.clones('lcs', 6, tau=0.4)}), t(tau) AS (VALUES {_SWEEP}) SELECT CAST(tau AS DOUBLE) AS tau, count(left_id) AS n_pairs FROM t LEFT JOIN x ON distance < tau GROUP BY tau")
def doc_tau_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distances once at the widest threshold; every threshold counts from them."""
    found = detect(T.line_paths(_docs(spark, sf_dir)), DetectorConfig.plain().but(metric="lcs", min_lines=6, tau=0.4))
    taus = spark.sql(f"SELECT CAST(col1 AS DOUBLE) AS tau FROM VALUES {_SWEEP}")
    return taus.join(found, F.col("distance") < F.col("tau"), "left").groupBy("tau").agg(F.count("left_id").alias("n_pairs"))


_SIZES = ", ".join(f"({n})" for n in range(6, 21))


@query(
    "doc_min_size_sweep",
    f"WITH {O.fragments(6)}, x AS ({O.clones('lcs', 6)}), m(l) AS (VALUES {_SIZES}), fr AS (SELECT l, count(id) AS n_fragments FROM m LEFT JOIN f ON n >= l GROUP BY l), "
    "pr AS (SELECT l, count(left_id) AS n_pairs FROM m LEFT JOIN (SELECT left_id, least(a.n, b.n) AS k FROM x JOIN f a ON a.id = left_id JOIN f b ON b.id = right_id) ON k >= l GROUP BY l) "
    "SELECT CAST(l AS BIGINT) AS min_lines, n_fragments, n_pairs FROM fr JOIN pr USING (l)",
)
def doc_min_size_sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _docs(spark, sf_dir)
    f = T.fragments(docs, min_lines=6).select("fragment_id", "n_lines")
    pairs = detect(T.line_paths(docs), DetectorConfig.plain().but(metric="lcs", min_lines=6))
    a, b = f.toDF("left_id", "na"), f.toDF("right_id", "nb")
    least = pairs.join(a, "left_id").join(b, "right_id").select(F.least("na", "nb").alias("k"), F.lit(0).alias("one_f"), F.lit(1).alias("one_p"))
    both = least.unionByName(f.select(F.col("n_lines").alias("k"), F.lit(1).alias("one_f"), F.lit(0).alias("one_p")))
    sizes = both.withColumn("min_lines", F.explode(F.sequence(F.lit(6), F.least(F.lit(20), "k"))))
    all_sizes = spark.range(6, 21).select(F.col("id").alias("min_lines"))
    counted = sizes.groupBy(F.col("min_lines").cast("long").alias("min_lines")).agg(F.sum("one_f").alias("n_fragments"), F.sum("one_p").alias("n_pairs"))
    return all_sizes.join(counted, "min_lines", "left").select("min_lines", F.coalesce("n_fragments", F.lit(0)).alias("n_fragments"), F.coalesce("n_pairs", F.lit(0)).alias("n_pairs"))


def _band(sim):
    return F.when(sim >= 0.9, "vst3").when(sim >= 0.7, "st3").when(sim >= 0.5, "mt3").otherwise("ty4")


@query(
    "doc_type_bands",
    f"WITH {O.fragments(6)}, {O.shared()}, m AS (SELECT {O.lcs('a.s', 'b.s')} AS z, a.s AS sa, b.s AS sb FROM p JOIN f a ON a.id = x JOIN f b ON b.id = y), "
    "s AS (SELECT round(1 - (greatest(len(sa), len(sb)) - z) / greatest(len(sa), len(sb)), 6) AS sim, sa = sb AS same FROM m) "
    "SELECT CASE WHEN same THEN 'ty1' WHEN sim >= 0.9 THEN 'vst3' WHEN sim >= 0.7 THEN 'st3' WHEN sim >= 0.5 THEN 'mt3' ELSE 'ty4' END AS band, count(*) AS n_pairs FROM s GROUP BY ALL",
)
def doc_type_bands(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs with a common line by bands of similarity: classes of equal documents are compared once and weighted by their sizes."""
    cfg = DetectorConfig.plain().but(metric="lcs", max_set_factor=None, min_lines=6)
    _, sets, _ = classes(T.line_paths(_docs(spark, sf_dir), "exact", 6), cfg)
    across = distance_counts(sets.withColumn("one", F.col("class_size").cast("long")), cfg)
    inside = sets.agg(F.sum(F.expr("class_size * (class_size - 1) div 2")).alias("n")).filter("n > 0").select(F.lit(0.0).alias("distance"), "n")
    sim = F.round(1 - F.col("distance"), 6)
    return across.unionByName(inside).select(F.when(F.col("distance") == 0, "ty1").otherwise(_band(sim)).alias("band"), "n").groupBy("band").agg(F.sum("n").alias("n_pairs"))


@query("doc_groups")
def doc_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clone groups as components of the pairs."""
    return groups(detect(T.line_paths(_docs(spark, sf_dir)), DetectorConfig.plain().but(min_lines=6)))


ORACLES["doc_groups"] = f"""WITH RECURSIVE x AS ({O.clones('lcs_mod', 6)}), e AS (SELECT left_id AS a, right_id AS b FROM x UNION SELECT right_id, left_id FROM x),
r AS (SELECT a, a AS b FROM e UNION SELECT r.a, e.b FROM r JOIN e ON r.b = e.a) SELECT a AS fragment_id, min(b) AS group_id FROM r GROUP BY a"""


@query(
    "doc_nearest",
    f"WITH {O.fragments(15)}, {O.every()}, q AS (SELECT x, y FROM p UNION ALL SELECT y, x FROM p), m AS (SELECT x, y, {O.lcs('a.s', 'b.s')} AS z, a.s AS sa, b.s AS sb FROM q JOIN f a ON a.id = x JOIN f b ON b.id = y), "
    "d AS (SELECT x, y, round((greatest(len(sa), len(sb)) - z) / greatest(len(sa), len(sb)), 6) AS d FROM m) "
    "SELECT x AS left_id, y AS right_id, d AS distance, rank FROM (SELECT *, row_number() OVER (PARTITION BY x ORDER BY d, y) AS rank FROM d) WHERE rank <= 3",
)
def doc_nearest(spark: SparkSession, sf_dir: str) -> DataFrame:
    paths = T.line_paths(_docs(spark, sf_dir), "exact", 15)
    return nearest(paths, paths, DetectorConfig.plain().but(metric="lcs"), 3)


@query(
    "doc_path_merge",
    f"WITH {O.fragments(15)}, g AS (SELECT id, unnest(s) AS v FROM f) SELECT id AS fragment_id, count(*) AS n_paths, count(DISTINCT v) AS n_merged FROM g GROUP BY id",
)
def doc_path_merge(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Paths of one line each before and after merging equal ones."""
    lines = T.fragments(_docs(spark, sf_dir), min_lines=15).select("fragment_id", "n_lines", F.posexplode("nodes").alias("path_no", "x"))
    paths = lines.select("fragment_id", "n_lines", F.array(F.array("x")).alias("nodes"), F.lit(1).alias("mult"))
    return S.encoded_paths(paths, "md5").groupBy("fragment_id").agg(F.sum("mult").alias("n_paths"), F.count("*").alias("n_merged"))


@query("doc_path_merge_one_node", f"{_para_paths_sql(False, True)} SELECT id AS fragment_id, CAST(sum(mult) AS BIGINT) AS n_paths, count(*) AS n_merged FROM w GROUP BY id")
def doc_path_merge_one_node(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Merging of paths that differ in one node, greedy in sorted order."""
    encoded = S.encoded_paths(T.paragraph_paths(_docs(spark, sf_dir), 15), "md5", "one_node")
    return encoded.groupBy("fragment_id").agg(F.sum("mult").alias("n_paths"), F.count("*").alias("n_merged"))


def _saving_sql() -> str:
    parts = []
    for name, merge in (("none", "sum(mult)"), ("identical", "count(*)"), ("one_node", "count(*)")):
        paths = _para_paths_sql(True, name == "one_node")
        parts.append(
            f"SELECT * FROM ({paths}, k AS MATERIALIZED (SELECT id, sum(mult) AS n, {merge} AS kept FROM w GROUP BY id) SELECT '{name}' AS merge, CAST((SELECT sum(kept) FROM k) AS BIGINT) AS n_paths, "
            "CAST((SELECT sum(a.kept * b.kept) FROM k a JOIN k b ON a.id < b.id AND greatest(a.n, b.n) <= 1.7 * least(a.n, b.n)) AS BIGINT) AS n_compared)"
        )
    return " UNION ALL ".join(parts)


@query("doc_merge_saving", _saving_sql())
def doc_merge_saving(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Paths kept and pairs of paths to compare, over all pairs of sets within the size factor, without merging, with equal and with one-node paths merged."""
    paths, out = T.paragraph_paths(_docs(spark, sf_dir), 15), None
    for how in ("none", "identical", "one_node"):
        k = S.encoded_paths(paths, "lsh", how).groupBy("fragment_id").agg(F.sum("mult").alias("n"), F.count("*").alias("kept"))
        sizes = k.groupBy("n", "kept").agg(F.count("*").alias("m"))
        a, b = sizes.toDF("na", "ka", "ma"), sizes.toDF("nb", "kb", "mb")
        near = a.join(b, F.greatest("na", "nb") <= 1.7 * F.least("na", "nb"))
        same = (F.col("na") == F.col("nb")) & (F.col("ka") == F.col("kb"))
        both = F.sum(F.col("ka") * F.col("kb") * F.when(same, F.col("ma") * (F.col("ma") - 1)).otherwise(F.col("ma") * F.col("mb")))
        row = near.agg((both / 2).cast("long").alias("n_compared")).withColumn("merge", F.lit(how))
        total = sizes.agg(F.sum(F.col("kept") * F.col("m")).alias("n_paths")).withColumn("merge", F.lit(how))
        row = row.join(total, "merge").select("merge", "n_paths", "n_compared")
        out = row if out is None else out.unionByName(row)
    return out


_GRID = [(a, c) for a in (1.2, 1.7, 2.5) for c in (3, 7, 15)]


@query(
    "doc_short_circuit",
    f"WITH {O.fragments(6)}, {O.shared()}, g(factor, cap) AS (VALUES {', '.join(str(x) for x in _GRID)}), k AS (SELECT a.n AS na, b.n AS nb FROM p JOIN f a ON a.id = x JOIN f b ON b.id = y) "
    "SELECT CAST(factor AS DOUBLE) AS factor, CAST(cap AS BIGINT) AS cap, count(*) AS n_pairs, count(*) FILTER (greatest(na, nb) > factor * least(na, nb)) AS cut_by_size, count(*) FILTER (abs(na - nb) > cap) AS cut_by_length FROM g, k GROUP BY ALL",
)
def doc_short_circuit(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Candidate pairs that each short circuit cuts, over a grid of its two parameters."""
    from pathtwin.match.candidates import shared_pairs

    encoded = S.encoded_paths(T.line_paths(_docs(spark, sf_dir), "exact", 6), "md5")
    n = encoded.select("fragment_id", F.size("code").alias("n"))
    k = shared_pairs(encoded).join(n.toDF("left_id", "na"), "left_id").join(n.toDF("right_id", "nb"), "right_id").groupBy("na", "nb").agg(F.count("*").alias("m"))
    grid = F.explode(F.array(*[F.struct(F.lit(float(a)).alias("factor"), F.lit(c).cast("long").alias("cap")) for a, c in _GRID]))
    k = k.withColumn("g", grid).select("na", "nb", "m", "g.*")
    big = F.greatest("na", "nb") > F.col("factor") * F.least("na", "nb")
    far = F.abs(F.col("na") - F.col("nb")) > F.col("cap")
    return k.groupBy("factor", "cap").agg(F.sum("m").alias("n_pairs"), F.sum(F.when(big, F.col("m")).otherwise(0)).alias("cut_by_size"), F.sum(F.when(far, F.col("m")).otherwise(0)).alias("cut_by_length"))


@query(
    "doc_label_agreement",
    f"WITH x AS ({O.clones('lcs_mod', 6)}), l AS (SELECT doc_id, max(quality) AS q FROM labels GROUP BY doc_id) SELECT count(*) AS n_pairs, count(*) FILTER (a.q = b.q) AS n_agree FROM x JOIN l a ON a.doc_id = left_id JOIN l b ON b.doc_id = right_id",
)
def doc_label_agreement(spark: SparkSession, sf_dir: str) -> DataFrame:
    pairs = detect(T.line_paths(_docs(spark, sf_dir)), DetectorConfig.plain().but(min_lines=6))
    q = read_table(spark, sf_dir, "labels").groupBy("doc_id").agg(F.max("quality").alias("q"))
    joined = pairs.join(q.toDF("left_id", "qa"), "left_id").join(q.toDF("right_id", "qb"), "right_id")
    return joined.agg(F.count("*").alias("n_pairs"), F.count_if(F.col("qa") == F.col("qb")).alias("n_agree"))


@query("doc_subclones", "SELECT item_id, doc_id FROM benchmark b JOIN documents d ON contains(d.text, b.text)")
def doc_subclones(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Passages that occur word for word in documents: rare-word postings propose, containment decides."""
    docs, bench = _docs(spark, sf_dir), read_table(spark, sf_dir, "benchmark")
    inner = F.split("text", "[ \n]")
    grams = F.when(F.size(inner) >= 5, windows(F.slice(inner, 2, F.greatest(F.lit(0), F.size(inner) - 2)), 3, " ")).otherwise(F.array().cast("array<string>"))
    b = bench.select("item_id", F.col("text").alias("passage"), grams.alias("g"))
    all_grams = F.array_distinct(windows(F.split(F.coalesce("text", F.lit("")), "[ \n]"), 3, " "))
    probe = b.filter(F.size("g") > 0).select("item_id", "passage", F.col("g")[0].alias("gram"))
    hits = docs.select("doc_id", "text", F.explode(all_grams).alias("gram")).join(probe, "gram").filter(F.contains("text", "passage"))
    rest = b.filter(F.size("g") == 0).select("item_id", "passage")
    short = docs.join(rest, F.contains("text", "passage"))
    return hits.select("item_id", "doc_id").unionByName(short.select("item_id", "doc_id")).distinct()


@query("name_metrics")
def name_metrics(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All metrics over pairs of distinct part names, characters as nodes."""
    names = read_table(spark, sf_dir, "part", "p_name").distinct()
    pairs = names.toDF("name_a").join(names.toDF("name_b"), F.col("name_a") < F.col("name_b"))
    chars = lambda c: F.transform(F.split(c, ""), F.ascii)
    return pairs.select("name_a", "name_b", *[F.round(distance_udf(m)(chars("name_a"), chars("name_b")), 6).alias(SHORT[m]) for m in METRICS])


def _name_sql() -> str:
    cols = ", ".join(f"round(CAST({O.distance(m, 'a', 'b', 'name_a', 'name_b')} AS DOUBLE), 6) AS {SHORT[m]}" for m in METRICS)
    return (
        "WITH n AS (SELECT DISTINCT p_name AS v FROM part), p AS (SELECT x.v AS name_a, y.v AS name_b, string_split(x.v, '') AS a, string_split(y.v, '') AS b FROM n x JOIN n y ON x.v < y.v), "
        f"q AS (SELECT *, {O.lcs('a', 'b')} AS z FROM p) SELECT name_a, name_b, {cols} FROM q"
    )


ORACLES["name_metrics"] = _name_sql()
