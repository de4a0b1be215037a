"""Recall and precision on labelled variants, and the rival families on documents."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathtwin import encode
from pathtwin.baselines import families as B
from pathtwin.config import DetectorConfig
from pathtwin.corpus.variants import EDITS, EMBED, KINDS, variants
from pathtwin.evaluation import measures as M
from pathtwin.frontends import text_lines as T
from pathtwin.match.detector import detect
from pathtwin.metrics import distance_udf
from pathtwin.plans.lineage import cut
from pathtwin.sources.io import read_table
from pathtwin.sql import oracles as O
from pathtwin.workloads.documents import _LSH, CAP, METRICS, PLAIN, SHORT, _docs

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
TAU = 0.3


def _edit_sql(kind: str) -> str:
    u = f"CAST('0x' || substr(md5(CAST(id AS VARCHAR) || '|' || CAST(i AS VARCHAR) || '|{kind}'), 1, 6) AS BIGINT)"
    return (
        f"flatten(list_transform(s, lambda x, i: CASE WHEN {u} % 10000 >= {EDITS[kind]} THEN [x] WHEN ({u} // 10000) % 3 = 0 THEN [x || ' ~'] "
        f"WHEN ({u} // 10000) % 3 = 1 THEN [x, 'new line ' || CAST(i AS VARCHAR) || ' ~'] ELSE CAST([] AS VARCHAR[]) END))"
    )


def _fresh_sql(kind: str, n: int) -> str:
    return f"list_transform(range(1, {n + 1}), lambda i: '{kind} ' || CAST(id AS VARCHAR) || ' ' || CAST(i AS VARCHAR))"


def _variants_sql(min_lines: int = 15) -> str:
    """CTEs up to ``x(id, kind, s, v, text)``."""
    swap = "list_transform(s, lambda x, i: coalesce(s[CASE WHEN i % 2 = 1 THEN i + 1 ELSE i - 1 END], x))"
    spaced = "array_to_string(list_transform(s, lambda x: chr(9) || replace(x, ' ', ' ' || chr(9) || ' ') || '  ' || chr(10)), chr(10))"
    renamed = "list_transform(s, lambda y: translate(y, 'aeiou', 'eioua'))"
    plain = {
        **{k: _edit_sql(k) for k in EDITS}, "embed_head": f"list_concat({_fresh_sql('embed_head', EMBED)}, s)", "embed_tail": f"list_concat(s, {_fresh_sql('embed_tail', EMBED)})",
        "permute": swap, "shift": f"list_concat({_fresh_sql('shift', 1)}, s)",
    }
    joined = lambda v: f"array_to_string({v}, chr(10))"
    made = {
        "ty1": ("s", O.LINES.replace("coalesce(text, '')", spaced), spaced), "ty2": (O.abstracted("blind", "s"), O.abstracted("blind", renamed), joined(renamed)),
        **{k: ("s", v, joined(v)) for k, v in plain.items()},
    }
    rows = " UNION ALL ".join(f"SELECT id, '{k}' AS kind, {a} AS s, {v} AS v, {t} AS text FROM f" for k, (a, v, t) in made.items())
    return f"{O.fragments(min_lines)}, x AS MATERIALIZED ({rows})"


def _var(spark: SparkSession, sf_dir: str) -> DataFrame:
    return variants(_docs(spark, sf_dir))


def _found(d) -> list:
    return [F.count("*").alias("n_pairs"), F.count_if(F.round(d, 6) < TAU).alias("n_found")]


def _codes(df: DataFrame, how: str) -> DataFrame:
    coded = lambda c: F.transform(c, lambda x: encode.code(F.split(x, " "), how))
    return df.select("origin_id", "kind", coded("s").alias("s"), coded("v").alias("v"))


def _recall(metric: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        d = distance_udf(metric)(F.col("s"), F.col("v"))
        return _codes(_var(spark, sf_dir), "md5").withColumn("d", d).groupBy("kind").agg(*_found(F.col("d")))

    return run


def _recall_sql(metric: str, source: str = "x") -> str:
    z = f", {O.lcs('s', 'v')} AS z" if O.needs_lcs(metric) else ""
    inner = f"SELECT kind, s AS sa, v AS sb{z} FROM {source}"
    return f"WITH {_variants_sql()}, m AS ({inner}) SELECT kind, count(*) AS n_pairs, count(*) FILTER (round({O.distance(metric, 'sa', 'sb')}, 6) < {TAU}) AS n_found FROM m GROUP BY kind"


for _m in METRICS:
    QUERIES[f"var_recall_{SHORT[_m]}"] = _recall(_m)
    ORACLES[f"var_recall_{SHORT[_m]}"] = _recall_sql(_m)


def var_corpus(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _var(spark, sf_dir).select("origin_id", "kind", F.size("v").cast("long").alias("n_lines"), F.md5(F.array_join("v", "\n")).alias("digest"))


QUERIES["var_corpus"] = var_corpus
ORACLES["var_corpus"] = f"WITH {_variants_sql()} SELECT id AS origin_id, kind, len(v) AS n_lines, md5(array_to_string(v, chr(10))) AS digest FROM x"


def var_recall_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall of the modified LCS under each encoding of nodes."""
    v = _var(spark, sf_dir)
    parts = [_codes(v, how).withColumn("encoding", F.lit(how)) for how in ("none", "prime4", "md5", "lsh")]
    rows = parts[0]
    for p in parts[1:]:
        rows = rows.unionByName(p)
    return rows.withColumn("d", distance_udf("lcs_mod")("s", "v")).groupBy("encoding", "kind").agg(*_found(F.col("d")))


QUERIES["var_recall_hash"] = var_recall_hash


def _hash_sql() -> str:
    plain = f"SELECT kind, s AS sa, v AS sb, {O.lcs('s', 'v')} AS z FROM x"
    coded = lambda c: f"list_transform({c}, lambda x: {_LSH})"
    d = O.distance("lcs_mod", "sa", "sb")
    agg = f"count(*) AS n_pairs, count(*) FILTER (round({d}, 6) < {TAU}) AS n_found"
    return (
        f"WITH {_variants_sql()}, m AS ({plain}), l AS (SELECT kind, {coded('s')} AS s, {coded('v')} AS v FROM x), k AS (SELECT kind, s AS sa, v AS sb, {O.lcs('s', 'v')} AS z FROM l), "
        f"e(encoding) AS (VALUES ('none'), ('prime4'), ('md5')) SELECT encoding, kind, {agg} FROM e, m GROUP BY ALL UNION ALL SELECT 'lsh', kind, {agg} FROM k GROUP BY ALL"
    )


ORACLES["var_recall_hash"] = _hash_sql()


def var_min_tau(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The threshold above which each variant pair is accepted is its distance: its spread by kind."""
    d = F.round(distance_udf("lcs")("s", "v"), 6)
    return _codes(_var(spark, sf_dir), "md5").withColumn("d", d).groupBy("kind").agg(F.min("d").alias("least"), F.max("d").alias("greatest"), F.round(F.avg("d"), 4).alias("mean"))


QUERIES["var_min_tau"] = var_min_tau
ORACLES["var_min_tau"] = (
    f"WITH {_variants_sql()}, m AS (SELECT kind, s AS sa, v AS sb, {O.lcs('s', 'v')} AS z FROM x), d AS (SELECT kind, round({O.distance('lcs', 'sa', 'sb')}, 6) AS d FROM m) "
    "SELECT kind, min(d) AS least, max(d) AS greatest, round(avg(d), 4) AS mean FROM d GROUP BY kind"
)


def family(spark: SparkSession, sf_dir: str, min_lines: int = 15) -> DataFrame:
    """Originals and variants as documents ``doc_id, kind, text``: ``doc_id = origin * 16 + number``, originals have number 0."""
    v = variants(_docs(spark, sf_dir), min_lines)
    number = F.create_map(*[x for i, k in enumerate(KINDS) for x in (F.lit(k), F.lit(i + 1))])
    rows = v.select((F.col("origin_id") * 16 + number[F.col("kind")]).alias("doc_id"), "kind", "text")
    origins = v.filter("kind = 'ty1'").select((F.col("origin_id") * 16).alias("doc_id"), F.lit("origin").alias("kind"), F.array_join("s", "\n").alias("text"))
    return rows.unionByName(origins)


def family_truth(docs: DataFrame) -> DataFrame:
    """Pairs ``left_id, right_id, kind`` of an original and each of its variants."""
    return docs.filter("kind <> 'origin'").select((F.floor(F.col("doc_id") / 16) * 16).alias("left_id"), F.col("doc_id").alias("right_id"), "kind")


def family_sql(min_lines: int = 15) -> str:
    """CTEs up to ``fam(doc_id, kind, text)``."""
    number = " ".join(f"WHEN '{k}' THEN {i + 1}" for i, k in enumerate(KINDS))
    return (
        f"{_variants_sql(min_lines)}, fam AS MATERIALIZED (SELECT id * 16 + CASE kind {number} END AS doc_id, kind, text FROM x "
        "UNION ALL SELECT id * 16, 'origin', array_to_string(s, chr(10)) FROM x WHERE kind = 'ty1')"
    )


#: Own set-ups of the tables, and what their SQL is made of: metric, encoding, cap.
SETUPS = {
    "default": (DetectorConfig(), ("lcs_mod", "lsh", CAP)), "md5": (PLAIN, ("lcs_mod", "md5", None)),
    "fast": (DetectorConfig.fast(), ("hamming", "md5", CAP)), "legacy": (DetectorConfig.legacy(), ("lcs", "md5", CAP)),
}


def setup_sql(name: str, min_lines: int = 15, mode: str = "exact", tau: float = 0.3, cap: int | None | str = "own") -> str:
    """Clone pairs of ``fam`` by one of the set-ups."""
    metric, encoding, own = SETUPS[name][1]
    source = ""
    if encoding == "lsh":
        lines = O.fragments(min_lines, mode)
        source = f"f0 AS ({lines[6:-1]}), f AS (SELECT id, n, list_transform(s, lambda x: CAST({_LSH} AS VARCHAR)) AS s FROM f0)"
    return O.clones(metric, min_lines, mode, tau, own if cap == "own" else cap, source).replace("FROM documents", "FROM fam")


def var_precision(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Share of reported pairs whose origins agree, over all pairs, for several set-ups."""
    paths, out = T.line_paths(family(spark, sf_dir)), None
    for name, (cfg, _) in SETUPS.items():
        found = detect(paths, cfg)
        same = F.floor(F.col("left_id") / 16) == F.floor(F.col("right_id") / 16)
        row = found.agg(F.count("*").alias("n_reported"), F.count_if(same).alias("n_same_origin")).withColumn("setup", F.lit(name))
        out = row if out is None else out.unionByName(row)
    return out.select("setup", "n_reported", "n_same_origin", F.round(F.col("n_same_origin") / F.col("n_reported"), 6).alias("precision"))


QUERIES["var_precision"] = var_precision
ORACLES["var_precision"] = f"WITH {family_sql()} " + " UNION ALL ".join(
    f"SELECT '{k}' AS setup, count(*) AS n_reported, count(*) FILTER (left_id // 16 = right_id // 16) AS n_same_origin, round(count(*) FILTER (left_id // 16 = right_id // 16) / count(*), 6) AS precision FROM ({setup_sql(k)})" for k in SETUPS
)


def var_exclusive(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Truth pairs (original, variant) by kind that the modified LCS finds and Hamming or LCS do not."""
    v = _codes(_var(spark, sf_dir), "md5")
    for m in ("lcs_mod", "lcs", "hamming"):
        v = v.withColumn(m, F.round(distance_udf(m)("s", "v"), 6) < TAU)
    return v.groupBy("kind").agg(F.count_if("lcs_mod").alias("n_mod"), F.count_if(F.col("lcs_mod") & ~F.col("lcs")).alias("only_vs_lcs"), F.count_if(F.col("lcs_mod") & ~F.col("hamming")).alias("only_vs_hamming"))


QUERIES["var_exclusive"] = var_exclusive
ORACLES["var_exclusive"] = (
    f"WITH {_variants_sql()}, m AS (SELECT kind, s AS sa, v AS sb, {O.lcs('s', 'v')} AS z FROM x), d AS (SELECT kind, round({O.distance('lcs_mod', 'sa', 'sb')}, 6) < {TAU} AS a, "
    f"round({O.distance('lcs', 'sa', 'sb')}, 6) < {TAU} AS b, round({O.distance('hamming', 'sa', 'sb')}, 6) < {TAU} AS c FROM m) "
    "SELECT kind, count(*) FILTER (a) AS n_mod, count(*) FILTER (a AND NOT b) AS only_vs_lcs, count(*) FILTER (a AND NOT c) AS only_vs_hamming FROM d GROUP BY kind"
)

# --- rival families ---------------------------------------------------------------------------------------

_P = f"WITH {O.fragments(15)}"
QUERIES["base_bag"] = lambda spark, sf_dir: B.token_bag(_docs(spark, sf_dir))
ORACLES["base_bag"] = (
    f"{_P}, w AS (SELECT id, unnest(string_split(array_to_string(s, ' '), ' ')) AS w FROM f), c AS (SELECT id, w, count(*) AS n FROM w GROUP BY ALL), t AS (SELECT id, sum(n) AS n FROM c GROUP BY id), "
    "o AS (SELECT a.id AS x, b.id AS y, sum(least(a.n, b.n)) AS c FROM c a JOIN c b ON a.w = b.w AND a.id < b.id GROUP BY ALL) "
    "SELECT x AS left_id, y AS right_id FROM o JOIN t p ON p.id = x JOIN t q ON q.id = y WHERE c >= round(greatest(p.n, q.n) * 0.7, 9)"
)
QUERIES["base_set"] = lambda spark, sf_dir: B.token_set(_docs(spark, sf_dir))
ORACLES["base_set"] = (
    f"WITH {O.fragments(15, 'keep_head')}, c AS (SELECT DISTINCT id, unnest(s) AS w FROM f), t AS (SELECT id, count(*) AS n FROM c GROUP BY id), o AS (SELECT a.id AS x, b.id AS y, count(*) AS c FROM c a JOIN c b ON a.w = b.w AND a.id < b.id GROUP BY ALL) "
    "SELECT x AS left_id, y AS right_id FROM o JOIN t p ON p.id = x JOIN t q ON q.id = y WHERE c >= round(greatest(p.n, q.n) * 0.7, 9)"
)
for _name, _tau in (("base_line", 0.3), ("base_line_58", 0.58)):
    QUERIES[_name] = lambda spark, sf_dir, t=_tau: B.line_lcs(_docs(spark, sf_dir), tau=t)
    ORACLES[_name] = f"SELECT left_id, right_id FROM ({O.clones('lcs', 15, 'blind', _tau)})"
QUERIES["base_win"] = lambda spark, sf_dir: B.line_windows(_docs(spark, sf_dir))
ORACLES["base_win"] = (
    f"{_P}, w AS (SELECT id, n - 5 AS nw, unnest(range(1, n - 4)) AS p, s FROM f), k AS (SELECT id, nw, p, h, list_transform(s[p:p + 5], lambda x, i: CASE WHEN i = h THEN chr(2) ELSE x END) AS key FROM w, (SELECT unnest(range(1, 7)) AS h)), "
    "m AS (SELECT DISTINCT a.id AS x, b.id AS y, a.nw, a.p FROM k a JOIN k b ON a.key = b.key AND a.h = b.h AND a.id <> b.id), s AS (SELECT x, y FROM m GROUP BY x, y, nw HAVING count(*) >= round(nw * 0.6, 9)) "
    "SELECT a.x AS left_id, a.y AS right_id FROM s a JOIN s b ON a.x = b.y AND a.y = b.x AND a.x < a.y"
)
QUERIES["base_run"] = lambda spark, sf_dir: B.token_runs(_docs(spark, sf_dir))
ORACLES["base_run"] = (
    f"{_P}, w AS (SELECT id, string_split(array_to_string(s, ' '), ' ') AS w FROM f), g AS (SELECT id, p, array_to_string(w[p:p + 14], ' ') AS h FROM (SELECT id, w, unnest(range(1, len(w) - 13)) AS p FROM w WHERE len(w) >= 15)), "
    "m AS (SELECT a.id AS x, b.id AS y, a.p - b.p AS diag, a.p AS p FROM g a JOIN g b ON a.h = b.h AND a.id < b.id), i AS (SELECT *, p - row_number() OVER (PARTITION BY x, y, diag ORDER BY p) AS island FROM m), "
    "r AS (SELECT x, y, count(*) + 14 AS words FROM i GROUP BY x, y, diag, island) SELECT x AS left_id, y AS right_id FROM r GROUP BY x, y HAVING sum(words) >= 50"
)
QUERIES["base_gram"] = lambda spark, sf_dir: B.ngram_index(_docs(spark, sf_dir))
ORACLES["base_gram"] = (
    f"{_P}, g AS (SELECT DISTINCT id, s[p:p + 4] AS g FROM (SELECT id, s, unnest(range(1, n - 3)) AS p FROM f)), t AS (SELECT id, count(*) AS n FROM g GROUP BY id), o AS (SELECT a.id AS x, b.id AS y, count(*) AS c FROM g a JOIN g b ON a.g = b.g AND a.id < b.id GROUP BY ALL), "
    "q AS (SELECT x, y FROM o JOIN t p ON p.id = x JOIN t q ON q.id = y WHERE c >= least(p.n, q.n) * 0.1), "
    f"z AS (SELECT x, y, {O.lcs('a.s', 'b.s')} AS z, least(a.n, b.n) AS n FROM q JOIN f a ON a.id = x JOIN f b ON b.id = y) SELECT x AS left_id, y AS right_id FROM z WHERE z >= round(n * 0.7, 9)"
)
QUERIES["base_vec"] = lambda spark, sf_dir: B.tree_vector(read_table(spark, sf_dir, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("v")), 1.0)


def learned_pairs(v: DataFrame, docs: DataFrame) -> DataFrame:
    """Pairs of ``docs`` by the learned family, trained on the variants ``v`` and as many pairs of different origins."""
    # but for ty2 all variants have the lines of their origin, which are counted once
    once = F.when(F.col("kind") == "ty1", B.line_counts(F.col("s"))).alias("a")
    v = cut(v.filter("kind <> 'ty2'").select("origin_id", "kind", once, B.line_counts(F.col("v")).alias("b")))
    v = v.withColumn("a", F.first("a", ignorenulls=True).over(Window.partitionBy("origin_id")))
    true, first = v.select("a", "b", F.lit(1).alias("y")), v.filter("kind = 'ty1'")
    half = max(97, first.count() // 2)  # remainders have either sign, so there is a bucket for each origin and about one other origin meets a variant
    other = v.select(F.col("origin_id").alias("o"), "b").withColumn("k", F.xxhash64("o") % half)
    base = first.select(F.col("origin_id").alias("p"), "a").withColumn("k", F.xxhash64("p") % half)
    false = base.join(other, "k").filter("o <> p").select("a", "b", F.lit(0).alias("y"))
    return B.learned(docs, true.unionByName(false))


def base_learn(spark: SparkSession, sf_dir: str) -> DataFrame:
    return learned_pairs(_var(spark, sf_dir), _docs(spark, sf_dir))


QUERIES["base_learn"] = base_learn


def doc_exclusive(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of the modified LCS on blind lines that no rival family reports."""
    docs = _docs(spark, sf_dir)
    ours = detect(T.line_paths(docs, "blind"), DetectorConfig.plain().but(max_set_factor=None, candidates="tiles")).select("left_id", "right_id")
    return M.exclusive(ours, [B.token_bag(docs), B.token_set(docs), B.line_lcs(docs), B.line_windows(docs), B.token_runs(docs), B.ngram_index(docs)])


QUERIES["doc_exclusive"] = doc_exclusive
ORACLES["doc_exclusive"] = f"SELECT left_id, right_id FROM ({O.clones('lcs_mod', 15, 'blind')})" + "".join(f" EXCEPT SELECT left_id, right_id FROM ({ORACLES[k]})" for k in ("base_bag", "base_set", "base_line", "base_win", "base_run", "base_gram"))


def doc_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _docs(spark, sf_dir)
    return M.overlap(B.line_lcs(docs), B.token_set(docs))


QUERIES["doc_overlap"] = doc_overlap
ORACLES["doc_overlap"] = (
    f"WITH a AS ({ORACLES['base_line']}), b AS ({ORACLES['base_set']}) SELECT (SELECT count(*) FROM (SELECT * FROM a EXCEPT SELECT * FROM b)) AS only_a, "
    "(SELECT count(*) FROM (SELECT * FROM b EXCEPT SELECT * FROM a)) AS only_b, (SELECT count(*) FROM (SELECT * FROM a INTERSECT SELECT * FROM b)) AS both"
)
