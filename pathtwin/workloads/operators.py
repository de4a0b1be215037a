"""Operators a user needs around the methods, shown on the given tables."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Window
from pyspark.sql import functions as F

from pathtwin import encode
from pathtwin.config import DetectorConfig
from pathtwin.frontends import text_lines as T
from pathtwin.frontends.event_flow import edges, symbols
from pathtwin.match.blocks import near_by_both
from pathtwin.match.detector import classes, detect
from pathtwin.metrics import columns as C
from pathtwin.plans.lineage import cut
from pathtwin.sources.io import read_table
from pathtwin.sql import oracles as O
from pathtwin.workloads.documents import PLAIN, _docs

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
#: Queries and vectors that a task of ``op_vec_cosine`` compares, about.
VEC_BLOCK = (512, 4096)


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


def _t(name: str, *columns: str):
    return lambda spark, sf_dir: read_table(spark, sf_dir, name, *columns)


lineitem, orders, customer, events, documents, part, labels = (_t(x) for x in ("lineitem", "orders", "customer", "events", "documents", "part", "labels"))


@query("op_scan_project", "SELECT l_orderkey, l_linenumber, round(l_extendedprice * (1 - l_discount), 4) AS net FROM lineitem")
def op_scan_project(s, d):
    return lineitem(s, d).select("l_orderkey", "l_linenumber", F.round(F.col("l_extendedprice") * (1 - F.col("l_discount")), 4).alias("net"))


@query("op_filter_pred", "SELECT doc_id, lang FROM documents WHERE lang IN ('en', 'de') AND n_chars BETWEEN 200 AND 2000 AND regexp_matches(text, '[0-9]')")
def op_filter_pred(s, d):
    return documents(s, d).filter(F.col("lang").isin("en", "de") & F.col("n_chars").between(200, 2000) & F.col("text").rlike("[0-9]")).select("doc_id", "lang")


@query("op_join_hash", "SELECT c_mktsegment, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY c_mktsegment")
def op_join_hash(s, d):
    return orders(s, d).join(customer(s, d).hint("shuffle_hash"), F.col("o_custkey") == F.col("c_custkey")).groupBy("c_mktsegment").agg(F.count("*").alias("n"))


@query("op_join_broadcast", "SELECT r_name, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def op_join_broadcast(s, d):
    n, r = _t("nation")(s, d), _t("region")(s, d)
    return customer(s, d).join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(r), F.col("n_regionkey") == F.col("r_regionkey")).groupBy("r_name").agg(F.count("*").alias("n"))


@query("op_join_merge", "SELECT o_orderpriority, sum(l_quantity) AS qty FROM lineitem JOIN orders ON l_orderkey = o_orderkey GROUP BY o_orderpriority")
def op_join_merge(s, d):
    return lineitem(s, d).join(orders(s, d).hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderpriority").agg(F.sum("l_quantity").alias("qty"))


@query("op_join_theta", "SELECT a.p_brand, count(*) AS n FROM part a JOIN part b ON a.p_brand = b.p_brand AND a.p_partkey < b.p_partkey AND abs(a.p_size - b.p_size) <= 1 GROUP BY a.p_brand")
def op_join_theta(s, d):
    a, b = part(s, d).alias("a"), part(s, d).alias("b")
    on = (F.col("a.p_brand") == F.col("b.p_brand")) & (F.col("a.p_partkey") < F.col("b.p_partkey")) & (F.abs(F.col("a.p_size") - F.col("b.p_size")) <= 1)
    return a.join(b, on).groupBy("a.p_brand").agg(F.count("*").alias("n"))


_BANDS = "VALUES ('s', 0, 500), ('m', 500, 2000), ('l', 2000, 10000), ('x', 10000, 1000000000)"


@query("op_join_range", f"WITH b(band, lo, hi) AS ({_BANDS}) SELECT band, count(*) AS n FROM documents JOIN b ON n_chars >= lo AND n_chars < hi GROUP BY band")
def op_join_range(s, d):
    b = s.sql(f"SELECT col1 AS band, col2 AS lo, col3 AS hi FROM {_BANDS}")
    return documents(s, d).join(F.broadcast(b), (F.col("n_chars") >= F.col("lo")) & (F.col("n_chars") < F.col("hi"))).groupBy("band").agg(F.count("*").alias("n"))


@query("op_join_interval", "SELECT a.event_id AS click_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def op_join_interval(s, d):
    e = events(s, d)
    a, b = e.filter("event_type = 'click'").alias("a"), e.filter("event_type = 'purchase'").alias("b")
    on = (F.col("a.user_id") == F.col("b.user_id")) & (F.col("b.ts") > F.col("a.ts")) & (F.col("b.ts") <= F.col("a.ts") + F.expr("INTERVAL 1 HOUR"))
    return a.join(b, on).select(F.col("a.event_id").alias("click_id"), F.col("b.event_id").alias("purchase_id"))


@query("op_join_asof", "SELECT p.event_id AS purchase_id, v.event_id AS view_id FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'view') v ON p.user_id = v.user_id AND p.ts >= v.ts")
def op_join_asof(s, d):
    """Last view of the same user at or before each purchase: one sort a user, no join."""
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w)
    return events(s, d).filter("event_type in ('view', 'purchase')").withColumn("view_id", seen).filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "view_id")


@query("op_join_semi", "SELECT doc_id FROM documents WHERE doc_id IN (SELECT doc_id FROM labels)")
def op_join_semi(s, d):
    return documents(s, d).join(labels(s, d), "doc_id", "left_semi").select("doc_id")


@query("op_join_anti", "SELECT doc_id FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels)")
def op_join_anti(s, d):
    return documents(s, d).join(labels(s, d), "doc_id", "left_anti").select("doc_id")


def _lcs_and_free(s, d):
    """Pairs by LCS and by Hamming without a length penalty, each with both distances, null from the threshold on.

    The second reports a share of all pairs, so both are compared and joined in the tasks that make them.
    """
    lcs, free = (PLAIN.but(metric=m, copy="off") for m in ("lcs", "hamming_free"))
    return near_by_both(classes(T.line_paths(_docs(s, d)), lcs)[1], lcs, free)


@query("op_join_full", f"WITH a AS ({O.clones('lcs')}), b AS ({O.clones('hamming_free')}) SELECT coalesce(a.left_id, b.left_id) AS left_id, coalesce(a.right_id, b.right_id) AS right_id, a.distance AS d_lcs, b.distance AS d_free FROM a FULL JOIN b ON a.left_id = b.left_id AND a.right_id = b.right_id")
def op_join_full(s, d):
    return _lcs_and_free(s, d).withColumnsRenamed({"d_one": "d_lcs", "d_other": "d_free"})


@query("op_agg_basic", "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity) AS qty, round(avg(l_extendedprice), 4) AS price, min(l_tax) AS lo, max(l_tax) AS hi FROM lineitem GROUP BY ALL")
def op_agg_basic(s, d):
    return lineitem(s, d).groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("qty"), F.round(F.avg("l_extendedprice"), 4).alias("price"), F.min("l_tax").alias("lo"), F.max("l_tax").alias("hi"))


@query("op_agg_distinct", "SELECT event_type, count(DISTINCT user_id) AS users FROM events GROUP BY event_type")
def op_agg_distinct(s, d):
    return events(s, d).groupBy("event_type").agg(F.count_distinct("user_id").alias("users"))


@query("op_agg_approx")
def op_agg_approx(s, d):
    return T.fragments(_docs(s, d)).select(F.explode("nodes").alias("x")).agg(F.approx_count_distinct("x", 0.02).alias("lines"))


@query("op_agg_collect", "SELECT user_id, array_to_string(list_sort(list_distinct(list(event_type))), ',') AS kinds FROM events GROUP BY user_id")
def op_agg_collect(s, d):
    return events(s, d).groupBy("user_id").agg(F.array_join(F.array_sort(F.collect_set("event_type")), ",").alias("kinds"))


for _name, _sql in (("rollup", "ROLLUP (source, lang)"), ("cube", "CUBE (source, lang)"), ("gsets", "GROUPING SETS ((source), (lang), ())")):
    ORACLES[f"op_agg_{_name}"] = f"SELECT source, lang, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY {_sql}"


@query("op_agg_rollup", ORACLES["op_agg_rollup"])
def op_agg_rollup(s, d):
    return documents(s, d).rollup("source", "lang").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query("op_agg_cube", ORACLES["op_agg_cube"])
def op_agg_cube(s, d):
    return documents(s, d).cube("source", "lang").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query("op_agg_gsets", ORACLES["op_agg_gsets"])
def op_agg_gsets(s, d):
    return documents(s, d).groupingSets([["source"], ["lang"], []], "source", "lang").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query("op_agg_pivot", "SELECT lang, count(*) FILTER (quality = 0) AS q0, count(*) FILTER (quality = 1) AS q1 FROM documents JOIN labels USING (doc_id) GROUP BY lang")
def op_agg_pivot(s, d):
    p = documents(s, d).join(labels(s, d), "doc_id").groupBy("lang").pivot("quality", [0, 1]).agg(F.count("doc_id"))
    return p.select("lang", F.coalesce(F.col("0"), F.lit(0)).alias("q0"), F.coalesce(F.col("1"), F.lit(0)).alias("q1"))


@query("op_agg_filter", "SELECT source, count(*) FILTER (toxic = 1) AS n_toxic, count(*) AS n FROM documents JOIN labels USING (doc_id) GROUP BY source")
def op_agg_filter(s, d):
    return documents(s, d).join(labels(s, d), "doc_id").groupBy("source").agg(F.count_if(F.col("toxic") == 1).alias("n_toxic"), F.count("*").alias("n"))


@query("op_agg_percentile", "SELECT lang, quantile_cont(n_chars, 0.5) AS median FROM documents GROUP BY lang")
def op_agg_percentile(s, d):
    return documents(s, d).groupBy("lang").agg(F.percentile("n_chars", 0.5).alias("median"))


@query("op_win_rank", "SELECT doc_id, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr FROM documents WINDOW w AS (PARTITION BY source ORDER BY n_chars, doc_id), v AS (PARTITION BY source ORDER BY n_chars)")
def op_win_rank(s, d):
    w, v = Window.partitionBy("source").orderBy("n_chars", "doc_id"), Window.partitionBy("source").orderBy("n_chars")
    return documents(s, d).select("doc_id", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(v).cast("long").alias("rk"), F.dense_rank().over(v).cast("long").alias("dr"))


@query("op_win_lead", "SELECT event_id, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS nxt FROM events")
def op_win_lead(s, d):
    return events(s, d).select("event_id", F.lead("event_type").over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias("nxt"))


@query("op_win_frame_rows", "SELECT doc_id, CAST(sum(n_chars) OVER (PARTITION BY source ORDER BY md5(CAST(doc_id AS VARCHAR)) ROWS UNBOUNDED PRECEDING) AS BIGINT) AS running FROM documents")
def op_win_frame_rows(s, d):
    w = Window.partitionBy("source").orderBy(F.md5(F.col("doc_id").cast("string"))).rowsBetween(Window.unboundedPreceding, 0)
    return documents(s, d).select("doc_id", F.sum("n_chars").over(w).alias("running"))


@query("op_win_frame_range", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS n FROM events")
def op_win_frame_range(s, d):
    w = Window.partitionBy("user_id").orderBy(F.expr("timestampdiff(MICROSECOND, TIMESTAMP_NTZ'1970-01-01', ts)")).rangeBetween(-3_600_000_000, 0)
    return events(s, d).select("event_id", F.count("*").over(w).alias("n"))


@query("op_win_islands", "SELECT user_id, event_type, min(event_id) AS first_id, count(*) AS run FROM (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) - row_number() OVER (PARTITION BY user_id, event_type ORDER BY ts, event_id) AS island FROM events) GROUP BY user_id, event_type, island HAVING count(*) > 1")
def op_win_islands(s, d):
    a, b = Window.partitionBy("user_id").orderBy("ts", "event_id"), Window.partitionBy("user_id", "event_type").orderBy("ts", "event_id")
    e = events(s, d).withColumn("island", F.row_number().over(a) - F.row_number().over(b))
    return e.groupBy("user_id", "event_type", "island").agg(F.min("event_id").alias("first_id"), F.count("*").alias("run")).filter("run > 1").drop("island")


@query("op_topk", "SELECT source, doc_id, rn FROM (SELECT source, doc_id, row_number() OVER (PARTITION BY source ORDER BY n_chars DESC, doc_id) AS rn FROM documents) WHERE rn <= 3")
def op_topk(s, d):
    w = Window.partitionBy("source").orderBy(F.desc("n_chars"), "doc_id")
    return documents(s, d).withColumn("rn", F.row_number().over(w).cast("long")).filter("rn <= 3").select("source", "doc_id", "rn")


@query("op_sort_limit", "SELECT doc_id, n_chars FROM documents ORDER BY n_chars DESC, doc_id LIMIT 20")
def op_sort_limit(s, d):
    return documents(s, d).select("doc_id", "n_chars").orderBy(F.desc("n_chars"), "doc_id").limit(20)


def _two(s, d):
    both = cut(_lcs_and_free(s, d))
    return (both.filter(f"{c} is not null").select("left_id", "right_id") for c in ("d_one", "d_other"))


for _name, _word in (("union", "UNION"), ("intersect", "INTERSECT"), ("except", "EXCEPT")):
    ORACLES[f"op_set_{_name}"] = f"SELECT left_id, right_id FROM ({O.clones('hamming_free')}) {_word} SELECT left_id, right_id FROM ({O.clones('lcs')})"


@query("op_set_union", ORACLES["op_set_union"])
def op_set_union(s, d):
    """Every row of the compared pairs is near by one metric at least and there once, so the union is their ids."""
    return _lcs_and_free(s, d).select("left_id", "right_id")


@query("op_set_intersect", ORACLES["op_set_intersect"])
def op_set_intersect(s, d):
    a, b = _two(s, d)
    return b.intersect(a)


@query("op_set_except", ORACLES["op_set_except"])
def op_set_except(s, d):
    a, b = _two(s, d)
    return b.exceptAll(a)


@query("op_dedup", "SELECT min(doc_id) AS doc_id, count(*) AS copies FROM documents GROUP BY text")
def op_dedup(s, d):
    return documents(s, d).groupBy(F.sha2("text", 256).alias("k")).agg(F.min("doc_id").alias("doc_id"), F.count("*").alias("copies")).drop("k")


@query("op_str_norm", f"WITH {O.fragments(1, 'blind')} SELECT id AS doc_id, md5(array_to_string(s, chr(10))) AS digest FROM f")
def op_str_norm(s, d):
    return T.fragments(_docs(s, d), "blind").select(F.col("fragment_id").alias("doc_id"), F.md5(F.array_join("nodes", "\n")).alias("digest"))


@query("op_str_metrics", "WITH n AS (SELECT DISTINCT p_name AS v FROM part) SELECT a.v AS a, b.v AS b, levenshtein(a.v, b.v) AS d FROM n a JOIN n b ON a.v < b.v")
def op_str_metrics(s, d):
    n = part(s, d).select("p_name").distinct()
    return n.toDF("a").join(n.toDF("b"), F.col("a") < F.col("b")).select("a", "b", F.levenshtein("a", "b").cast("long").alias("d"))


@query("op_str_split_explode", "SELECT doc_id, i - 1 AS pos, length(x) AS n FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS x, generate_subscripts(string_split(text, chr(10)), 1) AS i FROM documents)")
def op_str_split_explode(s, d):
    return documents(s, d).select("doc_id", F.posexplode(F.split("text", "\n", -1)).alias("pos", "x")).select("doc_id", F.col("pos").cast("long").alias("pos"), F.length("x").cast("long").alias("n"))


_WORDS = "WITH w AS (SELECT DISTINCT p_name AS v, string_split(p_name, ' ') AS t FROM part)"


def _names(s, d):
    return part(s, d).select(F.col("p_name").alias("v"), F.split("p_name", " ").alias("t")).distinct()


@query("op_hash_md5", f"{_WORDS} SELECT v, md5('[' || array_to_string(t, ', ') || ']') AS code FROM w")
def op_hash_md5(s, d):
    return _names(s, d).select("v", encode.md5(F.col("t")).alias("code"))


@query("op_hash_prime4", f"{_WORDS} SELECT v, CAST(list_reduce(list_transform(string_split('[' || array_to_string(t, ', ') || ']', ''), lambda c: CAST(ascii(c) AS BIGINT)), lambda h, c: (h * 31 + c) % 4294967296, CAST(0 AS BIGINT)) AS BIGINT) AS code FROM w")
def op_hash_prime4(s, d):
    return _names(s, d).select("v", encode.prime4(F.col("t")).alias("code"))


@query("op_hash_lsh", f"{_WORDS} SELECT v, (greatest(3, least(8, len(t))) - 3) * 200 + CAST('0x' || substr(list_min(list_transform(t, lambda x, i: md5('a' || CAST((i - 1) % 4 AS VARCHAR) || ' ' || x))), 1, 8) AS BIGINT) % 200 AS code FROM w")
def op_hash_lsh(s, d):
    return _names(s, d).select("v", encode.lsh(F.col("t")).alias("code"))


_PAIRS = "WITH n AS (SELECT DISTINCT p_name AS v, string_split(p_name, '') AS s FROM part), p AS (SELECT x.v AS a, y.v AS b, x.s AS sa, y.s AS sb FROM n x JOIN n y ON x.v < y.v)"


def _name_pairs(s, d):
    n = part(s, d).select(F.col("p_name").alias("v")).distinct()
    p = n.toDF("a").join(n.toDF("b"), F.col("a") < F.col("b"))
    return p.withColumns({"sa": F.split("a", ""), "sb": F.split("b", "")})


@query("op_arr_lcs", f"{_PAIRS} SELECT a, b, {O.lcs('sa', 'sb')} AS z FROM p")
def op_arr_lcs(s, d):
    """The Column form of the common subsequence."""
    return _name_pairs(s, d).select("a", "b", C.lcs_length(F.col("sa"), F.col("sb")).cast("long").alias("z"))


@query("op_arr_hamming", f"{_PAIRS} SELECT a, b, CAST({O.mismatches('sa', 'sb')} AS BIGINT) + abs(len(sa) - len(sb)) AS full_d, CAST({O.mismatches('sa', 'sb')} AS BIGINT) AS free_d FROM p")
def op_arr_hamming(s, d):
    return _name_pairs(s, d).select("a", "b", C.hamming(F.col("sa"), F.col("sb")).cast("long").alias("full_d"), C.hamming_free(F.col("sa"), F.col("sb")).cast("long").alias("free_d"))


@query("op_arr_jaccard", f"{_PAIRS} SELECT a, b, round({O.distance('jaccard', 'sa', 'sb')}, 6) AS d FROM p")
def op_arr_jaccard(s, d):
    return _name_pairs(s, d).select("a", "b", F.round(C.jaccard(F.col("sa"), F.col("sb")), 6).alias("d"))


@query("op_arr_cosine", f"{_PAIRS} SELECT a, b, round({O.distance('cosine', 'sa', 'sb')}, 6) AS d FROM p")
def op_arr_cosine(s, d):
    return _name_pairs(s, d).select("a", "b", F.round(C.cosine(F.col("sa"), F.col("sb")), 6).alias("d"))


@query("op_arr_ngram", f"{_PAIRS} SELECT a, b, round({O.distance('ngram', 'sa', 'sb')}, 6) AS d FROM p")
def op_arr_ngram(s, d):
    return _name_pairs(s, d).select("a", "b", F.round(C.ngram(F.col("sa"), F.col("sb")), 6).alias("d"))


@query("op_map_counts", "SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL")
def op_map_counts(s, d):
    """Counts gathered into a map a user, and listed again."""
    m = events(s, d).groupBy("user_id", "event_type").agg(F.count("*").alias("n")).groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.explode("m").alias("event_type", "n"))


@query("op_json_props", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) % 10 AS k, count(*) AS n FROM events GROUP BY ALL")
def op_json_props(s, d):
    return events(s, d).select((F.get_json_object("props", "$.k").cast("long") % 10).alias("k")).groupBy("k").agg(F.count("*").alias("n"))


@query("op_date_bucket", "SELECT CAST(date_trunc('week', ts) AS DATE) AS week, count(*) AS n FROM events GROUP BY ALL")
def op_date_bucket(s, d):
    return events(s, d).groupBy(F.to_date(F.date_trunc("week", "ts")).alias("week")).agg(F.count("*").alias("n"))


@query("op_math_bands", "SELECT CASE WHEN n_chars < 100 THEN 0 WHEN n_chars < 170 THEN 1 WHEN n_chars < 289 THEN 2 WHEN n_chars < 491 THEN 3 ELSE 4 END AS band, count(*) AS n FROM documents GROUP BY ALL")
def op_math_bands(s, d):
    cuts = F.when(F.col("n_chars") < 100, 0).when(F.col("n_chars") < 170, 1).when(F.col("n_chars") < 289, 2).when(F.col("n_chars") < 491, 3).otherwise(4)
    return documents(s, d).groupBy(cuts.alias("band")).agg(F.count("*").alias("n"))


@query("op_sample_hash", "SELECT doc_id FROM documents ORDER BY md5(CAST(doc_id AS VARCHAR) || '|7') LIMIT 400")
def op_sample_hash(s, d):
    return documents(s, d).orderBy(F.md5(F.concat(F.col("doc_id").cast("string"), F.lit("|7")))).limit(400).select("doc_id")


@query("op_cte_subquery", "SELECT o_orderkey FROM orders o WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 45) AND o_totalprice > (SELECT avg(o_totalprice) FROM orders)")
def op_cte_subquery(s, d):
    orders(s, d).createOrReplaceTempView("pt_orders")
    lineitem(s, d).createOrReplaceTempView("pt_lineitem")
    return s.sql("SELECT o_orderkey FROM pt_orders o WHERE EXISTS (SELECT 1 FROM pt_lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 45) AND o_totalprice > (SELECT avg(o_totalprice) FROM pt_orders)")


@query("op_recursive_paths", "WITH RECURSIVE e AS (SELECT DISTINCT event_type AS a, lead(event_type) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS b FROM events), r AS (SELECT a, b, 1 AS n FROM e WHERE b IS NOT NULL UNION ALL SELECT r.a, e.b, n + 1 FROM r JOIN e ON r.b = e.a WHERE n < 3 AND e.b IS NOT NULL) SELECT a, b, CAST(n AS BIGINT) AS n, count(*) AS ways FROM r GROUP BY ALL")
def op_recursive_paths(s, d):
    nxt = F.lead("event_type").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
    events(s, d).select(F.col("event_type").alias("a"), nxt.alias("b")).filter("b is not null").distinct().createOrReplaceTempView("pt_follow")
    return s.sql("WITH RECURSIVE r(a, b, n) AS (SELECT a, b, CAST(1 AS BIGINT) FROM pt_follow UNION ALL SELECT r.a, e.b, n + 1 FROM r JOIN pt_follow e ON r.b = e.a WHERE n < 3) SELECT a, b, n, count(*) AS ways FROM r GROUP BY a, b, n")


@query("op_vec_cosine", "SELECT a.vec_id AS q, b.vec_id AS v, round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 6) AS cos FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id WHERE a.vec_id % 50 = 0")
def op_vec_cosine(s, d):
    """A stated query set (ids divisible by 50) against every other vector, block by block.

    Vectors that are null, hold a null, are of length zero or of another dimension have a null cosine.
    """
    e = _t("embeddings")(s, d).select("vec_id", F.col("embedding").cast("array<double>").alias("e"))
    n = e.count()
    n_q, n_v = n // (50 * VEC_BLOCK[0]) + 1, n // VEC_BLOCK[1] + 1
    deal = lambda k: F.pmod(F.xxhash64("vec_id", "e"), F.lit(k)).cast("int")
    every = lambda k: F.explode(F.sequence(F.lit(0), F.lit(k - 1)))
    a = e.filter("vec_id % 50 = 0").select("vec_id", "e", deal(n_q).alias("q_block"), every(n_v).alias("v_block"))
    b = e.select(F.coalesce("vec_id", F.lit(0)).alias("vec_id"), F.isnull("vec_id").alias("unnamed"), "e", every(n_q).alias("q_block"), deal(n_v).alias("v_block"))

    def by_dim(g: pd.DataFrame) -> dict:
        """Row numbers and unit vectors of each dimension; rows without a direction are under ``None``."""
        rows: dict = {}
        for i, x in enumerate(g["e"]):
            x = None if x is None else np.asarray(x, float)
            good = x is not None and len(x) and np.isfinite(x).all() and x.any()
            rows.setdefault(len(x) if good else None, []).append((i, x))
        return {k: (np.array([i for i, _ in r]), None if k is None else np.stack([x / np.linalg.norm(x) for _, x in r])) for k, r in rows.items()}

    def run(q: pd.DataFrame, v: pd.DataFrame) -> pd.DataFrame:
        cos = np.full((len(q), len(v)), np.nan)
        of_v = by_dim(v)
        for k, (i, x) in by_dim(q).items():
            if k is not None and k in of_v:
                cos[np.ix_(i, of_v[k][0])] = x @ of_v[k][1].T
        ids = pd.arrays.IntegerArray(np.tile(v["vec_id"].to_numpy("int64"), len(q)), np.tile(v["unnamed"].to_numpy(bool), len(q)))
        return pd.DataFrame({"q": np.repeat(q["vec_id"].to_numpy("int64"), len(v)), "v": ids, "cos": cos.ravel()})

    pairs = a.groupBy("q_block", "v_block").cogroup(b.groupBy("q_block", "v_block")).applyInPandas(run, "q long, v long, cos double")
    return pairs.filter(~F.col("q").eqNullSafe(F.col("v"))).select("q", "v", F.round("cos", 6).alias("cos"))


@query("op_udf_scalar", f"{_PAIRS} SELECT a, b, levenshtein(a, b) / greatest(len(a), len(b)) < 0.5 AS near FROM p")
def op_udf_scalar(s, d):
    codes = lambda c: F.transform(c, F.ascii)
    return _name_pairs(s, d).select("a", "b", (C.distance_udf("levenshtein")(codes(F.col("sa")), codes(F.col("sb"))) < 0.5).alias("near"))


@query("op_udaf", "SELECT user_id, sum(value * value) / sum(value) AS weighted FROM events GROUP BY user_id")
def op_udaf(s, d):
    @F.pandas_udf("double")
    def weighted(v: pd.Series) -> float:
        return float((v * v).sum() / v.sum())

    return events(s, d).groupBy("user_id").agg(weighted("value").alias("weighted"))


@query("op_udtf", "SELECT p_partkey, i AS n, w FROM (SELECT p_partkey, unnest(string_split(p_name, ' ')) AS w, generate_subscripts(string_split(p_name, ' '), 1) AS i FROM part)")
def op_udtf(s, d):
    """Words of names by a registered table function in a lateral join."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="n: bigint, w: string")
    class Words:
        def eval(self, text: str):
            for i, w in enumerate((text or "").split(" "), 1):
                yield i, w

    s.udtf.register("pt_words", Words)
    part(s, d).createOrReplaceTempView("pt_part")
    return s.sql("SELECT p_partkey, n, w FROM pt_part, LATERAL pt_words(p_name)")


@query("op_sink_roundtrip", "SELECT lang, count(*) AS n, CAST(sum(n_chars) AS BIGINT) AS chars FROM documents GROUP BY lang")
def op_sink_roundtrip(s, d):
    """Documents through a partitioned Parquet table and a JSON table in the shared folder."""
    import uuid

    from pathtwin.plans.lineage import shared_folder

    at = f"{shared_folder(s)}/sink-{uuid.uuid4().hex}"
    documents(s, d).select("doc_id", "lang", "n_chars").write.partitionBy("lang").parquet(f"{at}/parquet")
    s.read.parquet(f"{at}/parquet").write.json(f"{at}/json")
    back = s.read.schema("doc_id long, lang string, n_chars long").json(f"{at}/json")
    return back.groupBy("lang").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))


@query("op_flow_degree", "WITH sy AS (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY ALL) SELECT event_type, max(n) AS most FROM sy GROUP BY event_type")
def op_flow_degree(s, d):
    return symbols(events(s, d)).join(events(s, d).select("event_id", "user_id"), "event_id").groupBy("user_id", "event_type").agg(F.count("*").alias("n")).groupBy("event_type").agg(F.max("n").alias("most"))
