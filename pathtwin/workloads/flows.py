"""Flow graphs of events, and the other carriers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathtwin.config import DetectorConfig
from pathtwin.flow.dominators import dominator_paths, idom_bulk, idom_local
from pathtwin.flow.exceptions import propagate
from pathtwin.frontends import event_flow as E
from pathtwin.frontends import tables as T
from pathtwin.match.detector import classes, detect, detect_classes, groups
from pathtwin.sources.io import read_table
from pathtwin.sql import oracles as O
from pathtwin.workloads.documents import clone_rows

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def _events(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_table(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type", "value")


_SYMBOLS = (
    "sy AS (SELECT user_id * 10000 + CAST(floor(date_diff('day', DATE '1970-01-05', CAST(ts AS DATE)) / 7) AS BIGINT) AS f, ts, event_id, event_type, "
    "event_type || '/' || CASE WHEN value < 20 THEN 'lo' WHEN value < 55 THEN 'mid' ELSE 'hi' END AS v FROM events)"
)
_EDGES = f"{_SYMBOLS}, e AS (SELECT DISTINCT f, coalesce(lag(v) OVER (PARTITION BY f ORDER BY ts, event_id), 'entry') AS src, v AS dst FROM sy)"
_DOM = (
    f"{_EDGES}, n AS (SELECT DISTINCT f, dst AS v FROM e), r AS (SELECT e.f, n.v AS l, dst AS v FROM e JOIN n ON e.f = n.f WHERE src = 'entry' AND dst <> n.v "
    "UNION SELECT r.f, r.l, e.dst FROM r JOIN e ON e.f = r.f AND e.src = r.v WHERE e.dst <> r.l), "
    "d AS (SELECT a.f, a.v AS l, b.v FROM n a JOIN n b ON a.f = b.f AND a.v <> b.v WHERE NOT EXISTS (SELECT 1 FROM r WHERE r.f = a.f AND r.l = a.v AND r.v = b.v)), "
    "k AS (SELECT n.f, n.v, count(d.l) AS depth FROM n LEFT JOIN d ON d.f = n.f AND d.v = n.v GROUP BY ALL), "
    "i AS (SELECT n.f, n.v, coalesce(max_by(d.l, k.depth), 'entry') AS idom FROM n LEFT JOIN d ON d.f = n.f AND d.v = n.v LEFT JOIN k ON k.f = d.f AND k.v = d.l GROUP BY ALL)"
)

QUERIES["flow_graph"] = lambda spark, sf_dir: E.edges(_events(spark, sf_dir))
ORACLES["flow_graph"] = f"WITH {_EDGES} SELECT f AS fragment_id, src, dst FROM e"
QUERIES["flow_dominators"] = lambda spark, sf_dir: idom_local(E.edges(_events(spark, sf_dir)))
ORACLES["flow_dominators"] = f"WITH RECURSIVE {_DOM} SELECT f AS fragment_id, v AS node_id, idom FROM i"
QUERIES["flow_dominators_bulk"] = lambda spark, sf_dir: idom_bulk(E.edges(_events(spark, sf_dir)))
ORACLES["flow_dominators_bulk"] = ORACLES["flow_dominators"]
QUERIES["flow_paths"] = lambda spark, sf_dir: dominator_paths(E.edges(_events(spark, sf_dir))).select("fragment_id", F.array_join("path", ">").alias("path"))
ORACLES["flow_paths"] = (
    f"WITH RECURSIVE {_DOM}, t AS (SELECT f, v, v AS path FROM i WHERE idom = 'entry' UNION ALL SELECT i.f, i.v, t.path || '>' || i.v FROM t JOIN i ON i.f = t.f AND i.idom = t.v) "
    "SELECT f AS fragment_id, path FROM t WHERE NOT EXISTS (SELECT 1 FROM i WHERE i.f = t.f AND i.idom = t.v)"
)
QUERIES["flow_exception_edges"] = lambda spark, sf_dir: E.edges(_events(spark, sf_dir), True).groupBy("fragment_id").agg(F.count("*").alias("n_edges"))
ORACLES["flow_exception_edges"] = (
    f"WITH {_SYMBOLS}, p AS (SELECT f, coalesce(lag(v) OVER (PARTITION BY f ORDER BY ts, event_id), 'entry') AS src, v AS dst FROM sy), "
    "x AS (SELECT f, v AS src, first(CASE WHEN event_type <> 'error' THEN v END IGNORE NULLS) OVER (PARTITION BY f ORDER BY ts, event_id ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING) AS dst, event_type FROM sy), "
    "a AS (SELECT * FROM p UNION SELECT f, src, dst FROM x WHERE event_type = 'error' AND dst IS NOT NULL) SELECT f AS fragment_id, count(*) AS n_edges FROM a GROUP BY f"
)


def flow_dominance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Number of strict dominators of each node, by climbing the tree."""
    paths = dominator_paths(E.edges(_events(spark, sf_dir)))
    return paths.select("fragment_id", F.posexplode("path").alias("n_dominators", "node_id")).distinct().select("fragment_id", "node_id", F.col("n_dominators").cast("long").alias("n_dominators"))


QUERIES["flow_dominance"] = flow_dominance
ORACLES["flow_dominance"] = f"WITH RECURSIVE {_DOM} SELECT f AS fragment_id, v AS node_id, depth AS n_dominators FROM k"
#: Weeks have fifteen symbols, so almost every two are candidates.
FLOWS = DetectorConfig.plain().but(metric="lcs", min_lines=10, candidates="blocks")
QUERIES["flow_clones"] = lambda spark, sf_dir: detect(E.flow_paths(_events(spark, sf_dir), 10), FLOWS).select("left_id", "right_id", "distance")
ORACLES["flow_clones"] = O.set_clones(
    f"WITH w AS MATERIALIZED (WITH RECURSIVE {_DOM}, tr AS (SELECT f, v, [v] AS path FROM i WHERE idom = 'entry' UNION ALL SELECT i.f, i.v, list_append(tr.path, i.v) FROM tr JOIN i ON i.f = tr.f AND i.idom = tr.v), "
    "big AS (SELECT f FROM sy GROUP BY f HAVING count(*) >= 10) SELECT f AS id, path AS q, count(*) AS mult FROM tr WHERE f IN (SELECT f FROM big) AND NOT EXISTS (SELECT 1 FROM i WHERE i.f = tr.f AND i.idom = tr.v) GROUP BY ALL)",
    "lcs",
)

_TAGS = "f AS (SELECT page_id AS id, regexp_extract_all(lower(coalesce(html, '')), '<(/?[a-z][a-z0-9]*)', 1) AS s FROM pages)"


def tag_clones(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages whose tag sequences differ by less than a tenth: pairs of classes of equal sequences, and their members."""
    cfg = DetectorConfig.plain().but(metric="lcs", min_lines=1, tau=0.1, max_set_factor=None)
    return clone_rows(T.tag_paths(read_table(spark, sf_dir, "pages", "page_id", "html")), cfg)


QUERIES["tag_clones"] = tag_clones
ORACLES["tag_clones"] = O.clones("lcs", 1, tau=0.1, source="f AS (SELECT id, s, len(s) AS n FROM (SELECT page_id AS id, regexp_extract_all(lower(coalesce(html, '')), '<(/?[a-z][a-z0-9]*)', 1) AS s FROM pages) WHERE len(s) >= 1)", by_class=True)
QUERIES["tag_paths"] = lambda spark, sf_dir: T.tag_paths(read_table(spark, sf_dir, "pages", "page_id", "html")).select("fragment_id", F.col("n_lines").cast("long").alias("n_tags"), F.md5(F.array_join(F.flatten("nodes"), " ")).alias("digest"))
ORACLES["tag_paths"] = f"WITH {_TAGS} SELECT id AS fragment_id, len(s) AS n_tags, md5(array_to_string(s, ' ')) AS digest FROM f"
QUERIES["dom_paths"] = lambda spark, sf_dir: T.dom_paths(read_table(spark, sf_dir, "pages")).select("fragment_id", "path_no", F.transform("nodes", lambda x: F.array_join(x, " ")).alias("path"))

_CONV = (
    "f AS (SELECT conv_id AS id, list(r || ' ' || b ORDER BY turn, r, b) AS s FROM (SELECT conv_id, turn, coalesce(role, '') AS r, CASE WHEN length(coalesce(text, '')) < 100 THEN 's' WHEN length(text) < 300 THEN 'm' ELSE 'l' END AS b FROM conversations) GROUP BY conv_id)"
)


def _conv(spark: SparkSession, sf_dir: str) -> DataFrame:
    return T.conversation_paths(read_table(spark, sf_dir, "conversations"))


def conv_clones(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Classes of conversations with equal sequences and the nearest other classes within the threshold."""
    cfg = DetectorConfig.plain().but(metric="lcs", min_lines=1, tau=0.3, max_set_factor=None)
    return detect(_conv(spark, sf_dir), cfg).select("left_id", "right_id", "distance")


QUERIES["conv_clones"] = conv_clones
ORACLES["conv_clones"] = (
    f"WITH {_CONV}, {O.shared()}, m AS (SELECT x, y, {O.lcs('a.s', 'b.s')} AS z, a.s AS sa, b.s AS sb FROM p JOIN f a ON a.id = x JOIN f b ON b.id = y), "
    f"d AS (SELECT x, y, round(CAST({O.distance('lcs', 'sa', 'sb')} AS DOUBLE), 6) AS d FROM m) SELECT x AS left_id, y AS right_id, d AS distance FROM d WHERE d < 0.3"
)


def order_seq_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Classes of orders with equal line sequences."""
    p = T.order_paths(read_table(spark, sf_dir, "lineitem"))
    key = F.array_join(F.transform("nodes", lambda x: F.array_join(x, "")), ">")
    return p.groupBy(key.alias("sequence")).agg(F.min("fragment_id").alias("rep_id"), F.count("*").alias("class_size"))


QUERIES["order_seq_classes"] = order_seq_classes
ORACLES["order_seq_classes"] = (
    "WITH l AS (SELECT l_orderkey AS k, string_agg(l_returnflag || l_linestatus || CASE WHEN l_quantity < 17 THEN 'a' WHEN l_quantity < 34 THEN 'b' ELSE 'c' END, '>' "
    "ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice) AS sequence FROM lineitem GROUP BY l_orderkey) SELECT sequence, min(k) AS rep_id, count(*) AS class_size FROM l GROUP BY sequence"
)


#: Orders have few different symbols and are short, so they meet by what is left of them.
ORDERS = DetectorConfig.plain().but(min_lines=1, tau=0.2, candidates="deletions")


def order_seq_clones(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Similar order sequences of any length, at a distance under 0.2.

    Rows ``pair``: representatives of two classes of equal sequences and their distance. Rows ``member``, one an order: its
    class's representative and the order, at distance zero. Together they hold every pair of similar orders.
    """
    paths = T.order_paths(read_table(spark, sf_dir, "lineitem"))
    pairs, members = detect_classes(paths, ORDERS.but(metric="lcs"))
    pairs = pairs.select(F.lit("pair").alias("row"), "left_id", "right_id", "distance")
    return pairs.unionByName(members.select(F.lit("member").alias("row"), F.col("rep_id").alias("left_id"), F.col("fragment_id").alias("right_id"), F.lit(0.0).alias("distance")))


QUERIES["order_seq_clones"] = order_seq_clones


def order_fast_vs_default(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of orders of any length under distance 0.2 that Hamming and plain LCS report: classes weighted by their sizes, and pairs inside a class."""
    paths, out = T.order_paths(read_table(spark, sf_dir, "lineitem")), None
    made = classes(paths, ORDERS)
    for name, metric in (("fast", "hamming"), ("lcs", "lcs")):
        pairs, members = detect_classes(paths, ORDERS.but(metric=metric), made)
        size = members.filter("fragment_id = rep_id").select("rep_id", F.col("class_size").alias("n"))
        across = pairs.join(size.toDF("left_id", "na"), "left_id").join(size.toDF("right_id", "nb"), "right_id").select((F.col("na") * F.col("nb")).alias("n"))
        inside = size.select(F.expr("n * (n - 1) div 2").alias("n"))
        found = across.unionByName(inside).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n_pairs")).withColumn("setup", F.lit(name))
        out = found if out is None else out.unionByName(found)
    return out.select("setup", "n_pairs")


QUERIES["order_fast_vs_default"] = order_fast_vs_default


def flow_exceptions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exceptions that escape from functions, along calls to the fixpoint.

    Parts stand for functions: a part calls the part of the next line of an order; lines of the greatest quantity raise their
    return flag, and a part handles the flag that its size names.
    """
    line = read_table(spark, sf_dir, "lineitem", "l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice", "l_returnflag", "l_quantity")
    w = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice")
    calls = line.select(F.col("l_partkey").alias("caller"), F.lead("l_partkey").over(w).alias("callee")).dropna().distinct()
    throws = line.filter("l_quantity >= 50").select(F.col("l_partkey").alias("fn"), F.col("l_returnflag").alias("exc")).distinct()
    flag = F.element_at(F.array(F.lit("A"), F.lit("N"), F.lit("R")), F.col("p_size") % 3 + 1)
    catches = read_table(spark, sf_dir, "part", "p_partkey", "p_size").select(F.col("p_partkey").alias("fn"), flag.alias("exc"))
    return propagate(calls, throws, catches).select("fn", "exc")


QUERIES["flow_exceptions"] = flow_exceptions
ORACLES["flow_exceptions"] = (
    "WITH RECURSIVE c AS (SELECT DISTINCT caller, callee FROM (SELECT l_partkey AS caller, lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_shipdate, l_extendedprice) AS callee FROM lineitem) WHERE callee IS NOT NULL), "
    "h AS (SELECT p_partkey AS fn, CASE p_size % 3 WHEN 0 THEN 'A' WHEN 1 THEN 'N' ELSE 'R' END AS exc FROM part), "
    "k AS (SELECT DISTINCT l_partkey AS fn, l_returnflag AS exc FROM lineitem l WHERE l_quantity >= 50 AND NOT EXISTS (SELECT 1 FROM h WHERE h.fn = l.l_partkey AND h.exc = l.l_returnflag) "
    "UNION SELECT c.caller, k.exc FROM k JOIN c ON c.callee = k.fn WHERE NOT EXISTS (SELECT 1 FROM h WHERE h.fn = c.caller AND h.exc = k.exc)) SELECT fn, exc FROM k"
)


def clone_report_by_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders in classes of equal sequences, rolled up by region and nation of their customers."""
    p = T.order_paths(read_table(spark, sf_dir, "lineitem"))
    key = F.array_join(F.transform("nodes", lambda x: F.array_join(x, "")), ">")
    seq = p.select("fragment_id", key.alias("seq"))
    many = seq.groupBy("seq").agg(F.count("*").alias("n")).filter("n > 1")
    cloned = seq.join(many, "seq", "left_semi").select(F.col("fragment_id").alias("o_orderkey"))
    orders, customer = read_table(spark, sf_dir, "orders", "o_orderkey", "o_custkey"), read_table(spark, sf_dir, "customer", "c_custkey", "c_nationkey")
    nation, region = read_table(spark, sf_dir, "nation"), read_table(spark, sf_dir, "region")
    j = cloned.join(orders, "o_orderkey").join(customer, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey"))
    return j.rollup("r_name", "n_name").agg(F.count("*").alias("n_cloned"))


QUERIES["clone_report_by_nation"] = clone_report_by_nation
ORACLES["clone_report_by_nation"] = (
    f"WITH c AS ({ORACLES['order_seq_classes'].replace('SELECT sequence, min(k) AS rep_id, count(*) AS class_size FROM l GROUP BY sequence', 'SELECT k FROM l WHERE sequence IN (SELECT sequence FROM l GROUP BY sequence HAVING count(*) > 1)')}) "
    "SELECT r_name, n_name, count(*) AS n_cloned FROM c JOIN orders ON o_orderkey = k JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name)"
)


def word_near_copies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Near copies by words, at the default threshold and of any length: bags propose, the longest common subsequence of words decides.

    Documents without a word are copies of each other.
    """
    from pathtwin.frontends.text_lines import word_paths

    docs = read_table(spark, sf_dir, "documents", "doc_id", "text")
    return detect(word_paths(docs), DetectorConfig.plain().but(metric="lcs", encoding="none", min_lines=0)).select("left_id", "right_id", "distance")


QUERIES["word_near_copies"] = word_near_copies


def _scale(percent: int):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        """A nested subset of documents by id hash, and the fast detector on it."""
        from pathtwin.frontends.text_lines import line_paths

        docs = read_table(spark, sf_dir, "documents", "doc_id", "text")
        kept = F.conv(F.substring(F.md5(F.col("doc_id").cast("string")), 1, 6), 16, 10).cast("long") % 100 < percent
        p = line_paths(docs.filter(kept), "exact", 6)
        found = detect(p, DetectorConfig.fast().but(min_lines=6)).agg(F.count("*").alias("n_pairs"))
        size = p.agg(F.count("*").alias("n_fragments"), F.sum("n_lines").alias("n_lines"))
        return size.withColumn("one", F.lit(1)).join(found.withColumn("one", F.lit(1)), "one").drop("one")

    return run


for _p in (1, 10, 100):
    _name = f"doc_scale_{'all' if _p == 100 else _p}"
    QUERIES[_name] = _scale(_p)
    _sub = f"FROM documents WHERE CAST('0x' || substr(md5(CAST(doc_id AS VARCHAR)), 1, 6) AS BIGINT) % 100 < {_p}"
    _frag, _cl = O.fragments(6).replace("FROM documents", _sub), O.clones("hamming", 6, cap=DetectorConfig().max_len_diff).replace("FROM documents", _sub)
    ORACLES[_name] = f"WITH {_frag} SELECT count(*) AS n_fragments, CAST(sum(n) AS BIGINT) AS n_lines, (SELECT count(*) FROM ({_cl})) AS n_pairs FROM f"
