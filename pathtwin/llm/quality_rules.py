"""Host-level quality rules, on DataFrame functions alone.

Every document is held against simple rules. Failures are summed by host (the ``source`` column);
a host's failure rate is shrunk towards the rate of all hosts by a beta prior that is fitted to the
hosts by moments, so a host with few documents is not judged on chance. Hosts whose shrunk rate of
base failures exceeds ``host_limit`` are rejected, and the verdict is joined back to the documents.

A null text is empty and so fails. A null source is no host: its documents are judged alone. Repeated
rows count as often as they occur. With fewer than two hosts, or hosts without any spread, the prior
has the weight of one document. An empty table gives an empty result. Columns of the input that have a
name of an added one are carried on as ``own_<name>``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathtwin.llm import text_stats as S
from pathtwin.plans.lineage import cut

HOST_LIMIT = 0.5
ADDED = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "n_lines", "base_failed", "shrunk_rate", "kept")
#: Tasks that the documents of one host are dealt over when they meet its verdict.
SALTS = 16


def measured(docs: DataFrame) -> DataFrame:
    """``docs`` with the statistics of each text and ``base_failed``; columns of added names become ``own_<name>``."""
    docs = docs.withColumnsRenamed({c: f"own_{c}" for c in docs.columns if c in ADDED})
    w, lines, text = "__words", "__lines", F.col("text")
    out = docs.withColumns({w: S.words(text), lines: S.worded_lines(text)}).withColumns({
        "n_words": F.size(w).cast("long"), "word_chars": S.word_chars(text), "n_symbols": S.n_symbols(text), "n_dup_lines": S.n_dup_lines(F.col(lines)),
        "n_repeat_words": S.n_repeat_words(F.col(w)), "n_lines": F.size(lines).cast("long"),
    })
    failed = (F.col("n_words") < 10) | (100 * F.col("n_repeat_words") > 20 * F.col("n_words"))
    return out.drop(w, lines).withColumn("base_failed", failed)


def host_verdicts(stats: DataFrame, host: str = "source", host_limit: float = HOST_LIMIT) -> DataFrame:
    """Rows ``host, n_docs, n_failed, shrunk_rate, host_rejected``. The prior is one row of sums over hosts."""
    rates = stats.filter(F.col(host).isNotNull()).groupBy(F.col(host).alias("host")).agg(F.count("*").alias("n_docs"), F.count_if("base_failed").alias("n_failed"))
    rate = F.col("n_failed") / F.col("n_docs")
    prior = rates.agg(F.avg(rate).alias("m"), F.var_pop(rate).alias("v"))
    weight = F.when((F.col("v") > 0) & (F.col("m") * (1 - F.col("m")) > F.col("v")), F.col("m") * (1 - F.col("m")) / F.col("v") - 1).otherwise(F.lit(1.0))
    prior = prior.select(F.lit(1).alias("one"), (F.col("m") * weight).alias("alpha"), weight.alias("weight"))
    shrunk = (F.col("n_failed") + F.col("alpha")) / (F.col("n_docs") + F.col("weight"))
    joined = rates.withColumn("one", F.lit(1)).join(F.broadcast(prior), "one")
    return joined.select("host", "n_docs", "n_failed", shrunk.alias("shrunk_rate")).withColumn("host_rejected", F.col("shrunk_rate") > host_limit)


def judge(docs: DataFrame, host_limit: float = HOST_LIMIT, keep_text: bool = True) -> DataFrame:
    """``docs`` with statistics, ``base_failed``, ``shrunk_rate`` and ``kept``.

    Statistics are worked out once and written, since both the host rates and the documents need them.
    The table of hosts is broadcast only if Spark finds it small enough; otherwise it is joined by shuffle,
    one row for each salt, so that a hot host is dealt over ``SALTS`` tasks.
    """
    found = measured(docs)
    stats = cut(found if keep_text else found.drop("text"))
    hosts = host_verdicts(stats, host_limit=host_limit).select(F.col("host").alias("__host"), "shrunk_rate", F.col("host_rejected").alias("__rejected"))
    hosts = hosts.withColumn("__salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    salt = F.pmod(F.xxhash64("doc_id", "n_words", "word_chars"), F.lit(SALTS)).cast("int")
    out = stats.withColumn("__deal", salt).join(hosts, (F.col("source") == F.col("__host")) & (F.col("__deal") == F.col("__salt")), "left")
    kept = ~F.col("base_failed") & ~F.coalesce("__rejected", F.lit(False))
    return out.withColumn("kept", kept).drop("__host", "__rejected", "__salt", "__deal")


ORACLE = r"""
WITH d AS (SELECT doc_id, source, coalesce(text, '') AS t FROM documents),
w AS (SELECT doc_id, source, t, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS w,
             list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM d),
win AS (SELECT doc_id, i, array_to_string(w[i:i + 4], ' ') AS g
        FROM (SELECT doc_id, w, unnest(range(1, len(w) - 3)) AS i FROM w WHERE len(w) >= 5)),
rep AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, g) AS n FROM win) WHERE n > 1),
cov AS (SELECT doc_id, count(DISTINCT i + k) AS n FROM rep, (SELECT unnest(range(0, 5)) AS k) GROUP BY doc_id),
s AS (SELECT w.doc_id, source, CAST(len(w) AS BIGINT) AS n_words,
             CAST(length(regexp_replace(t, '[\x20\x09-\x0D]+', '', 'g')) AS BIGINT) AS word_chars,
             CAST(length(regexp_replace(t, '[^#*$%&|<>]+', '', 'g')) AS BIGINT) AS n_symbols,
             CAST(len(l) - len(list_distinct(l)) AS BIGINT) AS n_dup_lines,
             CAST(coalesce(cov.n, 0) AS BIGINT) AS n_repeat_words
      FROM w LEFT JOIN cov USING (doc_id)),
b AS (SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM s),
h AS (SELECT source AS host, count(*) AS n, sum(CASE WHEN base_failed THEN 1 ELSE 0 END) AS k FROM b WHERE source IS NOT NULL GROUP BY source),
p AS (SELECT m, CASE WHEN v > 0 AND m * (1 - m) > v THEN m * (1 - m) / v - 1 ELSE 1 END AS wt
      FROM (SELECT avg(k / n) AS m, var_pop(k / n) AS v FROM h)),
r AS (SELECT host, (k + m * wt) / (n + wt) > 0.5 AS bad FROM h, p)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT base_failed AND NOT coalesce(bad, false) AS kept
FROM b LEFT JOIN r ON source = host
"""
