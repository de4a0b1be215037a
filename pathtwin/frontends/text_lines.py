"""Documents as linear flow graphs: a line is a node, a document is one path (or one path a line)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def normalised_lines(text: Column) -> Column:
    """Lower-cased, blank-squeezed, non-empty lines."""
    lines = F.split(F.coalesce(text, F.lit("")), "\n", -1)
    return F.filter(F.transform(lines, lambda x: F.trim(F.regexp_replace(F.lower(x), "[ \t]+", " "))), lambda x: x != "")


def abstract_line(line: Column, mode: str = "exact") -> Column:
    """Node label: the text (``exact``), word-count band and punctuation (``blind``), or both with the first word kept (``keep_head``)."""
    if mode == "exact":
        return line
    blind = F.concat_ws(" ", F.floor(F.size(F.split(line, " ")) / 4).cast("string"), F.regexp_replace(line, r"[\p{L}\p{N} ]", ""))
    return blind if mode == "blind" else F.concat_ws(" ", F.element_at(F.split(line, " "), 1), blind)


def fragments(docs: DataFrame, mode: str = "exact", min_lines: int = 1) -> DataFrame:
    """Rows ``fragment_id, n_lines, nodes``. The size filter comes before the abstraction."""
    lines = docs.select(F.col("doc_id").alias("fragment_id"), normalised_lines(F.col("text")).alias("l")).withColumn("n_lines", F.size("l"))
    return lines.filter(F.col("n_lines") >= min_lines).select("fragment_id", "n_lines", F.transform("l", lambda x: abstract_line(x, mode)).alias("nodes"))


def line_paths(docs: DataFrame, mode: str = "exact", min_lines: int = 1) -> DataFrame:
    """PATHS of single-block documents."""
    f = fragments(docs, mode, min_lines)
    return f.select("fragment_id", "n_lines", F.lit(0).alias("path_no"), F.transform("nodes", lambda x: F.split(x, " ")).alias("nodes"), F.lit(1).alias("mult"))


def paragraph_paths(docs: DataFrame, min_lines: int = 1) -> DataFrame:
    """PATHS of documents as trees: the first sentence is the root, each line is a branch of its sentences."""
    f = fragments(docs, "exact", min_lines)
    lines = f.select("fragment_id", "n_lines", F.col("nodes")[0].alias("head"), F.posexplode("nodes").alias("path_no", "line"))
    sentences = F.filter(F.transform(F.split("line", r"\. "), lambda x: F.trim(x)), lambda x: x != "")
    root = F.array(F.trim(F.element_at(F.split("head", r"\. "), 1)))
    return lines.select("fragment_id", "n_lines", "path_no", F.transform(F.concat(root, sentences), lambda x: F.split(x, " ")).alias("nodes"), F.lit(1).alias("mult"))


def word_paths(docs: DataFrame) -> DataFrame:
    """PATHS of documents as one sequence of lower-cased words."""
    words = F.regexp_extract_all(F.lower(F.coalesce("text", F.lit(""))), F.lit(r"[\p{L}\p{N}_]+"), F.lit(0))
    return docs.select(F.col("doc_id").alias("fragment_id"), F.size(words).alias("n_lines"), F.lit(0).alias("path_no"), F.transform(words, lambda w: F.array(w)).alias("nodes"), F.lit(1).alias("mult"))
