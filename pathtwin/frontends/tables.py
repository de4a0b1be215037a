"""Orders, pages, conversations and names as paths."""

from __future__ import annotations

from html.parser import HTMLParser

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def order_paths(lineitem: DataFrame) -> DataFrame:
    """PATHS of orders: a node is flag, status and quantity band of a line, in line order with full tie-break."""
    band = F.when(F.col("l_quantity") < 17, "a").when(F.col("l_quantity") < 34, "b").otherwise("c")
    row = F.struct("l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice", F.array("l_returnflag", "l_linestatus", band).alias("node"))
    g = lineitem.groupBy(F.col("l_orderkey").alias("fragment_id")).agg(F.array_sort(F.collect_list(row)).alias("rows"))
    return g.select("fragment_id", F.size("rows").alias("n_lines"), F.lit(0).alias("path_no"), F.transform("rows", lambda r: r["node"]).alias("nodes"), F.lit(1).alias("mult"))


def tag_paths(pages: DataFrame) -> DataFrame:
    """PATHS of pages: the sequence of their tags."""
    tags = F.regexp_extract_all(F.lower(F.coalesce("html", F.lit(""))), F.lit(r"<(/?[a-z][a-z0-9]*)"), F.lit(1))
    return pages.select(F.col("page_id").alias("fragment_id"), F.size(tags).alias("n_lines"), F.lit(0).alias("path_no"), F.transform(tags, lambda t: F.array(t)).alias("nodes"), F.lit(1).alias("mult"))


class _Tree(HTMLParser):
    VOID = {"br", "hr", "img", "input", "link", "meta"}

    def __init__(self):
        super().__init__()
        self.stack, self.leaves, self.open_leaf = [], [], False

    def handle_starttag(self, tag, attrs):
        self.stack.append(" ".join([tag, *sorted(k for k, _ in attrs)]))
        self.open_leaf = True
        if tag in self.VOID:
            self.handle_endtag(tag)

    def handle_endtag(self, tag):
        at = next((i for i in range(len(self.stack) - 1, -1, -1) if self.stack[i].split(" ")[0] == tag), None)
        if at is not None:
            if self.open_leaf:
                self.leaves.append(list(self.stack))
                self.open_leaf = False
            del self.stack[at:]


def dom_paths(pages: DataFrame) -> DataFrame:
    """PATHS of pages as trees; unclosed elements end with their parent."""

    def run(batches):
        for b in batches:
            rows = []
            for page, html in zip(b["page_id"], b["html"], strict=True):
                t = _Tree()
                t.feed(html or "")
                if t.open_leaf:
                    t.leaves.append(list(t.stack))
                rows += [(page, len(t.leaves), i, [x.split(" ") for x in p], 1) for i, p in enumerate(t.leaves)]
            yield pd.DataFrame(rows, columns=["fragment_id", "n_lines", "path_no", "nodes", "mult"])

    return pages.select("page_id", "html").mapInPandas(run, "fragment_id long, n_lines int, path_no int, nodes array<array<string>>, mult int")


def conversation_paths(turns: DataFrame) -> DataFrame:
    """PATHS of conversations: a node is role and length band of a turn."""
    band = F.when(F.length(F.coalesce("text", F.lit(""))) < 100, "s").when(F.length("text") < 300, "m").otherwise("l")
    row = F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce(band, F.lit("s")).alias("band"))
    g = turns.groupBy(F.col("conv_id").alias("fragment_id")).agg(F.array_sort(F.collect_list(row)).alias("rows"))
    return g.select("fragment_id", F.size("rows").alias("n_lines"), F.lit(0).alias("path_no"), F.transform("rows", lambda r: F.array(r["role"], r["band"])).alias("nodes"), F.lit(1).alias("mult"))
