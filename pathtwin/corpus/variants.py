"""Labelled variants of documents: each kind stands for a clone type and is made by hashes, so any engine can rebuild it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathtwin.frontends.text_lines import abstract_line, fragments, normalised_lines
from pathtwin.functions import let

#: Share of edited lines in ten-thousandths.
EDITS = {"vst3": 600, "st3": 2000, "mt3": 4000}
KINDS = ("ty1", "ty2", *EDITS, "embed_head", "embed_tail", "permute", "shift")
EMBED = 20


def _number(doc: Column, i: Column, kind: str) -> Column:
    return F.conv(F.substring(F.md5(F.concat_ws("|", doc.cast("string"), (i + 1).cast("string"), F.lit(kind))), 1, 6), 16, 10).cast("long")


def _edited(doc: Column, s: Column, kind: str) -> Column:
    def edit(x: Column, i: Column) -> Column:
        return let(_number(doc, i, kind), lambda u: by_number(x, i, u))

    def by_number(x: Column, i: Column, u: Column) -> Column:
        what = F.floor(u / 10000) % 3
        new = F.concat(F.lit("new line "), (i + 1).cast("string"), F.lit(" ~"))
        changed = F.when(what == 0, F.array(F.concat(x, F.lit(" ~")))).when(what == 1, F.array(x, new)).otherwise(F.array().cast("array<string>"))
        return F.when(u % 10000 < EDITS[kind], changed).otherwise(F.array(x))

    return F.flatten(F.transform(s, edit))


def _fresh(doc: Column, n: int, kind: str) -> Column:
    return F.transform(F.sequence(F.lit(1), F.lit(n)), lambda i: F.concat_ws(" ", F.lit(kind), doc.cast("string"), i.cast("string")))


def _spaced(s: Column) -> Column:
    """Text of the same lines with other blanks, and an empty line after each."""
    return F.array_join(F.transform(s, lambda x: F.concat(F.lit("\t"), F.replace(x, F.lit(" "), F.lit(" \t ")), F.lit("  \n"))), "\n")


def _renamed(s: Column) -> Column:
    return F.transform(s, lambda x: F.translate(x, "aeiou", "eioua"))


def variants(docs: DataFrame, min_lines: int = 15) -> DataFrame:
    """Rows ``origin_id, kind, s, v, text``: lines of the original and of the variant, and the variant's text.

    ``ty1`` differs in blanks and empty lines before it goes through the frontend; the lines of ``ty2``, which is renamed, are
    kept in blind form on both sides.
    """
    f = fragments(docs, "exact", min_lines).select(F.col("fragment_id").alias("origin_id"), F.col("nodes").alias("s"))
    d, s = F.col("origin_id"), F.col("s")
    blind = lambda lines: F.transform(lines, lambda x: abstract_line(x, "blind"))
    swapped = F.transform(s, lambda x, i: F.coalesce(F.get(s, F.when(i % 2 == 0, i + 1).otherwise(i - 1)), x))
    plain = {
        **{k: _edited(d, s, k) for k in EDITS}, "embed_head": F.concat(_fresh(d, EMBED, "embed_head"), s), "embed_tail": F.concat(s, _fresh(d, EMBED, "embed_tail")),
        "permute": swapped, "shift": F.concat(_fresh(d, 1, "shift"), s),
    }
    made = {"ty1": (s, normalised_lines(_spaced(s)), _spaced(s)), "ty2": (blind(s), blind(_renamed(s)), F.array_join(_renamed(s), "\n")), **{k: (s, v, F.array_join(v, "\n")) for k, v in plain.items()}}
    rows = F.array(*[F.struct(F.lit(k).alias("kind"), a.alias("s"), v.alias("v"), t.alias("text")) for k, (a, v, t) in made.items()])
    return f.select("origin_id", F.explode(rows).alias("r")).select("origin_id", "r.*")
