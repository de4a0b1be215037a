"""Statistics of whole texts as Column expressions: no Python runs on the executors.

A null text counts as empty. Sizes are unbounded: everything is linear in the text but the search for
repeated windows, which sorts a text's window hashes only where some window repeats.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

from pathtwin.llm.common import WORD

BLANKS = r"[\x20\x09-\x0D]+"
SPAN = 5


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """``body`` of ``value``, which is worked out once even where ``body`` uses it inside lambdas."""
    return F.transform(F.array(value), body)[0]


def words(text: Column) -> Column:
    return F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(WORD), F.lit(0))


def word_chars(text: Column) -> Column:
    return F.length(F.regexp_replace(F.coalesce(text, F.lit("")), BLANKS, "")).cast("long")


def chars_of(text: Column, kept: str) -> Column:
    """Number of characters outside the negated class ``kept``."""
    return F.length(F.regexp_replace(F.coalesce(text, F.lit("")), kept, "")).cast("long")


def n_symbols(text: Column) -> Column:
    return chars_of(text, r"[^#*$%&|<>]+")


def worded_lines(text: Column) -> Column:
    return F.filter(F.split(F.coalesce(text, F.lit("")), "\n", -1), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))


def n_dup_lines(lines: Column) -> Column:
    return (F.size(lines) - F.size(F.array_distinct(lines))).cast("long")


def _covered(hashes: Column, span: int) -> Column:
    """Words covered by the windows whose hash occurs twice or more."""
    paired = F.array_sort(F.transform(hashes, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))

    def starts(s: Column) -> Column:
        twin = lambda x, i: (F.get(s, i - 1)["h"] == x["h"]) | (F.get(s, i + 1)["h"] == x["h"])
        hit = F.filter(s, lambda x, i: F.coalesce(twin(x, i), (F.get(s, i - 1)["h"] == x["h"]), (F.get(s, i + 1)["h"] == x["h"]), F.lit(False)))
        return F.array_sort(F.transform(hit, lambda x: x["i"]))

    def add(acc: Column, i: Column) -> Column:
        end = i + F.lit(span)
        return F.struct(end.alias("end"), (acc["n"] + end - F.greatest(acc["end"], i)).cast("long").alias("n"))

    zero = F.struct(F.lit(0).alias("end"), F.lit(0).cast("long").alias("n"))
    return F.aggregate(let(paired, starts), zero, add, lambda acc: acc["n"])


def n_repeat_words(w: Column, span: int = SPAN) -> Column:
    """Words that lie in windows of ``span`` words found twice or more in the text, first ones included.

    Windows are told apart by a 64-bit hash of their words within one text.
    """

    def of(w: Column) -> Column:
        return F.transform(F.sequence(F.lit(0), F.size(w) - span), lambda i: F.xxhash64(*[F.get(w, i + k) for k in range(span)]))

    def count(h: Column) -> Column:
        return F.when(F.size(F.array_distinct(h)) == F.size(h), F.lit(0).cast("long")).otherwise(_covered(h, span))

    return F.when(F.size(w) < span + 1, F.lit(0).cast("long")).otherwise(let(let(w, of), count))
