"""Exception analysis across functions, to a fixpoint."""

from __future__ import annotations

from itertools import count

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathtwin.plans.lineage import cut


def propagate(calls: DataFrame, throws: DataFrame, catches: DataFrame, max_rounds: int | None = None) -> DataFrame:
    """Escaping exceptions ``fn, exc``.

    ``calls(caller, callee)``, ``throws(fn, exc)`` raised in the body, ``catches(fn, exc)`` handled there. Each
    round joins only the new facts to their callers; the rounds end when none is new. With ``max_rounds``, facts that need
    more are an error.
    """
    handled = catches.select("fn", "exc").distinct()
    handled, calls = cut(handled), cut(calls.select("caller", "callee").distinct())
    known = cut(throws.select("fn", "exc").distinct().join(handled, ["fn", "exc"], "left_anti"))
    new = known
    for n in count():
        if n == max_rounds:
            raise RuntimeError(f"exceptions still spread after {max_rounds} rounds")
        up = calls.join(new.withColumnRenamed("fn", "callee"), "callee").select(F.col("caller").alias("fn"), "exc").distinct()
        new = cut(up.join(handled, ["fn", "exc"], "left_anti").join(known, ["fn", "exc"], "left_anti"))
        if new.isEmpty():
            return known
        known = cut(known.unionByName(new))
    return known
