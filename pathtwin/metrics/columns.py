"""Distances over array columns: Arrow functions for real work, Column expressions for short arrays."""

from __future__ import annotations

import pyarrow as pa
from pyspark.sql import Column
from pyspark.sql import functions as F

from pathtwin.config import DetectorConfig
from pathtwin.functions import let
from pathtwin.metrics import kernels as K
from pathtwin.metrics.kernels import REGISTRY


def distance_udf(metric: str, cfg: DetectorConfig | None = None):
    """Arrow function ``(array, array) -> double``: the normalised distance of two paths."""
    cfg = cfg or DetectorConfig.plain()

    kw = {"normalise": cfg.normalise, "sub_slack": cfg.sub_slack, "sub_min_len": cfg.sub_min_len, "max_len_diff": cfg.max_len_diff}

    @F.arrow_udf("double")
    def path_distance(a: pa.Array, b: pa.Array) -> pa.Array:
        return pa.array([K.path_distance(x, y, metric, cfg.tau, **kw) for x, y in zip(a.to_pylist(), b.to_pylist(), strict=True)], pa.float64())

    return path_distance


def _sets(column: pa.Array) -> list[list[tuple[tuple, int]]]:
    """Sets of ``(path, times)``; every path is made once a batch."""
    paths = column.values
    codes, times = paths.field("code"), paths.field("mult").to_pylist()
    at, symbols = codes.offsets.to_pylist(), codes.values.to_pylist()
    made = [(tuple(symbols[i:j]), n) for i, j, n in zip(at, at[1:], times, strict=False)]
    ends = column.offsets.to_pylist()
    return [made[i:j] for i, j in zip(ends, ends[1:], strict=False)]


#: Path distances that a batch remembers.
HELD = 200_000
#: Product of two sets' numbers of nodes up to which their symbols are compared before their paths are.
SMALL = 250_000


def set_distance_udf(cfg: DetectorConfig, cutoff: float | None = None):
    """Arrow function over two arrays of ``struct<code, mult>``: the distance of two description sets, exact below ``cutoff``."""

    @F.arrow_udf("double")
    def delta(a: pa.Array, b: pa.Array) -> pa.Array:
        kw = {"normalise": cfg.normalise, "sub_slack": cfg.sub_slack, "sub_min_len": cfg.sub_min_len}
        known, out = {}, []
        for x, y in zip(_sets(a), _sets(b), strict=True):
            if len(known) > HELD:
                known.clear()
            out.append(K.set_distance(x, y, cfg.metric, cfg.tau, cfg.tie, cfg.max_len_diff, cutoff, known, **kw))
        return pa.array(out, pa.float64())

    return delta


def may_be_near(cfg: DetectorConfig, a: Column, b: Column, na: Column, nb: Column) -> Column:
    """Whether two sets of ``struct<code, mult>`` can be within ``tau``, by the symbols that they have in common; false is sure.

    A path is at least as far from a set as the share of its nodes that the set lacks. In the modified LCS a path of more than
    ``sub_min_len`` nodes may also hold a shorter one, so there it counts as near from nine tenths of that length on.
    """
    if not REGISTRY[cfg.metric][2] or cfg.normalise != "longer":
        return F.lit(True)
    least = cfg.sub_min_len * (1 - cfg.sub_slack)

    def cover(x: Column, y: Column, n: Column) -> Column:
        def of(every: Column) -> Column:
            def one(p: Column) -> Column:
                common = F.size(F.filter(p["code"], lambda c: F.array_contains(every, c)))
                share = F.when(F.size(p["code"]) == 0, F.lit(1.0)).otherwise(common / F.size(p["code"]))
                if cfg.metric == "lcs_mod":
                    share = F.when((F.size(p["code"]) > cfg.sub_min_len) & (common >= least - 1e-9), F.lit(1.0)).otherwise(share)
                return share * p["mult"]

            return F.aggregate(F.transform(x, one), F.lit(0.0), lambda s, v: s + v) / n

        return let(F.array_distinct(F.flatten(F.transform(y, lambda p: p["code"]))), of)

    whole = lambda s: F.aggregate(F.transform(s, lambda p: F.size(p["code"])), F.lit(0), lambda t, v: t + v)
    enough = F.when(na < nb, cover(a, b, na)).when(nb < na, cover(b, a, nb)).otherwise(F.greatest(cover(a, b, na), cover(b, a, nb)))
    small = whole(a).cast("long") * whole(b) <= SMALL
    return F.when(small, enough > 1 - cfg.tau - 1e-9).otherwise(True)


def hamming(a: Column, b: Column) -> Column:
    """Null padding of the shorter side counts the tail."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.when(x.eqNullSafe(y), 0).otherwise(1)), F.lit(0), lambda s, x: s + x)


def hamming_free(a: Column, b: Column) -> Column:
    n = F.least(F.size(a), F.size(b))
    return hamming(F.slice(a, 1, n), F.slice(b, 1, n))


def lcs_length(a: Column, b: Column) -> Column:
    """Row recurrence: each row is the running maximum of the row before and its matches."""

    def row(prev: Column, x: Column) -> Column:
        cand = F.zip_with(F.zip_with(prev, F.concat(F.array(F.lit(0)), prev), lambda p, q: F.struct(p.alias("p"), q.alias("q"))), b, lambda s, y: F.when(s["p"].isNull(), None).when(x == y, F.greatest(s["p"], s["q"] + 1)).otherwise(s["p"]))
        return F.aggregate(F.filter(cand, lambda c: c.isNotNull()), F.expr("array(0)"), lambda acc, c: F.concat(acc, F.array(F.greatest(c, F.element_at(acc, -1)))), lambda acc: F.slice(acc, 2, F.size(acc) - 1))

    zero = F.transform(b, lambda _: F.lit(0))
    return F.coalesce(F.array_max(F.aggregate(a, zero, row)), F.lit(0))


def jaccard(a: Column, b: Column) -> Column:
    either = F.size(F.array_union(a, b))
    return F.when(either == 0, F.lit(0.0)).otherwise(1 - F.size(F.array_intersect(a, b)) / either)


def _times(s: Column, x: Column) -> Column:
    return F.size(F.filter(s, lambda y: y == x))


def cosine(a: Column, b: Column) -> Column:
    total = lambda s, of: F.aggregate(F.transform(F.array_distinct(s), of), F.lit(0).cast("long"), lambda t, x: t + x)
    square = lambda s: total(s, lambda x: _times(s, x) * _times(s, x))
    return 1 - total(a, lambda x: _times(a, x) * _times(b, x)) / F.sqrt(square(a) * square(b))


def common_items(a: Column, b: Column) -> Column:
    """Size of the multiset overlap."""
    return F.aggregate(F.transform(F.array_distinct(a), lambda x: F.least(_times(a, x), _times(b, x))), F.lit(0), lambda t, x: t + x)


def ngram(a: Column, b: Column) -> Column:
    """Share of pairs of neighbours that the two sides do not have in common; sides without a pair are at distance zero if both are, else one."""
    pairs = lambda s: F.when(F.size(s) < 2, F.array().cast("array<string>")).otherwise(F.transform(F.slice(s, 1, F.greatest(F.size(s) - 1, F.lit(0))), lambda x, i: F.concat_ws("\x01", x, F.get(s, i + 1))))
    ga, gb = pairs(a), pairs(b)
    total = F.size(ga) + F.size(gb)
    return F.when(total == 0, F.lit(0.0)).otherwise(1 - 2 * common_items(ga, gb) / total)


def as_characters(ids: Column, base: int = 0x4E00) -> Column:
    """One private character a symbol id, so string functions count symbols."""
    return F.array_join(F.transform(ids, lambda i: F.decode(F.unhex(F.lpad(F.hex(i + base), 4, "0")), "UTF-16BE")), "")
