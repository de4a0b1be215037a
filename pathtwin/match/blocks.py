"""Every pair of sets compared, in tasks that hold two blocks of them.

Where symbols are few or the result is a large share of all pairs, lists of candidates are longer than the table of
pairs itself. Here no candidate is written: a task keeps the symbols of one block as lists, runs every path of the
other block over them, and only pairs below the threshold leave it. Paths without a common symbol cost nothing.

``near_in_tiles`` gives the same pairs where most have some common symbol but few have enough of them: a product of matrices
bounds what every two sets of a task have in common, and only pairs that it leaves are compared.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from decimal import ROUND_HALF_UP, Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathtwin.config import DetectorConfig
from pathtwin.metrics import kernels as K

#: Sets and symbols that one side of a task holds at most, about, and sets from which on a block is split so that all cores have work.
BLOCK_SETS, BLOCK_SYMBOLS, SPLIT_SETS, SPLIT = 32_768, 1_000_000, 512, 8
#: Distances of paths that a task keeps at most.
KEPT = 8_000_000
#: Pairs that a task gathers before they leave it.
BATCH = 100_000
#: Columns that symbols of single paths and of larger sets are told apart by in a bound, sets in a tile of it, and pairs of paths that are compared at once.
COLUMNS, SET_COLUMNS, TILE, AT_ONCE = 512, 1200, 2048, 200_000

IN_ORDER, AT_PLACES = ("lcs", "lcs_mod", "alignment"), ("hamming", "hamming_free")


def can_compare(cfg: DetectorConfig) -> bool:
    """Whether the metric is one that blocks are compared by."""
    return cfg.metric in IN_ORDER + AT_PLACES and cfg.normalise == "longer" and cfg.tie == "min" and cfg.tau <= 1


class Side:
    """Sets of one block: paths in order of their sets, symbols in order of their paths."""

    def __init__(self, table: pa.Table):
        sets = table.column("paths").combine_chunks()
        self.id, self.size, self.one = (table.column(c).to_numpy() for c in ("id", "n_paths", "one"))
        ends, one = sets.offsets.to_numpy(), sets.flatten()
        codes = one.field("code")
        at = codes.offsets.to_numpy().astype(np.int64)
        self.mult, self.len, self.code = one.field("mult").to_numpy(), np.diff(at), codes.flatten().to_numpy()
        self.set_at = (ends - ends[0]).astype(np.int64)
        self.path_at = at - at[0]
        self.owner = np.repeat(np.arange(len(self.id)), np.diff(self.set_at))
        self.single = len(self.owner) == len(self.id)

    def places(self) -> np.ndarray:
        """The place of every symbol in its path."""
        return np.arange(len(self.code)) - np.repeat(self.path_at[:-1], self.len)

    def distinct(self) -> tuple[Side, np.ndarray]:
        """The different paths alone, and for each path its number among them."""
        first, number, at = {}, np.empty(len(self.len), np.int64), self.path_at.tolist()
        for q in range(len(self.len)):
            number[q] = first.setdefault(self.code[at[q] : at[q + 1]].tobytes(), len(first))
        mine = np.unique(number, return_index=True)[1]
        out = object.__new__(Side)
        out.len = self.len[mine]
        out.path_at = np.concatenate([[0], np.cumsum(out.len)])
        out.code = self.code[np.repeat(self.path_at[mine] - out.path_at[:-1], out.len) + np.arange(out.path_at[-1])]
        return out, number


def _keyed(a: Side, b: Side, at_places: bool) -> tuple[np.ndarray, np.ndarray, int]:
    """Symbols of both sides as numbers from 0 on; symbols at different places differ if only places count."""
    both = np.concatenate([a.code, b.code])
    keys, n = np.unique(both, return_inverse=True)[1].astype(np.int64), len(a.code)
    if at_places:
        keys = np.unique(keys * (1 << 32) + np.concatenate([a.places(), b.places()]), return_inverse=True)[1].astype(np.int64)
    return keys[:n], keys[n:], int(keys.max()) + 1 if len(keys) else 0


class Places:
    """Symbols that a path has in common with each path of a block, at equal places."""

    def __init__(self, side: Side, keys: np.ndarray, n_keys: int):
        order = np.argsort(keys, kind="stable")
        self.paths = np.repeat(np.arange(len(side.len)), side.len)[order]
        self.start, self.n = np.concatenate([[0], np.cumsum(np.bincount(keys, minlength=n_keys))]), len(side.len)

    def common(self, keys: np.ndarray) -> np.ndarray:
        lists = [self.paths[self.start[k] : self.start[k + 1]] for k in keys.tolist()]
        return np.bincount(np.concatenate(lists), minlength=self.n) if lists else np.zeros(self.n, np.int64)


class Order:
    """Longest common subsequences of a path with each path of a block whose length takes ``words`` words of bits."""

    def __init__(self, side: Side, keys: np.ndarray, n_keys: int, mine: np.ndarray, words: int):
        self.mine, self.words = mine, words
        number = np.full(len(side.len), -1)
        number[mine] = np.arange(len(mine))
        path = np.repeat(number, side.len)
        here = np.flatnonzero(path >= 0)
        place, path, keys = side.places()[here], path[here], keys[here]
        # one row a symbol and path, with the bits of all places of the symbol
        pair, back = np.unique(keys * len(mine) + path, return_inverse=True)
        self.bits = np.zeros((words, len(pair)), np.uint64)
        np.bitwise_or.at(self.bits, (place >> 6, back), np.uint64(1) << (place & 63).astype(np.uint64))
        self.path = pair % len(mine)
        self.start = np.searchsorted(pair, np.arange(n_keys + 1) * len(mine))
        self.full = np.full((words, len(mine)), ~np.uint64(0))
        left = np.clip(side.len[mine] - 64 * np.arange(words)[:, None], 0, 64)
        self.full[left < 64] = (np.uint64(1) << left[left < 64].astype(np.uint64)) - np.uint64(1)
        self.row = self.full.copy()

    def common(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Numbers of the paths with a common symbol, and the common lengths."""
        row, seen = self.row, []
        for low, high in zip(self.start[keys].tolist(), self.start[keys + 1].tolist(), strict=True):
            if low == high:
                continue
            at = self.path[low:high]
            seen.append(at)
            if self.words == 1:
                r = row[0, at]
                u = r & self.bits[0, low:high]
                row[0, at] = (r + u) | (r ^ u)
                continue
            carry = np.zeros(high - low, np.uint64)
            for w in range(self.words):
                r = row[w, at]
                u = r & self.bits[w, low:high]
                s = r + u
                t = s + carry
                carry = ((s < u) | (t < carry)).astype(np.uint64)
                row[w, at] = t | (r ^ u)
        if not seen:
            return self.mine[:0], self.mine[:0]
        at = np.unique(np.concatenate(seen)) if sum(map(len, seen)) < len(self.mine) else np.arange(len(self.mine))
        # bits beyond a path's end take carries, so they are masked
        gone = self.full[:, at] & ~row[:, at]
        row[:, at] = self.full[:, at]
        return self.mine[at], np.bitwise_count(gone).sum(axis=0, dtype=np.int64)


def _orders(side: Side, keys: np.ndarray, n_keys: int) -> list[Order]:
    words = np.maximum(1, -(-side.len // 64))
    words = np.where(words == 1, 1, 2 ** np.ceil(np.log2(words)).astype(np.int64))
    return [Order(side, keys, n_keys, np.flatnonzero(words == w), int(w)) for w in np.unique(words)]


def path_distances(common: np.ndarray, n: np.ndarray, m: int, cfg: DetectorConfig) -> np.ndarray:
    """Distances of paths of ``n`` symbols and one of ``m`` by what they have in common; as ``kernels.path_distance``."""
    longer, shorter = np.maximum(n, m), np.minimum(n, m)
    d = (shorter if cfg.metric == "hamming_free" else longer) - common
    plain = np.where(longer > 0, d / np.maximum(longer, 1), 0.0)
    if cfg.max_len_diff is not None:
        plain = np.where(longer - shorter > cfg.max_len_diff, 1.0, plain)
    if cfg.metric == "lcs_mod":
        inside = (plain >= cfg.tau) & (shorter >= cfg.sub_min_len) & (100 * common >= round(100 * (1 - cfg.sub_slack)) * shorter)
        plain = np.where(inside, (shorter - common) / np.maximum(shorter, 1), plain)
    return plain


def _asked(a: Side, b: Side, cfg: DetectorConfig) -> Callable[[int], tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For a path of ``b``: the numbers of the paths of ``a`` that may be nearer than one, what they have in common, their distances."""
    at_places = cfg.metric in AT_PLACES
    ka, kb, n_keys = _keyed(a, b, at_places)
    every, empty = np.arange(len(a.len)), np.flatnonzero(a.len == 0)
    places = Places(a, ka, n_keys) if at_places else None
    orders = [] if at_places else _orders(a, ka, n_keys)

    def of(q: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        keys, m = kb[b.path_at[q] : b.path_at[q + 1]], int(b.len[q])
        if at_places:
            at, common = every, places.common(keys)
        elif not m:
            at, common = empty, np.zeros(len(empty), np.int64)
        elif len(orders) == 1:
            at, common = orders[0].common(keys)
        else:
            found = [o.common(keys) for o in orders]
            at, common = (np.concatenate([f[k] for f in found]) for k in (0, 1))
        return at, common, path_distances(common, a.len[at], m, cfg)

    return of


def runs(a: Side, b: Side, cfg: DetectorConfig) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray]]:
    """What ``_asked`` says of each path of ``b``, after its number."""
    of = _asked(a, b, cfg)
    for q in range(len(b.len)):
        yield q, *of(q)


def set_distances(a: Side, b: Side, cfg: DetectorConfig) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """For each set of ``b``: its number, and those of the sets of ``a`` that may be nearer than one, with their distances; as ``kernels.set_distance``.

    Sets may have many paths in common with others: each different path is compared once, as long as its distances are kept.
    """
    if a.single and b.single:
        for q, at, _, d in runs(a, b, cfg):
            n = np.minimum(a.size[at], b.size[q])
            yield q, at, d * n / n
        return
    (some, ia), (ones, ib) = a.distinct(), b.distinct()
    of, n, kept, every = _asked(some, ones, cfg), len(some.len), {}, np.arange(len(a.id))
    for y in range(len(b.id)):
        best, back = np.ones(len(a.len)), np.zeros(len(a.id))
        for q in range(b.set_at[y], b.set_at[y + 1]):
            p = int(ib[q])
            if p not in kept:
                if (len(kept) + 1) * n > KEPT:
                    kept.clear()
                at, _, d = of(p)
                kept[p] = np.ones(n)
                kept[p][at] = d
            near = kept[p][ia]
            back += b.mult[q] * np.minimum.reduceat(near, a.set_at[:-1])
            np.minimum(best, near, out=best)
        there, home = np.bincount(a.owner, best * a.mult, len(a.id)) / a.size, back / b.size[y]
        yield y, every, np.where(a.size < b.size[y], there, np.where(a.size > b.size[y], home, np.minimum(there, home)))


def rounded(d: np.ndarray) -> np.ndarray:
    """``d`` to six places, halves up in decimal, as Spark's ``round``."""
    x = d * 1e6
    out = np.floor(x + 0.5) / 1e6
    for k in np.flatnonzero(np.abs(x - np.floor(x) - 0.5) < 1e-4):
        out[k] = float(Decimal(repr(float(d[k]))).quantize(Decimal("1e-6"), ROUND_HALF_UP))
    return out


def _sides(batches: Iterator[pa.RecordBatch]) -> tuple[Side | None, Side | None, bool]:
    """Both sides of a task, and whether they are one block."""
    t = pa.Table.from_batches(list(batches))
    i, j, sub = (t.column(c).to_numpy() for c in ("i", "j", "sub"))
    pick = lambda k: Side(t.filter(pa.array(sub == k))) if (sub == k).any() else None
    a = pick(i[0])
    return (a, a, True) if i[0] == j[0] else (a, pick(j[0]), False)


def _number(sets: DataFrame) -> int:
    """Blocks that ``sets`` are dealt over."""
    symbols = F.aggregate("paths", F.lit(0).cast("long"), lambda t, p: t + F.size(p["code"]))
    n, m = sets.agg(F.count("*"), F.coalesce(F.sum(symbols), F.lit(0))).first()
    return max(1, -(-n // BLOCK_SETS), -(-m // BLOCK_SYMBOLS), min(SPLIT, -(-n // SPLIT_SETS)))


def _dealt(sets: DataFrame, blocks: int) -> DataFrame:
    one = F.col("one") if "one" in sets.columns else F.lit(1).cast("long").alias("one")
    return sets.select(F.col("fragment_id").alias("id"), F.col("n_paths").cast("long").alias("n_paths"), "paths", one, F.pmod(F.xxhash64("fragment_id"), F.lit(blocks)).cast("int").alias("sub"))


def in_blocks(sets: DataFrame, work, schema: str) -> DataFrame:
    """What ``work(a, b, same)`` yields for every two blocks of ``sets(fragment_id, paths, n_paths, ...)``, and for each block with itself; ``work`` gives record batches.

    A column ``one`` is the weight of a set.
    """
    blocks, sub = _number(sets), F.col("sub")
    task = lambda k: F.struct(F.least(k, sub).alias("i"), F.greatest(k, sub).alias("j"))
    dealt = _dealt(sets, blocks).withColumn("t", F.explode(F.transform(F.sequence(F.lit(0), F.lit(blocks - 1)), task))).select("id", "n_paths", "paths", "one", "sub", "t.*")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a, b, same = _sides(batches)
        if a is not None and b is not None:
            yield from work(a, b, same)

    return dealt.repartition(min(2000, 2 * blocks * (blocks + 1)), "i", "j").groupBy("i", "j").applyInArrow(run, schema)


def nearest_in_blocks(queries: DataFrame, index: DataFrame, cfg: DetectorConfig, k: int) -> DataFrame:
    """Rows ``left_id, right_id, distance``: for each query and each block of ``index`` its ``k`` nearest sets there, ties by id, itself left out.

    Sets without a common symbol are at distance one, so of those the smallest ids will do.
    """
    n, m = _number(queries), _number(index)
    left = _dealt(queries, n).withColumns({"i": F.col("sub"), "j": F.explode(F.sequence(F.lit(0), F.lit(m - 1))), "side": F.lit(0)})
    right = _dealt(index, m).withColumns({"i": F.explode(F.sequence(F.lit(0), F.lit(n - 1))), "j": F.col("sub"), "side": F.lit(1)})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(batches))
        side = t.column("side").to_numpy()
        if side.all() or not side.any():
            return
        a, b = (Side(t.filter(pa.array(side == s))) for s in (1, 0))
        first, x, y, d = np.argsort(a.id)[: k + 1], [], [], []
        for q, at, near in set_distances(a, b, cfg):
            rest = np.setdiff1d(first, at)
            at, near = np.concatenate([at, rest]), np.concatenate([rounded(near), np.ones(len(rest))])
            other = a.id[at] != b.id[q]
            at, near = at[other], near[other]
            if len(at) > k:
                least = near <= np.partition(near, k - 1)[k - 1]
                at, near = at[least], near[least]
            best = np.lexsort((a.id[at], near))[:k]
            x.append(np.full(len(best), b.id[q]))
            y.append(a.id[at[best]])
            d.append(near[best])
        yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in (x, y, d)], ["left_id", "right_id", "distance"])

    dealt = left.unionByName(right)
    return dealt.repartition(min(2000, 4 * n * m), "i", "j").groupBy("i", "j").applyInArrow(run, "left_id long, right_id long, distance double")


def distance_counts(sets: DataFrame, cfg: DetectorConfig) -> DataFrame:
    """Rows ``distance, n``: how many pairs of sets with a common symbol are at each distance, as ``compare`` rounds it; a pair counts as often as the product of its weights ``one``."""
    if cfg.metric not in ("lcs", "alignment") or cfg.max_len_diff is not None or not can_compare(cfg):
        raise ValueError("the metric does not tell pairs with a common symbol by their distance")

    def work(a: Side, b: Side, same: bool) -> Iterator[pa.RecordBatch]:
        found, n = [], 0

        def counted() -> tuple[np.ndarray, np.ndarray]:
            d, at = np.unique(np.concatenate([f[0] for f in found]), return_inverse=True)
            total = np.zeros(len(d), np.int64)
            np.add.at(total, at, np.concatenate([f[1] for f in found]))
            return d, total

        for y, at, d in set_distances(a, b, cfg):
            # one common symbol is a distance below one
            met = (d < 1) & (a.id[at] < b.id[y]) if same else d < 1
            at, d = at[met], d[met]
            found.append((d, a.one[at] * b.one[y]))
            n += len(at)
            if n >= 10 * BATCH:
                found = [counted()]
                n = len(found[0][0])
        if found:
            d, total = counted()
            yield pa.RecordBatch.from_arrays([pa.array(d), pa.array(total)], ["d", "n"])

    return in_blocks(sets, work, "d double, n long").groupBy(F.round("d", 6).alias("distance")).agg(F.sum("n").alias("n"))


def near_pairs(sets: DataFrame, cfg: DetectorConfig) -> DataFrame:
    """Pairs of ``sets`` below ``tau``: ``left_id, right_id, distance, relation``, what ``compare`` says of all pairs."""
    if not can_compare(cfg):
        raise ValueError("the metric is not one that blocks are compared by")

    def work(a: Side, b: Side, same: bool) -> Iterator[pa.RecordBatch]:
        found, n = [], 0

        def gathered() -> pa.RecordBatch:
            x, y, d, strict = (np.concatenate(c) for c in zip(*found, strict=True))
            return pa.RecordBatch.from_arrays([pa.array(np.minimum(x, y)), pa.array(np.maximum(x, y)), pa.array(d), pa.array(strict)], ["left_id", "right_id", "d", "strict"])

        for y, at, d in set_distances(a, b, cfg):
            keep = d < cfg.tau + 1e-6
            at, d = at[keep], d[keep]
            ok = a.id[at] < b.id[y] if same else np.ones(len(at), bool)
            if cfg.max_set_factor is not None:
                ok &= np.maximum(a.size[at], b.size[y]) <= np.minimum(a.size[at], b.size[y]) * cfg.max_set_factor
            at, d = at[ok], d[ok]
            if len(at):
                found.append((a.id[at], np.full(len(at), b.id[y]), d, a.size[at] == b.size[y]))
                n += len(at)
            if n >= BATCH:
                yield gathered()
                found, n = [], 0
        if n:
            yield gathered()

    return _below(in_blocks(sets, work, NEAR), cfg)


NEAR = "left_id long, right_id long, d double, strict boolean"


def _below(found: DataFrame, cfg: DetectorConfig) -> DataFrame:
    out = found.withColumn("distance", F.round("d", 6)).filter(F.col("distance") < F.lit(cfg.tau))
    return out.select("left_id", "right_id", "distance", F.when(F.col("strict"), "strict").otherwise("partial").alias("relation"))


def near_by_both(sets: DataFrame, cfg: DetectorConfig, other: DetectorConfig) -> DataFrame:
    """Full join of the pairs below ``tau`` by one metric and by another, made in the tasks: ``left_id, right_id, d_one, d_other``; a distance from ``tau`` on is null.

    A task has all pairs of its two blocks by either metric, so no pair travels before it is joined. Sets are of one path each.
    """
    if not can_compare(cfg) or not can_compare(other) or cfg.tau != other.tau or cfg.max_set_factor != other.max_set_factor:
        raise ValueError("both metrics must be compared by blocks, at one threshold and one factor of sizes")
    tau, factor = cfg.tau, cfg.max_set_factor

    def work(a: Side, b: Side, same: bool) -> Iterator[pa.RecordBatch]:
        found, n = [], 0

        def gathered() -> pa.RecordBatch:
            x, y, d, e = (np.concatenate(c) for c in zip(*found, strict=True))
            near = [pa.array(v, mask=np.isnan(v)) for v in (d, e)]
            return pa.RecordBatch.from_arrays([pa.array(np.minimum(x, y)), pa.array(np.maximum(x, y)), *near], ["left_id", "right_id", "d_one", "d_other"])

        for (y, at, d), (_, at2, e) in zip(set_distances(a, b, cfg), set_distances(a, b, other), strict=True):
            both = np.full((2, len(a.id)), np.nan)
            both[0, at], both[1, at2] = d, e
            pick = np.flatnonzero((both < tau + 1e-6).any(axis=0))
            if same:
                pick = pick[a.id[pick] < b.id[y]]
            if factor is not None:
                pick = pick[np.maximum(a.size[pick], b.size[y]) <= np.minimum(a.size[pick], b.size[y]) * factor]
            if len(pick):
                near = rounded(both[:, pick].ravel()).reshape(2, -1)
                near[~(near < tau)] = np.nan
                pick, near = pick[k := ~np.isnan(near).all(axis=0)], near[:, k]
                found.append((a.id[pick], np.full(len(pick), b.id[y]), near[0], near[1]))
                n += len(pick)
            if n >= BATCH:
                yield gathered()
                found, n = [], 0
        if n:
            yield gathered()

    return in_blocks(sets, work, "left_id long, right_id long, d_one double, d_other double")


def _columns(keys: np.ndarray, columns: int) -> np.ndarray:
    """A column for each symbol; beyond three quarters of them rare symbols share one, which only loosens a bound."""
    distinct, at, n = np.unique(keys, return_inverse=True, return_counts=True)
    rank = np.empty(len(distinct), np.int64)
    rank[np.argsort(-n, kind="stable")] = np.arange(len(distinct))
    own = columns * 3 // 4 if len(distinct) > columns else columns
    return np.where(rank < own, rank, own + rank % max(1, columns - own))[at]


def _nth(side: Side, keys: np.ndarray, n_keys: int) -> np.ndarray:
    """The running number of every symbol among the equal ones of its path."""
    in_path = np.repeat(np.arange(len(side.len)), side.len) * n_keys + keys
    order = np.argsort(in_path, kind="stable")
    start = np.flatnonzero(np.diff(in_path[order], prepend=-1))
    out = np.empty(len(keys), np.int64)
    out[order] = np.arange(len(keys)) - np.repeat(start, np.diff(start, append=len(keys)))
    return out


def least_common(n: np.ndarray, m: np.ndarray, cfg: DetectorConfig) -> np.ndarray:
    """Symbols that paths of ``n`` and of ``m`` symbols have in common at least if they are nearer than ``tau``."""
    longer, shorter = np.maximum(n, m), np.minimum(n, m)
    need = (1 - cfg.tau - 2e-6) * longer - 1e-6
    if cfg.max_len_diff is not None:
        need = np.where(longer - shorter > cfg.max_len_diff, np.inf if cfg.tau < 1 else 0, need)
    if cfg.metric == "lcs_mod":
        need = np.where(shorter >= cfg.sub_min_len, np.minimum(need, round(100 * (1 - cfg.sub_slack)) * shorter / 100 - 1e-6), need)
    return need


def _tiles(n: int) -> list[slice]:
    return [slice(k, k + TILE) for k in range(0, n, TILE)]


def _thin_paths(a: Side, b: Side, cfg: DetectorConfig) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of sets of one path each that have enough symbols in common, whatever their order."""
    ka, kb, n_keys = _keyed(a, b, False)
    keys = np.concatenate([ka * (1 << 32) + _nth(a, ka, n_keys), kb * (1 << 32) + _nth(b, kb, n_keys)])
    column, sides = _columns(keys, COLUMNS), []
    for s, c in ((a, column[: len(ka)]), (b, column[len(ka) :])):
        order = np.argsort(s.len, kind="stable")
        row = np.empty(len(order), np.int64)
        row[order] = np.arange(len(order))
        held = np.bincount(np.repeat(row, s.len) * COLUMNS + c, minlength=len(order) * COLUMNS).astype(np.float32).reshape(-1, COLUMNS)
        sides.append((order, held, *np.unique(s.len[order], return_inverse=True)))
    (oa, xa, ua, la), (ob, xb, ub, lb) = sides
    need = least_common(ua[:, None], ub[None, :], cfg).astype(np.float32)
    can = need <= np.minimum(ua[:, None], ub[None, :])
    for s in _tiles(len(oa)):
        for t in _tiles(len(ob)):
            at, to = la[s], lb[t]
            if can[at[0] : at[-1] + 1, to[0] : to[-1] + 1].any():
                x, y = np.nonzero(xa[s] @ xb[t].T >= need[at][:, to])
                yield oa[s][x], ob[t][y]


def _weight(n: np.ndarray, cfg: DetectorConfig) -> np.ndarray:
    """What a symbol of a path of ``n`` takes off its distance at most; paths that may hold an embedded one weigh more."""
    one = 1 / np.maximum(n, 1)
    if cfg.metric != "lcs_mod":
        return one
    return np.where(n > cfg.sub_min_len, np.maximum(one, 1 / max(cfg.sub_min_len * (1 - cfg.sub_slack), 1e-9)), one)


def _lacking(common: np.ndarray, n: np.ndarray, cfg: DetectorConfig) -> np.ndarray:
    """Least distance of paths of ``n`` symbols from such as have ``common`` of them."""
    return np.where(n == 0, 0.0, np.maximum(1 - common * _weight(n, cfg), 0.0))


def _weights(side: Side, column: np.ndarray, cfg: DetectorConfig) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sets by size; the weights of their symbols in their order, and which symbols they hold."""
    order = np.argsort(side.size, kind="stable")
    row = np.empty(len(order), np.int64)
    row[order] = np.arange(len(order))
    w = side.mult / side.size[side.owner] * _weight(side.len, cfg)
    # an empty path counts as one of a symbol that no other has, in a column of its own
    n, empty = SET_COLUMNS + 1, np.flatnonzero(side.len == 0)
    cell = np.concatenate([row[np.repeat(side.owner, side.len)] * n + column, row[side.owner[empty]] * n + SET_COLUMNS])
    weight = np.bincount(cell, np.concatenate([np.repeat(w, side.len), w[empty]]), len(order) * n).astype(np.float32).reshape(-1, n)
    return order, weight, (weight > 0).astype(np.float32)


def _thin_sets(a: Side, b: Side, cfg: DetectorConfig) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Pairs of sets of which the smaller one's paths may have enough symbols in the larger one."""
    ka, kb, _ = _keyed(a, b, False)
    column = _columns(np.concatenate([ka, kb]), SET_COLUMNS)
    (oa, wa, pa_), (ob, wb, pb) = _weights(a, column[: len(ka)], cfg), _weights(b, column[len(ka) :], cfg)
    least, factor, na, nb = np.float32(1 - cfg.tau - 1e-4), cfg.max_set_factor or np.inf, a.size[oa], b.size[ob]
    for s in _tiles(len(oa)):
        for t in _tiles(len(ob)):
            n, m = na[s], nb[t]
            if n[0] > m[-1] * factor or m[0] > n[-1] * factor:
                continue
            hit = np.zeros((len(n), len(m)), bool)
            if n[0] <= m[-1]:
                hit |= (wa[s] @ pb[t].T >= least) & (n[:, None] <= m)
            if m[0] <= n[-1]:
                hit |= (pa_[s] @ wb[t].T >= least) & (n[:, None] >= m)
            x, y = np.nonzero(hit)
            near = np.maximum(n[x], m[y]) <= np.minimum(n[x], m[y]) * factor
            yield oa[s][x[near]], ob[t][y[near]]


def _thin_by_paths(a: Side, b: Side, ka: np.ndarray, kb: np.ndarray, n_keys: int, x: np.ndarray, y: np.ndarray, cfg: DetectorConfig) -> np.ndarray:
    """Which of the pairs ``x, y`` of sets may be near by what each path of ``x`` has in common with each single path of ``y``."""
    keep, order = np.zeros(len(x), bool), np.argsort(y, kind="stable")
    n_paths, kind = np.diff(a.set_at), np.uint16 if a.len.max() < 1 << 16 else np.int64
    for mine in np.split(order, np.flatnonzero(np.diff(y[order])) + 1):
        q0, q1 = b.set_at[y[mine[0]]], b.set_at[y[mine[0]] + 1]
        s0, s1, m = b.path_at[q0], b.path_at[q1], b.len[q0:q1]
        held = np.zeros((n_keys, q1 - q0), kind)
        held[kb[s0:s1], np.repeat(np.arange(q1 - q0), m)] = 1
        step = int(AT_ONCE // (q1 - q0) // n_paths[x[mine]].mean()) + 1
        for part in np.split(mine, range(step, len(mine), step)):
            at = x[part]
            paths = np.repeat(a.set_at[at] - np.cumsum(n_paths[at]) + n_paths[at], n_paths[at]) + np.arange(n_paths[at].sum())
            n = a.len[paths]
            # symbols are added place by place, over the paths that are long enough
            by_length = np.argsort(-n, kind="stable")
            start, left = a.path_at[paths[by_length]], np.searchsorted(-n[by_length], -np.arange(n.max()), side="left")
            total = np.zeros((len(paths), q1 - q0), held.dtype)
            for k, live in enumerate(left.tolist()):
                total[:live] += held.take(ka[start[:live] + k], axis=0)
            both = np.empty_like(total)
            both[by_length] = total
            ends, size, times = np.cumsum(n_paths[at]) - n_paths[at], b.size[y[mine[0]]], b.mult[q0:q1]

            def may(there: np.ndarray, home: np.ndarray, sizes: np.ndarray, size=size) -> np.ndarray:
                return np.where(sizes < size, there, np.where(sizes > size, home, np.minimum(there, home))) < cfg.tau + 1e-5

            # first by the most that a path has in common with any one
            there = np.add.reduceat(_lacking(both.max(axis=1), n, cfg) * a.mult[paths], ends) / a.size[at]
            home = (_lacking(np.maximum.reduceat(both, ends, axis=0), m, cfg) * times).sum(axis=1) / size
            near = may(there, home, a.size[at])
            if not near.any():
                continue
            rows = np.repeat(near, n_paths[at])
            n, both, paths, part, at = n[rows, None], both[rows].astype(np.int64), paths[rows], part[near], at[near]
            ends = np.cumsum(n_paths[at]) - n_paths[at]
            # with no threshold the modified LCS takes embedded paths as such whatever the plain distance, so more in common is never farther
            d = path_distances(np.minimum(both, np.minimum(n, m)), n, m, cfg.but(tau=-1.0))
            there = np.add.reduceat(d.min(axis=1) * a.mult[paths], ends) / a.size[at]
            home = (np.minimum.reduceat(d, ends, axis=0) * times).sum(axis=1) / size
            keep[part] = may(there, home, a.size[at])
    return keep


def common_lengths(codes: np.ndarray, n_at: np.ndarray, n: np.ndarray, m_at: np.ndarray, m: np.ndarray) -> np.ndarray:
    """Longest common subsequences of many pairs of paths, given by where they begin in ``codes`` and their lengths."""
    turn = n > m
    short_at, short, long_at, long = np.where(turn, m_at, n_at), np.minimum(n, m), np.where(turn, n_at, m_at), np.maximum(n, m)
    out, done = np.zeros(len(n), np.int64), 0
    for width, kind in ((8, np.uint8), (16, np.uint16), (32, np.uint32), (64, np.uint64)):
        mine = np.flatnonzero((short > done) & (short <= width))
        done = width
        if not len(mine):
            continue
        mine = mine[np.argsort(-long[mine], kind="stable")]
        at, row = np.arange(width), np.full(len(mine), np.iinfo(kind).max, kind)
        held = np.where(at < short[mine, None], codes[np.minimum(short_at[mine, None] + at, len(codes) - 1)], -1)
        start, left = long_at[mine], np.searchsorted(-long[mine], -np.arange(long[mine[0]]), side="left")
        for k, live in enumerate(left.tolist()):
            hits = np.packbits(held[:live] == codes[start[:live] + k, None], axis=1, bitorder="little").view(kind).ravel()
            r = row[:live]
            u = r & hits
            row[:live] = (r + u) | (r ^ u)
        out[mine] = width - np.bitwise_count(row)
    for k in np.flatnonzero(short > done).tolist():
        out[k] = K.lcs_length(codes[short_at[k] : short_at[k] + short[k]].tolist(), codes[long_at[k] : long_at[k] + long[k]].tolist())
    return out


def pair_distances(a: Side, b: Side, codes: np.ndarray, x: np.ndarray, y: np.ndarray, cfg: DetectorConfig) -> np.ndarray:
    """Distances of sets ``x`` of ``a`` and ``y`` of ``b``, pair by pair; as ``kernels.set_distance``. ``codes`` has the symbols of ``a``, then those of ``b``."""
    na, nb = np.diff(a.set_at)[x], np.diff(b.set_at)[y]
    n = na * nb
    start, pair = np.cumsum(n) - n, np.repeat(np.arange(len(x)), n)
    local = np.arange(n.sum()) - start[pair]
    i, j = local // nb[pair], local % nb[pair]
    p, q = a.set_at[x][pair] + i, b.set_at[y][pair] + j
    la, lb, common = a.len[p], b.len[q], np.zeros(len(p), np.int64)
    look = np.minimum(la, lb) > 0
    if cfg.max_len_diff is not None:
        # so unlike in length, they are as far apart as can be, unless one may lie in the other
        look &= (np.abs(la - lb) <= cfg.max_len_diff) | ((np.minimum(la, lb) >= cfg.sub_min_len) & (cfg.metric == "lcs_mod"))
    look = np.flatnonzero(look)
    common[look] = common_lengths(codes, a.path_at[p[look]], la[look], len(a.code) + b.path_at[q[look]], lb[look])
    d = path_distances(common, la, lb, cfg)
    back = np.empty(len(d))
    back[start[pair] + j * na[pair] + i] = d
    there, home = (_means(v, inner, outer, side, at) for v, inner, outer, side, at in ((d, nb, na, a, x), (back, na, nb, b, y)))
    return np.where(a.size[x] < b.size[y], there, np.where(a.size[x] > b.size[y], home, np.minimum(there, home)))


def _means(d: np.ndarray, inner: np.ndarray, outer: np.ndarray, side: Side, at: np.ndarray) -> np.ndarray:
    """For each pair the mean of the least of every ``inner`` distances, over the ``outer`` paths of its set of ``side``."""
    runs_of = np.repeat(inner, outer)
    best, pair = np.minimum.reduceat(d, np.cumsum(runs_of) - runs_of), np.repeat(np.arange(len(at)), outer)
    path = side.set_at[at][pair] + np.arange(len(pair)) - (np.cumsum(outer) - outer)[pair]
    return np.bincount(pair, best * side.mult[path], len(at)) / side.size[at]


def near_in_tiles(sets: DataFrame, cfg: DetectorConfig) -> DataFrame:
    """What ``near_pairs`` gives, by a bound on all pairs of a task and a comparison of those that it leaves."""
    if not can_compare(cfg) or cfg.metric not in IN_ORDER:
        raise ValueError("the metric is not one that common symbols bound")

    def work(a: Side, b: Side, same: bool) -> Iterator[pa.RecordBatch]:
        ka, kb, n_keys = _keyed(a, b, False)
        codes = np.concatenate([ka, kb])
        if len(codes) and codes.max() < 1 << 15:
            codes = codes.astype(np.int16)
        sizes = np.diff(a.set_at), np.diff(b.set_at)
        for x, y in (_thin_paths if a.single and b.single else _thin_sets)(a, b, cfg):
            if same:
                x, y = x[k := a.id[x] < b.id[y]], y[k]
            if cfg.max_set_factor is not None:
                x, y = x[k := np.maximum(a.size[x], b.size[y]) <= np.minimum(a.size[x], b.size[y]) * cfg.max_set_factor], y[k]
            if len(x) and not (a.single and b.single):
                x, y = x[k := _thin_by_paths(a, b, ka, kb, n_keys, x, y, cfg)], y[k]
            if not len(x):
                continue
            ends = np.cumsum(sizes[0][x] * sizes[1][y]) // AT_ONCE
            for part in np.split(np.arange(len(x)), np.flatnonzero(np.diff(ends)) + 1):
                x1, y1 = x[part], y[part]
                d = pair_distances(a, b, codes, x1, y1, cfg)
                x1, y1, d = (v[d < cfg.tau + 1e-6] for v in (x1, y1, d))
                if len(d):
                    p, q = a.id[x1], b.id[y1]
                    yield pa.RecordBatch.from_arrays([pa.array(v) for v in (np.minimum(p, q), np.maximum(p, q), d, a.size[x1] == b.size[y1])], ["left_id", "right_id", "d", "strict"])

    return _below(in_blocks(sets, work, NEAR), cfg)
