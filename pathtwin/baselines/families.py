"""Rival detector families over documents. Each returns ``left_id, right_id``.

Most propose pairs by equi-joins of postings, those on bags and sets by lists inside tasks that hold two blocks; prefix
filters are lossless for their thresholds.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pathtwin.config import DetectorConfig
from pathtwin.frontends import text_lines as T
from pathtwin.functions import windows
from pathtwin.match.detector import detect
from pathtwin.metrics import distance_udf
from pathtwin.plans.lineage import cut


#: Items that one side of a task holds, and numbers that the frequencies of items are kept by. They only set how work is dealt out and ordered.
BLOCK_ITEMS, FREQUENCIES = 6_000_000, 1 << 16
#: Vectors that one side of a task holds at most, blocks that they are split into at least so that all cores have work, bands at most, vectors in a tile, pairs measured at once.
BLOCK_VECTORS, SPLIT, BANDS, TILE, AT_ONCE = 32_768, 8, 256, 1024, 100_000
_NTH = np.uint64(0x9E3779B97F4A7C15)


def _bags(column: pa.Array) -> pa.Array:
    """Lists of hashed words as ``size, key, bag``: distinct hashes in order with their numbers, as bytes."""
    out, ends, values = [], column.offsets.to_numpy(), column.values.to_numpy(zero_copy_only=False)
    for i, j in zip(ends, ends[1:], strict=False):
        words, times = np.unique(values[i:j].view(np.uint64), return_counts=True)
        bag = words.tobytes() + times.astype(np.uint32).tobytes()
        out.append({"size": int(j - i), "key": hashlib.md5(bag).hexdigest(), "bag": bag})
    return pa.array(out, pa.struct([("size", pa.int64()), ("key", pa.string()), ("bag", pa.binary())]))


def _items(bag: bytes) -> np.ndarray:
    """Hashes of the words of a bag, of repeated ones with their running numbers."""
    n = len(bag) // 12
    words, times = np.frombuffer(bag, np.uint64, n), np.frombuffer(bag, np.uint32, n, 8 * n).astype(np.int64)
    nth = np.arange(times.sum()) - np.repeat(np.cumsum(times) - times, times)
    return np.repeat(words, times) + nth.astype(np.uint64) * _NTH


def _slots(items: np.ndarray) -> np.ndarray:
    return (items >> np.uint64(48)).astype(np.int64)


def _item_frequencies(bags: DataFrame) -> np.ndarray:
    """Items by the first bits of their hashes."""

    def count(batches):
        total = np.zeros(FREQUENCIES, np.int64)
        for batch in batches:
            for bag in batch.column(0).to_pylist():
                total += np.bincount(_slots(_items(bag)), minlength=FREQUENCIES)
        hit = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(hit), pa.array(total[hit])], ["slot", "n"])

    out = np.zeros(FREQUENCIES, np.int64)
    for r in bags.select("bag").mapInArrow(count, "slot long, n long").groupBy("slot").agg(F.sum("n").alias("n")).collect():
        out[r["slot"]] = r["n"]
    return out


def _near_bags(block: pd.DataFrame, share: float, often: np.ndarray) -> pd.DataFrame:
    """Pairs ``x, y`` of one task: a block of a band with one of the same band, and with one of the band above.

    Items are ordered by frequency. Of a bag of ``n`` that needs ``t`` in common the first ``n - t + l`` are listed; two bags that
    overlap in ``t`` have at least ``l`` of the listed items in common, and pairs that have are counted in full.
    """
    band, i, j = (int(block[c].iloc[0]) for c in ("b", "i", "j"))
    ids, bands, subs = (block[c].to_numpy() for c in ("id", "band", "sub"))
    own, above = (bands == band) & (subs == j) & (j >= i), (bands == band + 1) & (subs == j)
    first, second = np.flatnonzero((bands == band) & (subs == i)), np.flatnonzero(own | above)
    if not len(first) or not len(second):
        return pd.DataFrame({"x": pd.Series([], dtype="int64"), "y": pd.Series([], dtype="int64")})
    bags, size = block["bag"].tolist(), block["size"].to_numpy()
    del block
    least = [round(n * share, 9) for n in size.tolist()]
    need = np.ceil(least).astype(np.int64)
    common = np.maximum(1, np.minimum(need, size // 12))
    distinct, ends = np.empty(0, np.uint64), np.cumsum(size)
    for part in np.split(np.arange(len(bags)), np.searchsorted(ends, np.arange(1_000_000, ends[-1], 1_000_000))):
        distinct = np.union1d(distinct, np.concatenate([_items(bags[k]) for k in part])) if len(part) else distinct
    place = np.empty(len(distinct), np.int32)
    place[np.lexsort((distinct, often[_slots(distinct)]))] = np.arange(len(distinct), dtype=np.int32)
    for k, bag in enumerate(bags):
        bags[k] = np.sort(place[np.searchsorted(distinct, _items(bag))])
    listed = [b[: n - t + c] for b, n, t, c in zip(bags, size, need, common, strict=True)]
    posts = np.concatenate([listed[k] for k in second])
    order = np.argsort(posts, kind="stable")
    holder = np.repeat(np.arange(len(second)), [len(listed[k]) for k in second])[order]
    start = np.concatenate([[0], np.cumsum(np.bincount(posts, minlength=len(distinct)))])
    held, x_out, y_out = np.zeros(len(distinct), bool), [], []
    for x in first:
        low, n = start[listed[x]], start[listed[x] + 1] - start[listed[x]]
        met = np.bincount(holder[np.repeat(low - np.cumsum(n) + n, n) + np.arange(n.sum())], minlength=len(second))
        near = second[met >= np.minimum(common[x], common[second])]
        near = near[(np.minimum(size[x], size[near]) >= need[near]) & (np.minimum(size[x], size[near]) >= need[x])]
        near = near[(bands[near] > band) | (subs[near] != i) | (ids[near] > ids[x])]
        held[bags[x]] = True
        for y in near:
            if np.count_nonzero(held[bags[y]]) >= max(least[x], least[y]):
                x_out.append(ids[x])
                y_out.append(ids[y])
        held[bags[x]] = False
    return pd.DataFrame({"x": np.array(x_out, np.int64), "y": np.array(y_out, np.int64)})


def _dealt_by_bands(rows: DataFrame, blocks: dict[int, int], *columns: str) -> DataFrame:
    """``rows(id, band, ...)`` dealt over ``blocks`` of each band, for tasks ``b, i, j``: block ``i`` of a band meets block ``j`` of the same and of the next."""
    many = F.create_map(*[F.lit(x) for b, n in blocks.items() for x in (b, n)]) if blocks else F.create_map(F.lit(0), F.lit(1))
    n_of = lambda b: F.coalesce(F.try_element_at(many, b), F.lit(0))
    number = lambda n, make: F.transform(F.filter(F.sequence(F.lit(0), F.greatest(n, F.lit(1)) - 1), lambda k: k < n), make)
    task = lambda b, i, j: F.struct(b.alias("b"), i.cast("int").alias("i"), j.cast("int").alias("j"))
    b, sub = F.col("band"), F.col("sub")
    met = F.concat(number(F.greatest(n_of(b), n_of(b + 1)), lambda j: task(b, sub, j)), number(sub, lambda i: task(b, i, sub)), number(n_of(b - 1), lambda i: task(b - 1, i, sub)))
    dealt = rows.withColumn("sub", F.pmod(F.xxhash64("id", F.lit(1)), n_of(b)).cast("int"))
    return dealt.select("id", "band", "sub", *columns, F.explode(met).alias("t")).select("id", "band", "sub", *columns, "t.*")


def _bag_overlap(words: DataFrame, share: float, once: bool = False) -> DataFrame:
    """Pairs of ``words(id, s)`` whose bags ``s`` of strings overlap in at least ``share`` of the larger; rows of one id are one bag.

    With ``once`` a string counts once in a bag.

    Equal bags are compared once. Bags are dealt out by bands of size, of which only neighbours can hold a pair, and by blocks in
    a band; every two blocks meet in one task, which keeps its lists of items to itself, so no pair travels that is not a result.
    """
    made = F.arrow_udf("size long, key string, bag binary")(_bags)
    band = F.floor(F.log(F.col("size").cast("double")) / (1e-9 - math.log(share)))

    def packed(words: DataFrame) -> DataFrame:
        words = words.filter((F.size("s") > 0) & F.col("id").isNotNull()).withColumn("s", F.array_distinct("s") if once else F.col("s"))
        bags = words.select("id", made(F.transform("s", lambda x: F.xxhash64(x))).alias("v")).select("id", "v.*")
        return cut(bags.withColumn("band", band.cast("int")))

    bags = packed(words)
    if bags.groupBy("id").count().filter("count > 1").head(1):
        bags = packed(words.groupBy("id").agg(F.flatten(F.collect_list("s")).alias("s")))
    of = cut(bags.select("id", "key").join(bags.groupBy("key").agg(F.min("id").alias("rep")), "key").select("id", "rep"))
    reps = bags.join(of.filter("id = rep").select("id"), "id", "left_semi")
    blocks = {r["band"]: -(-r["n"] // BLOCK_ITEMS) for r in bags.groupBy("band").agg(F.sum("size").alias("n")).collect()}
    dealt = _dealt_by_bands(reps, blocks, "size", "bag")
    often = _item_frequencies(bags)
    found = dealt.groupBy("b", "i", "j").applyInPandas(lambda block: _near_bags(block, share, often), "x long, y long")
    across = found.join(of.toDF("p", "x"), "x").join(of.toDF("q", "y"), "y").select(F.least("p", "q").alias("left_id"), F.greatest("p", "q").alias("right_id"))
    inside = of.alias("a").join(of.alias("b"), "rep").filter("a.id < b.id").select(F.col("a.id").alias("left_id"), F.col("b.id").alias("right_id"))
    return across.unionByName(inside)


def token_bag(docs: DataFrame, min_lines: int = 15, share: float = 0.7) -> DataFrame:
    """Bags of words; repeated words are numbered."""
    f = T.fragments(docs, min_lines=min_lines)
    return _bag_overlap(f.select(F.col("fragment_id").alias("id"), F.split(F.array_join("nodes", " "), " ").alias("s")), share)


def token_set(docs: DataFrame, min_lines: int = 15, share: float = 0.7) -> DataFrame:
    """Sets of blind lines with their first word; order does not matter."""
    f = T.fragments(docs, "keep_head", min_lines).select(F.col("fragment_id").alias("id"), F.col("nodes").alias("s"))
    return _bag_overlap(f, share, once=True)


def _sharing(f: DataFrame, need: Column) -> DataFrame:
    """Pairs ``x, y`` of ``f(id, s)`` where ``x`` may have ``need`` of its symbols in ``y``: one of its rarest is there.

    Lists of frequent symbols are joined only with fragments that have hardly any others.
    """
    rows = f.select("id", (F.size("s") - need + 1).alias("keep"), F.explode("s").alias("c"))
    every = rows.select("id", "c").distinct()
    often = every.groupBy("c").agg(F.count("*").alias("freq"))
    pos = F.row_number().over(Window.partitionBy("id").orderBy("freq", "c"))
    rare = rows.join(often, "c").withColumn("pos", pos).filter(F.col("pos") <= F.col("keep")).select("id", "c").distinct()
    return rare.toDF("x", "c").join(every.toDF("y", "c"), "c").filter("x <> y").select("x", "y").distinct()


def line_lcs(docs: DataFrame, min_lines: int = 15, tau: float = 0.3) -> DataFrame:
    """Blind lines compared by longest common subsequence; a difference below ``tau`` passes.

    Blind lines are few and frequent, so lists of them are long; a bound on every pair inside tasks needs none.
    """
    cfg = DetectorConfig.plain().but(metric="lcs", min_lines=min_lines, tau=tau, max_set_factor=None, candidates="tiles")
    return detect(T.line_paths(docs, "blind"), cfg).select("left_id", "right_id")


def line_windows(docs: DataFrame, min_lines: int = 15, size: int = 6, share: float = 0.6) -> DataFrame:
    """Windows of lines that match with at most one line replaced; both sides need ``share`` of their windows matched.

    A matched window has all but one of its lines on the other side and a line is in at most ``size`` windows, which says
    how many lines a pair shares at least.
    """
    code = lambda c: F.transform(c, lambda x: F.xxhash64(x))
    f = T.fragments(docs, min_lines=max(min_lines, size)).select(F.col("fragment_id").alias("id"), code(F.col("nodes")).alias("s"))
    f = f.withColumn("least", F.ceil(F.round((F.size("s") - size + 1) * share, 9)))
    pairs = _sharing(f, F.greatest(F.lit(size - 1), F.ceil(F.col("least") * (size - 1) / size))).filter("x < y")

    def holes(s: Column) -> Column:
        """For each window its hash with one line left out, for each of its lines."""
        left_out = lambda i, k: F.xxhash64(F.lit(k), *[F.get(s, i - 1 + j) for j in range(size) if j != k])
        return F.transform(F.sequence(F.lit(1), F.size(s) - size + 1), lambda i: F.array(*[left_out(i, k) for k in range(size)]))

    h = f.select("id", "least", holes(F.col("s")).alias("h"))
    both = pairs.join(h.toDF("x", "nx", "hx"), "x").join(h.toDF("y", "ny", "hy"), "y").withColumn("common", F.array_intersect(F.flatten("hx"), F.flatten("hy")))
    hits = lambda c: F.size(F.filter(c, lambda w: F.arrays_overlap(w, F.col("common"))))
    return both.filter((hits(F.col("hx")) >= F.col("nx")) & (hits(F.col("hy")) >= F.col("ny"))).select(F.col("x").alias("left_id"), F.col("y").alias("right_id"))


def runs(f: DataFrame, block: int = 15, least: int = 50, among: DataFrame | None = None) -> DataFrame:
    """Pairs of ``f(id, w)`` with runs of equal tokens: hashed blocks are joined and consecutive ones chained on their diagonal; runs add up to ``least`` tokens.

    With ``among(left_id, right_id)`` only those pairs are looked at.
    """
    hashes = F.transform(windows(F.col("w"), block), lambda x: F.xxhash64(x))
    if among is None:
        return _all_runs(f.select("id", F.md5(F.to_json("w")).alias("key"), hashes.alias("hs")), block, least)
    g = cut(f.select("id", F.posexplode(hashes).alias("pos", "h")))
    m = among.select(F.col("left_id").alias("x"), F.col("right_id").alias("y")).filter("x < y").distinct()
    m = m.join(g.toDF("x", "p", "h"), "x").join(g.toDF("y", "q", "h"), ["y", "h"]).select("x", "y", (F.col("p") - F.col("q")).alias("diag"), F.col("p").alias("pos"))
    island = F.col("pos") - F.row_number().over(Window.partitionBy("x", "y", "diag").orderBy("pos"))
    found = m.withColumn("island", island).groupBy("x", "y", "diag", "island").agg((F.count("*") + block - 1).alias("words"))
    total = found.groupBy("x", "y").agg(F.sum("words").alias("words")).filter(F.col("words") >= least)
    return total.select(F.col("x").alias("left_id"), F.col("y").alias("right_id"))


def _all_runs(f: DataFrame, block: int, least: int) -> DataFrame:
    """Pairs of ``f(id, key, hs)`` as in ``runs``: equal texts are matched once, and blocks that always follow each other travel as one.

    A block has one follower if every place of it has that one next, and a block is a beginning unless the one before it has it as
    its only follower and is before it everywhere. So a chain is the same wherever its first block is, and chains are joined in place of blocks.
    """
    f = cut(f)
    texts = cut(f.groupBy("key").agg(F.min("id").alias("rep"), F.count("*").alias("copies")))
    of = f.select("id", "key").join(texts, "key").select("id", "rep")
    at = F.transform("hs", lambda h, i: F.struct(F.get("hs", i - 1).alias("before"), h.alias("h"), F.get("hs", i + 1).alias("after")))
    rows = f.join(texts.select(F.col("rep").alias("id"), "copies"), "id").select("id", "copies", F.posexplode(at).alias("pos", "b")).select("id", "copies", "pos", "b.*")
    g = cut(rows)
    only = lambda c: (F.count(c) == F.count("*")) & (F.min(c) == F.max(c))
    known = g.groupBy("h").agg(F.coalesce(only("before"), F.lit(False)).alias("one_before"), F.coalesce(only("after"), F.lit(False)).alias("one_after"), F.count("*").alias("n"))
    w = Window.partitionBy("id").orderBy("pos")
    g = g.join(known, "h").filter((F.col("n") > 1) | (F.col("copies") > 1))
    follows = (F.lag("pos").over(w) == F.col("pos") - 1) & F.lag("one_after").over(w) & F.col("one_before")
    chains = g.withColumn("new", (~F.coalesce(follows, F.lit(False))).cast("int")).withColumn("chain", F.sum("new").over(w))
    chains = cut(chains.groupBy("id", "copies", "chain").agg(F.min("pos").alias("pos"), F.min_by("h", "pos").alias("first"), F.count("*").alias("n")))
    a, b = chains.select(F.col("id").alias("x"), F.col("pos").alias("p"), "first", "n", "copies"), chains.select(F.col("id").alias("y"), F.col("pos").alias("q"), "first")
    m = a.join(b, "first").filter((F.col("x") < F.col("y")) | ((F.col("x") == F.col("y")) & (F.col("copies") > 1))).select("x", "y", (F.col("p") - F.col("q")).alias("diag"), F.col("p").alias("pos"), "n")
    goes_on = F.lag(F.col("pos") + F.col("n")).over(Window.partitionBy("x", "y", "diag").orderBy("pos")) == F.col("pos")
    words = F.col("n") + F.when(F.coalesce(goes_on, F.lit(False)), 0).otherwise(block - 1)
    total = cut(m.withColumn("words", words).groupBy("x", "y").agg(F.sum("words").alias("words")).filter(F.col("words") >= least).select("x", "y"))
    both = total.join(of.toDF("left_id", "x"), "x").join(of.toDF("right_id", "y"), "y")
    return both.filter((F.col("x") < F.col("y")) | (F.col("left_id") < F.col("right_id"))).select(F.least("left_id", "right_id").alias("left_id"), F.greatest("left_id", "right_id").alias("right_id"))


def token_runs(docs: DataFrame, min_lines: int = 15, block: int = 15, least: int = 50) -> DataFrame:
    """Runs of equal words of documents."""
    f = T.fragments(docs, min_lines=min_lines).select(F.col("fragment_id").alias("id"), F.split(F.array_join("nodes", " "), " ").alias("w"))
    return runs(f, block, least)


def ngram_index(docs: DataFrame, min_lines: int = 15, n: int = 5, share: float = 0.1, verify: float = 0.7) -> DataFrame:
    """Common n-grams of lines filter, the longest common subsequence over the shorter side verifies.

    What verifies bounds what the shorter side has in common, so its rarest lines propose the pairs whose n-grams are counted.
    """
    f = T.fragments(docs, min_lines=min_lines).select(F.col("fragment_id").alias("id"), F.transform("nodes", lambda x: F.xxhash64(x)).alias("s"))
    f = f.withColumn("g", F.array_distinct(F.transform(F.sequence(F.lit(0), F.size("s") - n), lambda i: F.xxhash64(*[F.get("s", i + k) for k in range(n)])))).filter(F.size("s") >= n)
    left, right = f.toDF("x", "sx", "gx"), f.toDF("y", "sy", "gy")
    shorter = F.least(F.size("sx"), F.size("sy"))
    near = _sharing(f, F.ceil(F.round(F.size("s") * verify, 9))).join(left, "x").join(right, "y").filter(F.size("sx") <= F.size("sy"))
    common = F.size(F.array_intersect("gx", "gy"))
    near = near.filter((common > 0) & (common >= F.least(F.size("gx"), F.size("gy")) * share))
    length = F.greatest(F.size("sx"), F.size("sy")) - distance_udf("lcs", DetectorConfig.plain().but(normalise="none"))("sx", "sy")
    found = near.filter(length >= F.round(shorter * verify, 9))
    return found.select(F.least("x", "y").alias("left_id"), F.greatest("x", "y").alias("right_id")).distinct()


def _near_vectors(block: pa.Table, radius: float) -> Iterator[pa.RecordBatch]:
    """Pairs of one task, dealt out as in ``_near_bags``: vectors nearer than ``radius`` that agree on one of their buckets.

    A product of matrices bounds all distances of a tile; what it leaves is measured dimension by dimension.
    """
    band, i, j = (block.column(c)[0].as_py() for c in ("b", "i", "j"))
    ids, bands, subs = (block.column(c).to_numpy() for c in ("id", "band", "sub"))
    first, second = np.flatnonzero((bands == band) & (subs == i)), np.flatnonzero(((bands == band) & (subs == j) & (j >= i)) | ((bands == band + 1) & (subs == j)))
    if not len(first) or not len(second):
        return
    v, h = (block.column(c).combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1) for c in ("v", "h"))
    low = v - v[first].mean(axis=0)
    square = np.einsum("ij,ij->i", low, low)
    # errors of a product in four bytes must stay small beside the radius
    kind, error = (np.float32, 1e-5) if 1e-3 * square.max() < radius * radius else (np.float64, 1e-12)
    own = np.concatenate([low, square[:, None], np.ones((len(low), 1))], axis=1).astype(kind)
    other = np.concatenate([-2 * low, np.ones((len(low), 1)), square[:, None]], axis=1).astype(kind)
    least = kind(radius * radius + 4 * error * square.max() + error)
    for s in range(0, len(first), TILE):
        x0 = first[s : s + TILE]
        for t in range(0, len(second), TILE):
            y0 = second[t : t + TILE]
            at = np.flatnonzero(~(own[x0] @ other[y0].T > least))
            for part in np.split(at, range(AT_ONCE, len(at), AT_ONCE)):
                x, y = x0[part // len(y0)], y0[part % len(y0)]
                met = (h[x] == h[y]).any(axis=1) & (ids[x] != ids[y]) & ((bands[y] > band) | (subs[y] != i) | (ids[y] > ids[x]))
                x, y, d = x[met], y[met], np.zeros(met.sum())
                for k in range(v.shape[1]):
                    d += (v[x, k] - v[y, k]) ** 2
                d = np.sqrt(d)
                x, y, d = ids[x[near := d < radius]], ids[y[near]], d[near]
                if len(d):
                    yield pa.RecordBatch.from_arrays([pa.array(c) for c in (np.minimum(x, y), np.maximum(x, y), d)], ["left_id", "right_id", "d"])


def tree_vector(vectors: DataFrame, radius: float) -> DataFrame:
    """Euclidean near pairs of count vectors by random-projection buckets (lossy).

    Buckets are four radii wide, so near vectors are in equal or neighbouring ones of the first table. Every two blocks of such
    meet in one task, which looks at all tables; pairs that share a bucket and are not near never leave it.
    """
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector, vector_to_array

    v = vectors.select("id", array_to_vector(F.col("v").cast("array<double>")).alias("v"))
    model = BucketedRandomProjectionLSH(inputCol="v", outputCol="h", bucketLength=radius * 4, numHashTables=6, seed=5).fit(v)
    hashed = cut(model.transform(v).select("id", vector_to_array("v").alias("v"), F.array(*[vector_to_array(F.col("h")[k])[0] for k in range(6)]).alias("h")).filter("id is not null"))
    hashed = hashed.filter(F.forall("v", lambda x: F.abs(x) < float("inf")))  # others are near nothing
    low, high = hashed.agg(F.min(F.col("h")[0]), F.max(F.col("h")[0])).first()
    wide = max(1.0, ((high or 0.0) - (low or 0.0) + 1) // BANDS)
    rows = hashed.withColumn("band", F.floor((F.col("h")[0] - F.lit(low or 0.0)) / wide).cast("int"))
    counts = {r["band"]: r["n"] for r in rows.groupBy("band").agg(F.count("*").alias("n")).collect()}
    total = sum(counts.values())
    each = min(BLOCK_VECTORS, max(TILE, -(-total // SPLIT)))
    dealt = _dealt_by_bands(rows, {b: -(-n // each) for b, n in counts.items()}, "v", "h")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from _near_vectors(pa.Table.from_batches(list(batches)), radius)

    found = dealt.groupBy("b", "i", "j").applyInArrow(run, "left_id long, right_id long, d double")
    return found.select("left_id", "right_id", F.round("d", 6).alias("distance")).distinct()


def projection_bands(vectors: DataFrame, cosine: float = 0.9, bands: int = 12, rows: int = 10, seed: int = 11) -> DataFrame:
    """Pairs of vectors that agree on all signs of one of ``bands`` groups of ``rows`` random projections and reach ``cosine`` (lossy).

    Equal vectors are compared once and their results copied, so copies do not fill a bucket.
    """
    @F.pandas_udf("array<long>")
    def keys(v: pd.Series) -> pd.Series:
        if not len(v):
            return pd.Series([], dtype=object)
        x = np.stack(v.to_numpy()).astype(np.float64)
        planes = np.random.default_rng(seed).standard_normal((x.shape[1], bands * rows))
        bits = (x @ planes > 0).reshape(len(x), bands, rows)
        return pd.Series(list(bits @ (1 << np.arange(rows, dtype=np.int64))))

    v = vectors.select("id", F.col("v").cast("array<double>").alias("v")).filter(F.size("v") > 0)
    members = v.groupBy("v").agg(F.min("id").alias("rep"))
    reps = members.select("rep", "v")
    posts = reps.select("rep", F.posexplode(keys("v")).alias("band", "key"))
    pairs = posts.alias("a").join(posts.alias("b"), ["band", "key"]).filter("a.rep < b.rep").select(F.col("a.rep").alias("p"), F.col("b.rep").alias("q")).distinct()
    joined = pairs.join(reps.toDF("p", "x"), "p").join(reps.toDF("q", "y"), "q")
    dot = lambda x, y: F.aggregate(F.zip_with(x, y, lambda s, t: s * t), F.lit(0.0), lambda t, z: t + z)
    joined = joined.withColumn("cosine", dot(F.col("x"), F.col("y")) / F.sqrt(dot(F.col("x"), F.col("x")) * dot(F.col("y"), F.col("y"))))
    of = v.join(members, "v").select("id", "rep")
    near = joined.filter(F.col("cosine") >= cosine).select("p", "q", "cosine")
    across = near.join(of.toDF("a", "p"), "p").join(of.toDF("b", "q"), "q").select(F.least("a", "b").alias("left_id"), F.greatest("a", "b").alias("right_id"), F.round("cosine", 6).alias("cosine"))
    inside = of.alias("m").join(of.alias("n"), "rep").filter("m.id < n.id").select(F.col("m.id").alias("left_id"), F.col("n.id").alias("right_id"), F.lit(1.0).alias("cosine"))
    return across.unionByName(inside)


FEATURES = ("lines", "words", "chars", "digits", "marks", "heads")


def line_counts(c: Column) -> Column:
    """Counts of an array of lines."""
    text = F.array_join(c, "\n")
    heads = F.array_distinct(F.transform(c, lambda x: F.element_at(F.split(x, " "), 1)))
    cols = (F.size(c), F.size(F.split(text, "[ \n]")), F.length(text), F.length(F.regexp_replace(text, "[^0-9]+", "")), F.length(F.regexp_replace(text, r"[\p{L}\p{N}\s]+", "")), F.size(heads))
    return F.array(*[x.cast("double") for x in cols])


def features(docs: DataFrame, min_lines: int = 15) -> DataFrame:
    """Counts of a fragment, the input of the learned filter."""
    f = T.fragments(docs, min_lines=min_lines)
    heads = F.array_distinct(F.transform("nodes", lambda x: F.element_at(F.split(x, " "), 1)))
    return f.select(F.col("fragment_id").alias("id"), heads.alias("actions"), line_counts(F.col("nodes")).alias("x"))


def learned(docs: DataFrame, truth: DataFrame, action_share: float = 0.55, size_share: float = 0.6) -> DataFrame:
    """Action-overlap and size filters, then a logistic model on relative feature differences, fitted on labelled pairs ``a, b, y`` of counts."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.functions import array_to_vector, vector_to_array

    relative = lambda a, b: F.zip_with(a, b, lambda p, q: F.abs(p - q) / F.greatest(F.lit(1.0), p, q))
    seen = cut(truth.select(relative(F.col("a"), F.col("b")).alias("v"), F.col("y").cast("double").alias("y")))
    model = LogisticRegression(featuresCol="v", labelCol="y", regParam=0.01).fit(seen.withColumn("v", array_to_vector("v")))
    f = features(docs)
    pairs = _bag_overlap(f.select("id", F.col("actions").alias("s")), action_share, once=True)
    a, b = f.select(F.col("id").alias("left_id"), F.col("x").alias("xa")), f.select(F.col("id").alias("right_id"), F.col("x").alias("xb"))
    near = pairs.join(a, "left_id").join(b, "right_id").filter(F.least(F.col("xa")[1], F.col("xb")[1]) >= size_share * F.greatest(F.col("xa")[1], F.col("xb")[1]))
    scored = model.transform(near.withColumn("v", array_to_vector(relative(F.col("xa"), F.col("xb")))))
    return scored.filter(vector_to_array("probability")[1] >= 0.5).select("left_id", "right_id")
