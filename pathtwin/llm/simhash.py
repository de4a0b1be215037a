"""SimHash near-duplicates through a byte-position inverted index with count filtering.

A fingerprint is eight positional bytes. Two that differ in at most two bits agree in at least six of them,
the guaranteed minimum. The index lists distinct fingerprints under each (position, byte); for every pair
that meets in lists, the shared positions are tallied, pairs short of the minimum are dropped and the rest
are verified on their bits.

A list of one byte holds about 1/256 of all fingerprints, and more of a hot byte, so a list longer than
``long_list`` is split by further positions: its fingerprints are listed under the bytes of every six
positions. A linked pair agrees in six positions at least, so it meets there, and the meeting counts for all
six positions. No list of six bytes holds more than 65,536 fingerprints, whatever the table. One that is still
longer than ``long_list`` is split by its last two bytes, each fingerprint under its own value and the 16 values one bit
away: pairs within two bits have such a value in common, and at most 17 fingerprints share one. So nothing
is dropped, no list is paired up beyond a bound, and tallies are exact for every pair that can link.

Texts are lower-cased in A-Z only; words are split at ASCII blanks. Fewer than three words give one
shingle of the whole sequence; no word, or a null text, gives fingerprint zero, which links like any
other. Copies share a fingerprint and are never paired up. Repeated rows are rows of one group. An
empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathtwin.llm.common import map_slices
from pathtwin.plans.components import connected_components
from pathtwin.plans.lineage import cut, settled

SEED = 42
#: Bits that linked fingerprints may differ in.
MAX_BITS = 2
POSITIONS = 8
#: Positional bytes that they must then share.
SHARED = POSITIONS - MAX_BITS
LONG_LIST = 32
#: Shingles counted at once.
STEP = 65536


def fingerprint(text: str | None, size: int = 3) -> int:
    """64-bit majority of the shingle hashes, unsigned."""
    from xxhash import xxh64_intdigest

    words = (text or "").encode("utf-8", "surrogatepass").lower().split()
    if not words:
        return 0
    joined = b" ".join(words)
    n = max(1, len(words) - size + 1)
    sizes = np.fromiter(map(len, words), np.int64, len(words)) + 1
    ends = np.cumsum(sizes) - 1
    first, last = (ends - sizes + 1)[:n], ends[len(words) - n :]
    ones = np.zeros(64, np.int64)
    for at in range(0, n, STEP):
        spans = zip(first[at : at + STEP].tolist(), last[at : at + STEP].tolist(), strict=True)
        h = np.array([xxh64_intdigest(joined[i:j], SEED) for i, j in spans], np.uint64)
        ones += np.unpackbits(h.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * ones > n, bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, size: int = 3) -> DataFrame:
    """Rows ``doc_id, th, fp``: a hash of the text, and the fingerprint as a signed long. One pass, no shuffle."""

    def run(parts: Iterator[dict]) -> Iterator[dict]:
        for p in parts:
            yield {"doc_id": p["doc_id"], "th": p["th"], "fp": np.array([fingerprint(t, size) for t in p["text"]], np.uint64).view(np.int64)}

    text = F.col("text").cast("string")
    named = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("th"), text.alias("text"))
    return map_slices(named, run, "doc_id long, th long, fp long")


def _signed(x: int) -> int:
    return x - (1 << 64) if x >> 63 else x


def _byte(p: int) -> Column:
    return F.shiftrightunsigned("fp", 8 * p).bitwiseAND(F.lit(255))


#: Lists are kept under one position, or under six: the positions of each kind of list, and the bits they cover.
KINDS = [(p,) for p in range(POSITIONS)] + list(combinations(range(POSITIONS), SHARED))
COVER = [sum(255 << 8 * p for p in kind) for kind in KINDS]


def _pairs(lists: DataFrame) -> DataFrame:
    """Rows ``a, b, kind`` of the pairs in sorted lists ``kind, fps``."""
    after = lambda x, i: F.transform(F.slice("fps", i + 2, F.size("fps")), lambda y: F.struct(x.alias("a"), y.alias("b")))
    return lists.select("kind", F.explode(F.flatten(F.transform("fps", after))).alias("p")).select("p.a", "p.b", "kind")


def fingerprint_links(fps: DataFrame, long_list: int = LONG_LIST) -> DataFrame:
    """Links ``a, b`` between distinct fingerprints ``fp``: all pairs within ``MAX_BITS`` bits.

    The driver sees the sizes of the 2,048 lists of one byte, which say whose fingerprints are split.
    """
    spots = F.array(*[F.lit(256 * p) + _byte(p).cast("int") for p in range(POSITIONS)])
    sizes = fps.select(F.explode(spots).alias("spot")).groupBy("spot").agg(F.count("*").alias("n"))
    hot = [0] * (4 * POSITIONS)
    for r in sizes.filter(F.col("n") > long_list).collect():
        hot[r["spot"] // 64] |= 1 << r["spot"] % 64
    if any(hot):
        bits = F.array(*[F.lit(_signed(x)).cast("long") for x in hot])
        is_hot = [F.getbit(F.get(bits, F.lit(4 * p) + F.shiftright(_byte(p).cast("int"), 6)), _byte(p).cast("int") % 64) == 1 for p in range(POSITIONS)]
    else:
        is_hot = [F.lit(False)] * POSITIONS
    some_hot = is_hot[0]
    for h in is_hot[1:]:
        some_hot = some_hot | h
    post = lambda k: F.struct(F.lit(k).alias("kind"), F.col("fp").bitwiseAND(F.lit(_signed(COVER[k]))).alias("value"))
    short = F.array_compact(F.array(*[F.when(~h, post(k)) for k, h in enumerate(is_hot)]))
    split = F.when(some_hot, F.array(*[post(k) for k in range(POSITIONS, len(KINDS))])).otherwise(F.array().cast("array<struct<kind:int,value:bigint>>"))
    posts = fps.select("fp", F.explode(F.concat(short, split)).alias("list")).select("fp", "list.*")
    lists = posts.groupBy("kind", "value").agg(F.collect_list("fp").alias("fps")).filter(F.size("fps") > 1)
    lists = cut(lists.select("kind", F.array_sort("fps").alias("fps"), "value"))
    few = _pairs(lists.filter(F.size("fps") <= long_list))
    free = F.array(*[F.array(*[F.lit(_signed(1 << b)).cast("long") for b in range(64) if not cover >> b & 1]) for cover in COVER[POSITIONS:]])
    many = lists.filter(F.size("fps") > long_list).withColumn("free", F.get(free, F.col("kind") - POSITIONS))
    many = many.select("kind", "value", "free", F.explode("fps").alias("fp"))
    rims = F.concat(F.array(F.col("fp")), F.transform("free", lambda bit: F.col("fp").bitwiseXOR(bit)))
    many = many.select("kind", "value", "fp", F.explode(rims).alias("rim"))
    many = many.groupBy("kind", "value", "rim").agg(F.collect_list("fp").alias("fps")).filter(F.size("fps") > 1)
    met = few.unionByName(_pairs(many.select("kind", F.array_sort("fps").alias("fps"))))
    positions = F.array(*[F.lit(sum(1 << p for p in kind)) for kind in KINDS])
    tally = met.groupBy("a", "b").agg(F.bit_or(F.get(positions, F.col("kind"))).alias("positions"))
    likely = tally.filter(F.bit_count("positions") >= SHARED)
    return likely.filter(F.bit_count(F.col("a").bitwiseXOR(F.col("b"))) <= MAX_BITS).select("a", "b")


def near_duplicates(docs: DataFrame, long_list: int = LONG_LIST, size: int = 3) -> DataFrame:
    """Rows ``doc_id, th, fp, fingerprint, component, component_id``.

    ``component`` is the smallest fingerprint of a group and is the group's own key; ``component_id`` is its smallest
    doc_id, which groups share where ids are null or repeat.
    """
    found = cut(fingerprints(docs, size))
    groups = cut(found.groupBy("fp").agg(F.min("doc_id").alias("least")))
    parts = settled(lambda: connected_components(fingerprint_links(groups.select("fp"), long_list)))
    parts = parts.withColumnRenamed("node", "fp")
    groups = groups.join(parts, "fp", "left").withColumn("component", F.coalesce("component", "fp"))
    least = groups.groupBy("component").agg(F.min("least").alias("component_id"))
    groups = groups.join(least, "component").select("fp", "component", "component_id")
    shown = F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint")
    return found.join(groups, "fp").select("doc_id", "th", "fp", shown, "component", "component_id")


def one_of_each(docs: DataFrame, long_list: int = LONG_LIST, size: int = 3) -> DataFrame:
    """``docs`` with one document of each group: that of the smallest id, then of the smallest text hash.

    A null id comes before all others. The verdicts are joined to the documents by id and text hash.
    """
    nobody, text_hash = F.lit(-(2**63)), F.xxhash64(F.col("text").cast("string"))
    keyed = docs.withColumns({"__k": F.coalesce(F.col("doc_id").cast("long"), nobody), "__th": text_hash})
    named = docs.select(F.coalesce(F.col("doc_id").cast("long"), nobody).alias("doc_id"), "text")
    found = near_duplicates(named, long_list, size)
    first = F.min(F.struct(F.col("doc_id").alias("__k"), F.col("th").alias("__th"))).alias("x")
    kept = found.groupBy("component").agg(first).select("x.*")
    return keyed.join(kept, ["__k", "__th"], "left_semi").dropDuplicates(["__k", "__th"]).drop("__k", "__th")
