"""Removal of repeated byte passages by distributed difference-cover suffix sorting.

Every byte that lies in a string of ``length`` bytes that also starts elsewhere is removed. Sorting the
suffixes of a whole corpus would move many times its size, so exact steps first narrow the text down:

1. Anchors. Among the hashes of the K-byte strings in every window of ``length`` bytes the least is an
   anchor. Two equal windows have the same anchor at the same place, so a window can repeat only if its
   anchor's K bytes do; anchors that occur once are dropped.
2. Contexts. All windows of an anchor lie in a context of fixed reach around it. Equal contexts repeat as
   a whole and are settled at once; one of each goes on, if the anchor has different contexts too.
3. Blocks. The starts of the windows in a context are taken in blocks; all windows of a block share a
   core. Blocks with a core of their own cannot repeat. In the others the core, which is common to its
   class, is replaced with one symbol.
4. Suffix sorting. Classes are dealt to tasks and each task sorts the suffixes of its remaining text with
   the difference cover modulo three: sampled triples are sorted and named, names are sorted by
   recursion, the remaining suffixes are merged in, and neighbours in suffix order are compared by
   prefix. A window repeats exactly if it shares its whole prefix with a neighbour.

A class with more than ``hot`` contexts is first split by the cores of ever smaller blocks, down to single
windows, so no task gets an unbounded class and nothing is left out.

Matches never cross texts. A null text is empty; texts shorter than ``length`` keep all bytes. Repeated
rows, also under one id, count as occurrences of their own. An empty table gives an empty result.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathtwin.llm.common import column_of, hand_back, map_slices
from pathtwin.plans.lineage import cut, settled

LENGTH = 400
#: Bytes of an anchor, as a share of the length.
ANCHOR_SHARE = 0.4
#: Contexts of a class that one task may get.
HOT = 20_000
#: Starts of a block.
BLOCK = 40
#: Contexts that a task sorts together.
BATCH = 4_000
#: Bytes hashed at once.
STEP = 1 << 19
#: Tasks that the rows of one anchor are dealt over.
SALTS = 16

_U = np.uint64
_rng = np.random.default_rng(20_011)
_TABLE = _rng.integers(0, 1 << 63, 256, dtype=np.uint64) * _U(2) + _rng.integers(0, 2, 256, dtype=np.uint64)
_ODD = _U(0x9E3779B97F4A7C15)
_POWERS: dict[str, np.ndarray] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    if not _POWERS or len(_POWERS["up"]) < n:
        size = max(n, STEP + 4096)
        _POWERS["up"] = np.cumprod(np.full(size, _ODD, np.uint64))
        _POWERS["down"] = np.cumprod(np.full(size, _U(pow(int(_ODD), -1, 1 << 64)), np.uint64))
    return _POWERS["up"], _POWERS["down"]


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> _U(32))) * _U(0xD6E8FEB86659FD93)
    return h ^ (h >> _U(29))


def _window_min(x: np.ndarray, w: int) -> np.ndarray:
    """Minimum of every ``w`` neighbours."""
    n = len(x) - w + 1
    grid = np.concatenate([x, np.full((-len(x)) % w, 2**64 - 1, np.uint64)]).reshape(-1, w)
    head = np.minimum.accumulate(grid, 1).ravel()
    tail = np.minimum.accumulate(grid[:, ::-1], 1)[:, ::-1].ravel()
    return np.minimum(tail[:n], head[w - 1 : w - 1 + n])


def find_anchors(text: bytes, length: int, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Places of the anchors of all windows, hashes of their ``k`` bytes and of their contexts."""
    n, reach = len(text), length - k
    places, keys, contexts, last = [], [], [], -1
    for first in range(0, n - length + 1, STEP):
        starts = min(STEP, n - length + 1 - first)
        lo, hi = max(0, first - reach), min(n, first + starts + reach + length)
        b = np.frombuffer(text, np.uint8, hi - lo, lo)
        up, down = _powers(len(b) + 1)
        total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(_TABLE[b] * up[: len(b)])])
        at = np.arange(first - lo, first - lo + starts + reach)
        h = _mix((total[at + k] - total[at]) * down[at])
        least = _window_min((h & ~_U(0xFFFFF)) | np.arange(len(h), dtype=np.uint64), reach + 1)
        pick = (least & _U(0xFFFFF)).astype(np.int64)
        pick = pick[np.concatenate([[True], pick[1:] != pick[:-1]])]
        a = at[pick]
        fresh = a + lo > last
        a, pick = a[fresh], pick[fresh]
        if not len(a):
            continue
        last = int(a[-1]) + lo
        s, e = np.maximum(a - reach, -lo), np.minimum(a + length, n - lo)
        s = np.maximum(s, 0)
        c = (total[e] - total[s]) * down[s] + (a - s).astype(np.uint64) * _U(0xA24BAED4963EE407) + (e - a).astype(np.uint64) * _U(0x9FB21C651E98DF25)
        places.append(a + lo)
        keys.append(h[pick])
        contexts.append(_mix(c))
    if not places:
        return np.zeros(0, np.int64), np.zeros(0, np.uint64), np.zeros(0, np.uint64)
    return np.concatenate(places), np.concatenate(keys), np.concatenate(contexts)


def suffix_order(s: np.ndarray) -> np.ndarray:
    """Suffix array of positive integers by the difference cover modulo three."""
    n = len(s)
    if n < 3:
        return np.array(sorted(range(n), key=lambda i: s[i:].tolist()), np.int64)
    t = np.concatenate([s.astype(np.int64), np.zeros(3, np.int64)])
    # one place past the end joins the sample when it is of the first kind, so that the halves stay apart
    one = np.arange(1, n + (n % 3 == 1), 3)
    two = np.arange(2, n, 3)
    sample = np.concatenate([one, two])
    top = int(t.max()) + 1
    if top < 1 << 20:
        triple = (t[sample] * top + t[sample + 1]) * top + t[np.minimum(sample + 2, n + 2)]
    else:
        _, pair = np.unique(t[sample] * top + t[sample + 1], return_inverse=True)
        triple = pair * top + t[np.minimum(sample + 2, n + 2)]
    order = np.argsort(triple, kind="stable")
    ranked = triple[order]
    name = np.empty(len(sample), np.int64)
    name[order] = np.cumsum(np.concatenate([[1], ranked[1:] != ranked[:-1]]))
    if name[order[-1]] < len(sample):
        order = suffix_order(name)
    rank = np.zeros(n + 4, np.int64)
    rank[sample[order]] = np.arange(1, len(sample) + 1)
    by_sample = sample[order]
    by_sample = by_sample[by_sample < n]
    zero = np.arange(0, n, 3)
    wide = n + 5
    key0 = t[zero] * wide + rank[zero + 1]
    zero = zero[np.argsort(key0, kind="stable")]
    key0 = t[zero] * wide + rank[zero + 1]
    ones, twos = by_sample[by_sample % 3 == 1], by_sample[by_sample % 3 == 2]
    before = np.searchsorted(t[ones] * wide + rank[ones + 1], key0)
    both = np.concatenate([zero, twos])
    _, pair = np.unique(t[both] * top + t[both + 1], return_inverse=True)
    long_key = pair * wide + rank[both + 2]
    before += np.searchsorted(long_key[len(zero) :], long_key[: len(zero)])
    out, taken = np.empty(n, np.int64), np.zeros(n, bool)
    place = before + np.arange(len(zero))
    out[place] = zero
    taken[place] = True
    out[~taken] = by_sample
    return out


def repeated_prefixes(symbols: np.ndarray, need: np.ndarray) -> np.ndarray:
    """Whether the first ``need`` symbols from each place also start at another; places of need zero are no starts."""
    order = suffix_order(symbols)
    x, y = order[:-1], order[1:]
    fit = (need[x] == need[y]) & (need[x] > 0)
    x, y = x[fit], y[fit]
    padded = np.concatenate([symbols, np.zeros(int(need.max(initial=0)) + 1, symbols.dtype)])
    hit, k = np.zeros(len(symbols), bool), 0
    while len(x):
        done = need[x] == k
        hit[x[done]] = True
        hit[y[done]] = True
        go = ~done & (padded[x + k] == padded[y + k])
        x, y, k = x[go], y[go], k + 1
    return hit


def blocks_of(left: bytes, right: bytes, reach: int, size: int, low: int = 0, high: int | None = None) -> Iterator[tuple[int, int, int, int, bytes, bytes, bytes]]:
    """Blocks of starts ``lo..hi`` bytes before the anchor.

    Yields ``lo, hi``, the starts among them whose windows lie in the text, the core outside the anchor, and
    what the windows cover beside the core, to the left and right; both are short where the text ends.
    """
    high = reach if high is None else high
    first, last, n = max(low, reach - len(right)), min(high, len(left)), len(left)
    for lo in range(low - low % size, last + 1, size):
        hi = min(lo + size - 1, high)
        if hi >= first:
            core = left[n - lo :] + b"|" + right[: reach - hi] if lo else b"|" + right[: reach - hi]
            yield lo, hi, max(lo, first), min(hi, last), core, left[max(0, n - hi) : n - lo], right[reach - hi : reach - lo]


def solve(classes: list, lefts: list, rights: list, reach: int, size: int = BLOCK) -> list[tuple[int, int] | None]:
    """For each context the least and greatest start, counted back from the anchor, of a repeated window."""
    groups: dict = {}
    for i, (c, left, right) in enumerate(zip(classes, lefts, rights, strict=True)):
        for lo, hi, near, far, core, before, after in blocks_of(left, right, reach, size):
            groups.setdefault((c, lo, hi, core), {}).setdefault((before, after), []).append((i, near, far))
    found: list = [None] * len(classes)

    def note(i: int, near: int, far: int) -> None:
        was = found[i]
        found[i] = (near, far) if was is None else (min(was[0], near), max(was[1], far))

    parts, owners, symbol = [], [], 256
    for (_, lo, hi, _), arounds in groups.items():
        for rows in arounds.values():
            if len(rows) > 1:
                for i, near, far in rows:
                    note(i, near, far)
        if len(arounds) > 1:
            symbol += 1
            core, n = symbol, hi - lo
            for (before, after), rows in arounds.items():
                i, near, far = rows[0]
                symbol += 1
                parts += [before, core, after, symbol]
                owners.append((i if len(rows) == 1 else -1, hi, n + 1, len(before) + len(after) + 2, hi - len(before) - lo, near, far))
    if not owners:
        return found
    hi, need_of, sizes, missing, near, far = np.array([o[1:] for o in owners], np.int64).T
    symbols = np.concatenate([np.array([p], np.int64) if isinstance(p, int) else np.frombuffer(p, np.uint8).astype(np.int64) + 1 for p in parts])
    which = np.repeat(np.arange(len(owners)), sizes)
    offset = np.arange(len(symbols)) - (np.cumsum(sizes) - sizes)[which]
    start = hi[which] - offset - missing[which]
    need = np.where((start >= near[which]) & (start <= far[which]), need_of[which], 0)
    hit = np.flatnonzero(repeated_prefixes(symbols, need))
    for k, d in zip(which[hit].tolist(), start[hit].tolist(), strict=True):
        if owners[k][0] >= 0:
            note(owners[k][0], d, d)
    return found


_CONTEXT = "k long, th long, at int, cls long, lft binary, rgt binary"
_SPAN = "k long, th long, s int, e int"


def _texts(docs: DataFrame, *more: str) -> DataFrame:
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    k = F.coalesce(F.col("doc_id").cast("long"), F.lit(-(2**63)))
    return docs.select(*more, k.alias("k"), F.xxhash64(text).alias("th"), text.cast("binary").alias("bytes"))


def _solver(reach: int, length: int, key: str):
    """Sorts whole classes, ``key`` naming the class; rows may be limited to starts ``lo..hi``."""

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for x in _whole_classes(batches, key):
            left, right = x["lft"].tolist(), x["rgt"].tolist()
            if "lo" in x:
                left = [t[max(0, len(t) - hi) :] for t, hi in zip(left, x["hi"], strict=True)]
                right = [t[: reach - lo] for t, lo in zip(right, x["lo"], strict=True)]
            found = solve(x[key].tolist(), left, right, reach)
            hit = [i for i, f in enumerate(found) if f is not None]
            x, near, far = x.iloc[hit], np.array([found[i][0] for i in hit], np.int64), np.array([found[i][1] for i in hit], np.int64)
            yield pd.DataFrame({"k": x["k"], "th": x["th"], "s": x["at"] - far, "e": x["at"] - near + length})
        hand_back()

    return run


def _hot_spans(hot: DataFrame, reach: int, length: int, limit: int) -> list[DataFrame]:
    """Spans in classes of too many contexts: split by the cores of ever smaller blocks, to single windows."""
    spans, rows, size = [], hot.select("*", F.lit(0).alias("lo"), F.lit(reach).alias("hi"), F.col("lft").alias("l"), F.col("rgt").alias("r")), reach + 1
    schema = _CONTEXT + ", lo int, hi int, near int, far int, part binary, core long"
    while size > 1:
        size = max(1, size // 6)

        def split(batches: Iterator[pd.DataFrame], size: int = size) -> Iterator[pd.DataFrame]:
            from xxhash import xxh64_intdigest

            for b in batches:
                out = []
                for x in b.itertuples(index=False):
                    for lo, hi, near, far, core, before, after in blocks_of(x.lft, x.rgt, reach, size, x.lo, x.hi):
                        key = xxh64_intdigest(core + b"%d|%d|%d" % (x.cls, lo, hi)) - (1 << 63)
                        out.append((x.k, x.th, x.at, x.cls, x.lft, x.rgt, lo, hi, near, far, b"%d|" % len(before) + before + after, key))
                yield pd.DataFrame(out, columns=[c.split()[0] for c in schema.split(", ")])

        rows = cut(rows.select("k", "th", "at", "cls", "lft", "rgt", "lo", "hi").mapInPandas(split, schema))
        twins = rows.groupBy("core", "part").agg(F.count("*").alias("n"), F.min(F.struct("k", "th", "at")).alias("rep"))
        many = twins.groupBy("core").agg(F.count("*").alias("m")).filter("m > 1")
        span = [F.col("k"), F.col("th"), (F.col("at") - F.col("far")).alias("s"), (F.col("at") - F.col("near") + length).alias("e")]
        spans.append(rows.join(twins.filter("n > 1").select("core", "part"), ["core", "part"], "left_semi").select(*span))
        if size == 1:
            break
        left = twins.join(many, "core").select("core", "part", "rep.k", "rep.th", "rep.at", "m")
        rows = cut(rows.join(left, ["core", "part", "k", "th", "at"]))
        small = rows.filter(F.col("m") <= limit)

        spans.append(small.repartition("core").sortWithinPartitions("core").mapInPandas(_solver(reach, length, "core"), _SPAN))
        rows = rows.filter(F.col("m") > limit).drop("m", "core", "part", "near", "far")
        if rows.isEmpty():
            break
    return spans


def salted(keys: DataFrame) -> DataFrame:
    """One row for each salt: the rows of a common key are dealt over as many tasks."""
    return keys.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))


def _whole_classes(batches: Iterator[pd.DataFrame], key: str) -> Iterator[pd.DataFrame]:
    """Sorted batches, cut again where the key changes, of at least ``BATCH`` rows but for the last."""
    held: list[pd.DataFrame] = []
    for b in batches:
        held.append(b)
        if sum(map(len, held)) < BATCH:
            continue
        x = pd.concat(held, ignore_index=True)
        last = int(np.searchsorted(x[key].to_numpy(), x[key].iloc[-1]))
        if last:
            yield x.iloc[:last]
        held = [x.iloc[last:]]
    if held and sum(map(len, held)):
        yield pd.concat(held, ignore_index=True)


def repeated_spans(docs: DataFrame, length: int = LENGTH, hot: int = HOT) -> DataFrame:
    """Rows ``k, th, spans``: by id and hash of a text, its overlapping repeated byte ranges; written, and all that led to them deleted."""
    return settled(lambda: _spans(docs, length, hot))


def _spans(docs: DataFrame, length: int, hot: int) -> DataFrame:
    k = max(1, int(length * ANCHOR_SHARE))
    reach = length - k

    def anchors(parts: Iterator[dict]) -> Iterator[dict]:
        for p in parts:
            met = [find_anchors(text, length, k) for text in p["bytes"]]
            sizes = [len(at) for at, _, _ in met]
            yield {
                "k": np.repeat(np.array(p["k"], np.int64), sizes), "th": np.repeat(np.array(p["th"], np.int64), sizes), "at": np.concatenate([m[0] for m in met]).astype(np.int32),
                "kh": np.concatenate([m[1] for m in met]).view(np.int64), "ch": np.concatenate([m[2] for m in met]).view(np.int64),
            }

    texts = _texts(docs).filter(F.octet_length("bytes") >= length)
    found = cut(map_slices(texts, anchors, "k long, th long, at int, kh long, ch long").withColumn("salt", F.pmod(F.xxhash64("k", "th", "at"), F.lit(SALTS)).cast("int")))
    classes = found.groupBy("kh").agg(F.count("*").alias("n"), (F.min("ch") < F.max("ch")).alias("mixed")).filter("n > 1")
    again = cut(found.join(salted(classes), ["kh", "salt"]))
    contexts = again.groupBy("kh", "ch").agg(F.count("*").alias("copies"), F.min(F.struct("k", "th", "at")).alias("rep"), F.first("mixed").alias("mixed"), F.first("n").alias("n"))
    contexts = cut(contexts)
    whole = again.join(salted(contexts.filter("copies > 1").select("kh", "ch")), ["kh", "ch", "salt"], "left_semi")
    spans = [whole.select("k", "th", F.greatest(F.lit(0), F.col("at") - reach).alias("s"), (F.col("at") + length).alias("e"))]
    wanted = contexts.filter("mixed").groupBy("rep.k", "rep.th").agg(F.collect_list(F.struct("rep.at", F.col("kh").alias("cls"), "n")).alias("wanted"))

    def around(parts: Iterator[dict]) -> Iterator[dict]:
        names = ("k", "th", "at", "cls", "lft", "rgt", "n")
        for p in parts:
            out = []
            for key, th, text, want in zip(p["k"], p["th"], p["bytes"], p["wanted"], strict=True):
                for w in want:
                    a = w["at"]
                    out.append((key, th, a, w["cls"], text[max(0, a - reach) : a], text[a + k : a + length], w["n"]))
                    if len(out) >= BATCH:
                        yield dict(zip(names, zip(*out, strict=True), strict=True))
                        out = []
            if out:
                yield dict(zip(names, zip(*out, strict=True), strict=True))

    cuts = map_slices(texts.join(wanted, ["k", "th"]), around, _CONTEXT + ", n long")
    heavy = contexts.filter(F.col("mixed") & (F.col("n") > hot))
    if heavy.isEmpty():
        cool = cuts
    else:
        cuts = cut(cuts)
        cool = cuts.filter(F.col("n") <= hot)
        spans += _hot_spans(cuts.filter(F.col("n") > hot).drop("n"), reach, length, hot)
    sorted_classes = cool.drop("n").repartition("cls").sortWithinPartitions("cls")
    spans.append(sorted_classes.mapInPandas(_solver(reach, length, "cls"), _SPAN))
    out = spans[0]
    for s in spans[1:]:
        out = out.unionByName(s)
    return out.groupBy("k", "th").agg(F.collect_list(F.struct("s", "e")).alias("spans"))


def merged(spans, size: int) -> list[tuple[int, int]]:
    """Disjoint, non-adjacent ranges that cover the same bytes."""
    if spans is None or not len(spans):
        return []
    x = np.array(sorted((max(0, p["s"]), min(size, p["e"])) for p in spans), np.int64)
    ends = np.maximum.accumulate(x[:, 1])
    new = np.concatenate([[True], x[1:, 0] > ends[:-1]])
    first = np.flatnonzero(new)
    return list(zip(x[first, 0].tolist(), ends[np.concatenate([first[1:] - 1, [len(x) - 1]])].tolist(), strict=True))


def remaining(text: bytes, spans: list[tuple[int, int]]) -> bytes:
    out, at = [], 0
    for s, e in spans:
        out.append(text[at:s])
        at = e
    return b"".join([*out, text[at:]])


def dedup_digests(docs: DataFrame, length: int = LENGTH, hot: int = HOT) -> DataFrame:
    """Rows ``doc_id, n_bytes, n_removed, n_spans, kept_sha256``."""

    def digest(parts: Iterator[dict]) -> Iterator[dict]:
        for p in parts:
            cuts = [merged(spans, len(text)) for text, spans in zip(p["bytes"], p["spans"], strict=True)]
            kept = [remaining(text, c) for text, c in zip(p["bytes"], cuts, strict=True)]
            yield {
                "doc_id": [None if key == -(2**63) else key for key in p["k"]], "n_bytes": [len(t) for t in p["bytes"]],
                "n_removed": [len(t) - len(x) for t, x in zip(p["bytes"], kept, strict=True)], "n_spans": [len(c) for c in cuts],
                "kept_sha256": [hashlib.sha256(x).hexdigest() for x in kept],
            }

    joined = _texts(docs).join(repeated_spans(docs, length, hot), ["k", "th"], "left")
    return map_slices(joined, digest, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string")


def without_repeats(docs: DataFrame, length: int = LENGTH, hot: int = HOT) -> DataFrame:
    """``docs`` with the repeated bytes of ``text`` removed and ``n_chars`` updated; cut characters go whole.

    A null text stays null and an empty one empty; a text that is all repeats becomes empty and its row stays.
    """
    names = docs.columns
    joined = docs.withColumns({"__k": F.coalesce(F.col("doc_id").cast("long"), F.lit(-(2**63))), "__th": F.xxhash64(F.coalesce(F.col("text").cast("string"), F.lit("")))})
    spans = repeated_spans(docs, length, hot).select(F.col("k").alias("__k"), F.col("th").alias("__th"), F.col("spans").alias("__spans"))
    joined = joined.join(spans, ["__k", "__th"], "left").drop("__k", "__th").withColumn("text", F.col("text").cast("string"))

    def stripped(pairs: list) -> list:
        out = []
        for pair in pairs:
            raw = pair["text"].encode() if pair and pair["text"] else b""
            out.append(remaining(raw, merged(pair["spans"], len(raw))).decode(errors="ignore") if raw else None)
        return out

    def run(arrays: Iterator[pa.Array]) -> Iterator[pa.Array]:
        yield from column_of(stripped, pa.string())(arrays)

    strip = F.arrow_udf("string")(run)
    cut_text = F.when(F.col("__spans").isNull() | F.col("text").isNull(), F.col("text")).otherwise(F.coalesce("__cut", F.lit("")))
    hit = F.when(F.col("__spans").isNotNull(), F.struct("text", F.col("__spans").alias("spans")))
    out = joined.withColumn("__cut", strip(hit)).withColumn("text", cut_text).select(*names)
    if "n_chars" in names:
        kind = docs.schema["n_chars"].dataType
        out = out.withColumn("n_chars", F.length("text").cast(kind))
    return out
