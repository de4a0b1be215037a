"""Toxicity after noisy-channel deobfuscation.

A character trigram model is counted over all documents. Spans that look disguised (letters mixed with
look-alike symbols, letters repeated three times or more, single letters set apart by separators) become
lattices: a symbol may be the letter it resembles or a break, a run may be one or two letters, a
separator may be nothing or a break. A Viterbi search under the trigram model decodes each lattice; the
restored words join the words of the text, and a lexicon model scores them.

The lexicon holds words and word beginnings that mark the positive label in a bounded sample of labelled
rows; near copies there share one vote. A logistic curve over a text's evidence gives the score.

Null and empty texts have no evidence and get the score of such texts. Without labels of both classes the
score is constant. Repeated rows and ties change nothing; an empty table gives an empty result.
"""

from __future__ import annotations

import math
import re
from collections import defaultdict
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathtwin.llm.common import column_of, fold, map_slices
from pathtwin.llm.rule_ensemble import labelled_sample

#: Labelled rows that the lexicon is learned on, the least by hash of the id.
SAMPLE = 9_000
#: Entries of the lexicon, the strongest first.
LEXICON = 4_000
#: Positive rows, near copies aside, that a lexicon entry needs.
VOTES = 4
#: Decoded spans that a worker remembers.
HELD = 50_000
#: Lengths of word beginnings that may enter the lexicon.
BEGINNINGS = (4, 5, 6)

# Letters that digits and signs resemble.
LOOKS_LIKE = {"0": "o", "1": "il", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "il", "+": "t", "(": "c", "*": "aeiou"}
SEPARATORS = " .-_*~"

BASE = 27
_CLASS = np.zeros(256, np.int16)
for _i in range(26):
    _CLASS[ord("a") + _i] = _CLASS[ord("A") + _i] = _i + 1
_LETTER = _CLASS > 0
_LETTER[0x80:] = True
_SIGN = np.zeros(256, bool)
for _c in LOOKS_LIKE:
    _SIGN[ord(_c)] = True
_GAP = np.zeros(256, bool)
for _c in SEPARATORS:
    _GAP[ord(_c)] = True
_WORDS = re.compile(r"[^\W\d_]+").findall


class CharModel:
    """Interpolated trigram log-probabilities over a..z and the break."""

    def __init__(self, counts: np.ndarray):
        c = counts.reshape(BASE, BASE, BASE).astype(np.float64)
        uni = (c.sum((0, 1)) + 1) / (c.sum() + BASE)
        two = c.sum(0)
        bi = (two + 5 * uni) / (two.sum(1, keepdims=True) + 5)
        self.log = np.log((c + 5 * bi[None]) / (c.sum(2, keepdims=True) + 5)).tolist()


def char_counts(texts: Iterator[str]) -> np.ndarray:
    total = np.zeros(BASE**3, np.int64)
    for text in texts:
        b = np.frombuffer(text.encode("utf-8", "replace"), np.uint8)
        for at in range(0, len(b), 1 << 20):
            x = np.concatenate([[0, 0], _CLASS[b[at : at + (1 << 20)]], [0]]).astype(np.int32)
            x = x[np.concatenate([[True], (x[1:] > 0) | (x[:-1] > 0)])]
            total += np.bincount((x[:-2] * BASE + x[1:-1]) * BASE + x[2:], minlength=BASE**3)
    return total


def corpus_char_counts(docs: DataFrame) -> np.ndarray:
    """Trigram counts over all texts: each task adds up its own table, tables are summed by shuffle."""

    def run(parts: Iterator[dict]) -> Iterator[dict]:
        total = sum((char_counts(t for t in p["text"] if t) for p in parts), np.zeros(BASE**3, np.int64))
        at = np.flatnonzero(total)
        yield {"gram": at, "n": total[at]}

    counted = map_slices(docs.select(F.col("text").cast("string").alias("text")), run, "gram int, n long")
    summed = counted.groupBy("gram").agg(F.sum("n").alias("n")).toPandas()
    out = np.zeros(BASE**3, np.int64)
    out[summed["gram"].to_numpy(np.int64)] = summed["n"].to_numpy(np.int64)
    return out


def disguised(text: str) -> list[tuple[int, int]]:
    """Byte spans of the UTF-8 text that look disguised, in order, disjoint."""
    b = np.frombuffer(text.encode("utf-8", "replace"), np.uint8)
    if len(b) < 3:
        return []
    letter, sign, gap = _LETTER[b], _SIGN[b], _GAP[b]
    hit = np.zeros(len(b), bool)
    near = letter | sign
    hit[1:-1] = sign[1:-1] & near[:-2] & near[2:] & (letter[:-2] | letter[2:])
    hit[:-2] |= sign[:-2] & letter[1:-1] & letter[2:] & np.concatenate([[True], ~(near | _GAP[b])[: len(b) - 3] | (b[: len(b) - 3] == 32)])
    low = np.where(letter & (b < 0x60), b + 32, b)
    hit[:-2] |= letter[:-2] & (low[:-2] == low[1:-1]) & (low[1:-1] == low[2:]) & (b[:-2] < 0x80)
    word = np.zeros(len(b), bool)
    solid = ~np.isin(b, np.frombuffer(b" \t\n\r\v\f", np.uint8))
    alone = np.zeros(len(b), bool)
    one = near & (b < 0x80)
    alone[1:-1] = one[1:-1] & ~near[:-2] & ~near[2:]
    alone[0], alone[-1] = one[0] and not near[1], one[-1] and not near[-2]
    if len(b) >= 7:
        k = len(b) - 6
        run = alone[:k] & gap[1 : k + 1] & alone[2 : k + 2] & gap[3 : k + 3] & alone[4 : k + 4] & gap[5 : k + 5] & alone[6 : k + 6]
        for i in np.flatnonzero(run):
            word[i : i + 7] = True
    starts = np.flatnonzero(hit)
    if len(starts):
        edge = np.flatnonzero(np.diff(np.concatenate([[False], solid, [False]]).astype(np.int8)))
        which = np.unique(np.searchsorted(edge[::2], starts, "right") - 1)
        for k in which:
            word[edge[2 * k] : edge[2 * k + 1]] = True
    cuts = np.flatnonzero(np.diff(np.concatenate([[False], word, [False]]).astype(np.int8))).tolist()
    return list(zip(cuts[::2], cuts[1::2], strict=True))


def lattice(span: str) -> Iterator[tuple[int, int, tuple[int, ...], float]]:
    """Edges ``i, j, out, cost`` of a span: its characters ``i..j`` may stand for ``out``, letters 1..26 or the break 0."""
    s, i = span.lower(), 0
    while i < len(s):
        ch, j = s[i], i + 1
        while j < len(s) and s[j] == ch:
            j += 1
        if "a" <= ch <= "z":
            x = ord(ch) - 96
            if j - i == 1:
                yield i, j, (x,), 0.0
            else:
                yield i, j, (x,), 2.0 if j - i == 2 else 0.3
                yield i, j, (x, x), 0.0 if j - i == 2 else 0.3
        else:
            likes = LOOKS_LIKE.get(ch, "")
            for y in likes:
                yield i, j, (ord(y) - 96,), 0.5 + 0.4 * (len(likes) > 2)
                if j - i > 1:
                    yield i, j, (ord(y) - 96,) * 2, 1.0
            if ch in SEPARATORS:
                yield i, j, (), 0.2
            yield i, j, (0,), 1.5 if ch in SEPARATORS else 9.0
        i = j


def decode(span: str, model: CharModel) -> str:
    """Likeliest plain text of a disguised span: words of a..z parted by blanks; other letters stay breaks.

    A Viterbi search over the lattice whose states are the last two letters; breaks in a row are one.
    """
    log, n = model.log, len(span.lower())
    best: dict[int, dict] = defaultdict(dict)
    best[0][0, 0] = (0.0, None)
    for i, j, out, cost in lattice(span):
        ahead = best[j]
        for state, (score, _) in best[i].items():
            a, c, total = *state, score - cost
            for x in out:
                if x == 0 and c == 0:
                    continue
                total += log[a][c][x]
                a, c = c, x
            if (a, c) not in ahead or total > ahead[a, c][0]:
                ahead[a, c] = (total, (i, state, out))
    ends = {state: score + (log[state[0]][state[1]][0] if state[1] else 0.0) for state, (score, _) in best[n].items()}
    state = max(ends, key=ends.__getitem__)
    at, made = n, []
    while (back := best[at][state][1]) is not None:
        at, state, out = back
        made.append(out)
    return "".join(" " if x == 0 else chr(96 + x) for out in reversed(made) for x in out).strip()


class Restorer:
    """Words of texts with disguised spans decoded; decoded spans are remembered."""

    def __init__(self, counts: np.ndarray):
        self.model, self.known = CharModel(counts), {}

    def decoded(self, span: str) -> str:
        if (out := self.known.get(span)) is None:
            if len(self.known) > HELD:
                self.known.clear()
            out = self.known[span] = decode(span, self.model)
        return out

    def restore(self, text: str) -> str:
        b, parts, at = text.encode("utf-8", "replace"), [], 0
        for i, j in disguised(text):
            parts += [b[at:i].decode("utf-8", "replace"), self.decoded(b[i:j].decode("utf-8", "replace"))]
            at = j
        return "".join([*parts, b[at:].decode("utf-8", "replace")])

    def words(self, text: str) -> set[str]:
        found = set(_WORDS(text.lower()))
        if spans := disguised(text):
            b = text.encode("utf-8", "replace")
            for i, j in spans:
                found.update(self.decoded(b[i:j].decode("utf-8", "replace")).split())
        return found


def evidence(words: set[str], lexicon: dict[str, float]) -> tuple[float, float]:
    """Strongest weight and the damped sum of the others."""
    hits = []
    for w in words:
        best = lexicon.get(w, 0.0)
        for n in BEGINNINGS:
            if len(w) > n:
                best = max(best, lexicon.get(w[:n] + "-", 0.0))
        if best:
            hits.append(best)
    if not hits:
        return 0.0, 0.0
    return max(hits), math.log1p(sum(hits) - max(hits))


def _terms(words: set[str]) -> Iterator[tuple[str, ...]]:
    """Each word with its beginnings."""
    for w in words:
        yield (w, *(w[:n] + "-" for n in BEGINNINGS if len(w) > n))


def learn(rows: Iterable[tuple[set[str], int]]) -> tuple[dict[str, float], np.ndarray]:
    """Lexicon and the three logistic weights. Rows of the positive label come first.

    Only words of positive rows can enter the lexicon, so of the others those alone are kept, as numbers.
    """
    number: dict[str, int] = {}
    docs: list[tuple[np.ndarray, np.ndarray, int]] = []
    families: dict[tuple[int, int], np.ndarray] = {}
    known = None
    for words, label in rows:
        y = int(bool(label))
        if not y and known is None:
            votes = np.zeros(len(number), np.int64)
            for (_, side), ids in families.items():
                votes[ids] += side
            known = {w: i for w, i in number.items() if votes[i] >= VOTES}
            number = known
        if y and known is not None:
            raise ValueError("rows of the positive label must come first")
        groups = ([number.setdefault(t, len(number)) for t in terms] if y else [number[t] for t in terms if t in number] for terms in _terms(words))
        groups = [g for g in groups if g]
        ids = np.array([i for g in groups for i in g], np.int32)
        first = np.cumsum([0, *map(len, groups)])[:-1].astype(np.int32)
        family = (min(map(hash_word, words), default=0), y)
        families[family] = np.unique(np.concatenate([families[family], ids])) if family in families else np.unique(ids)
        docs.append((ids, first, y))
    totals = np.bincount([y for _, y in families], minlength=2)
    if not totals.all():
        share = (totals[1] + 0.5) / (totals.sum() + 1)
        return {}, np.array([math.log(share / (1 - share)), 0.0, 0.0])
    size = 1 + max(number.values(), default=0)
    size = max(size, 1 + max((int(ids.max()) for ids, _, _ in docs if len(ids)), default=0))
    count = np.zeros((2, size), np.int64)
    for (_, y), ids in families.items():
        count[y][ids] += 1
    ratio = np.log((count[1] + 0.5) / (totals[1] + 1)) - np.log((count[0] + 0.5) / (totals[0] + 1))
    chosen = (count[1] >= VOTES) & (count[1] >= 0.004 * totals[1]) & (ratio > 2.5)
    strongest = sorted(((w, float(ratio[i])) for w, i in number.items() if chosen[i]), key=lambda x: (-x[1], x[0]))[:LEXICON]
    lexicon, weight = dict(strongest), np.zeros(size)
    for w, value in strongest:
        weight[number[w]] = value
    x = np.ones((len(docs), 3))
    for k, (ids, first, _) in enumerate(docs):
        hits = np.maximum.reduceat(weight[ids], first) if len(ids) else np.zeros(1)
        x[k, 1:] = hits.max(), math.log1p(hits.sum() - hits.max())
    y = np.array([float(v) for _, _, v in docs])
    w = np.zeros(3)
    for _ in range(50):
        p = 1 / (1 + np.exp(-x @ w))
        h = (x * (p * (1 - p))[:, None]).T @ x + np.diag([1e-3, 0.05, 0.05])
        w -= np.linalg.solve(h, x.T @ (p - y) + np.array([1e-3, 0.05, 0.05]) * w)
    return lexicon, w


def hash_word(w: str) -> int:
    from xxhash import xxh64_intdigest

    return xxh64_intdigest(w)


def toxicity_scores(docs: DataFrame, labels: DataFrame, folds: int = 5, held_out: int = 0, rows: int = SAMPLE, keep_as: str | None = None) -> DataFrame:
    """Rows ``doc_id, held_out, score, predicted``; with ``keep_as`` all columns of ``docs`` and the score under that name.

    Two passes over the texts and no shuffle of them but for the sampled rows, which go to one task.
    """
    d = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    counts = corpus_char_counts(d)

    def fit(parts: Iterator[dict]) -> Iterator[dict]:
        restorer = Restorer(counts)
        lexicon, w = learn((restorer.words(t or ""), y) for p in parts for t, y in zip(p["text"], p["y"], strict=True))
        yield {"word": [*lexicon, *("", " ", "  ")], "w": [*lexicon.values(), *w.tolist()]}

    sample = d.join(labelled_sample(labels, "toxic", folds, held_out, rows), "doc_id").withColumn("th", F.xxhash64("text"))
    sample = sample.dropDuplicates(["doc_id"]).coalesce(1).sortWithinPartitions(F.desc("y"), "th", "doc_id")
    learned = {r["word"]: r["w"] for r in map_slices(sample.select("text", "y"), fit, "word string, w double").collect()}
    base, strong, more = (learned.pop(k, 0.0) for k in ("", " ", "  "))

    def run(arrays: Iterator[pa.Array]) -> Iterator[pa.Array]:
        restorer = Restorer(counts)

        def scores(texts: list) -> list:
            found = (evidence(restorer.words(t or ""), learned) for t in texts)
            return [1 / (1 + math.exp(-min(max(base + strong * x + more * y, -500), 500))) for x, y in found]

        yield from column_of(scores, pa.float64())(arrays)

    score = F.arrow_udf("double")(run)
    if keep_as:
        return docs.withColumn(keep_as, score(F.col("text").cast("string")))
    held = F.coalesce(fold("doc_id", folds) == held_out, F.lit(False))
    scored = d.withColumn("score", score("text"))
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
