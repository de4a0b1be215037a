"""Distances of two symbol sequences. Order-based ones use integers as bit rows."""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Sequence


def exact(a: Sequence, b: Sequence) -> int:
    return int(list(a) != list(b))


def hamming(a: Sequence, b: Sequence) -> int:
    """Mismatches over the common length, and the difference of lengths."""
    return hamming_free(a, b) + abs(len(a) - len(b))


def hamming_free(a: Sequence, b: Sequence) -> int:
    """Mismatches over the common length alone."""
    return sum(x != y for x, y in zip(a, b, strict=False))


def _masks(a: Sequence) -> dict:
    masks: dict = {}
    for i, x in enumerate(a):
        masks[x] = masks.get(x, 0) | 1 << i
    return masks


def lcs_length(a: Sequence, b: Sequence) -> int:
    """Longest common subsequence: one addition and a few bit operations a symbol of ``b``."""
    if not a or not b:
        return 0
    masks, full = _masks(a), (1 << len(a)) - 1
    row = full
    for y in b:
        hit = row & masks.get(y, 0)
        row = ((row + hit) | (row - hit)) & full
    return len(a) - row.bit_count()


def lcs(a: Sequence, b: Sequence) -> int:
    return max(len(a), len(b)) - lcs_length(a, b)


def levenshtein(a: Sequence, b: Sequence) -> int:
    """Insertions, deletions and substitutions, by vertical differences kept as bits."""
    if not a:
        return len(b)
    masks, top, full = _masks(a), 1 << (len(a) - 1), (1 << len(a)) - 1
    up, down, score = full, 0, len(a)
    for y in b:
        eq = masks.get(y, 0)
        diag = (((eq & up) + up) ^ up) | eq | down
        plus, minus = (down | ~(diag | up)) & full, up & diag
        score += bool(plus & top) - bool(minus & top)
        plus, minus = ((plus << 1) | 1) & full, (minus << 1) & full
        up, down = (minus | ~(diag | plus)) & full, plus & diag
    return score


def damerau(a: Sequence, b: Sequence) -> int:
    """Levenshtein with swaps of neighbours, unrestricted: a few rows, whatever the lengths.

    ``before`` holds, for each column, the cell two steps back of the last row where its symbols were equal.
    """
    m, far = len(b), len(a) + len(b) + 1
    # column j is at j + 1; one column before the first is out of reach
    before, up, row = [far] * (m + 2), [far] * (m + 2), [far, *range(m + 1)]
    seen: dict = {}
    for i, x in enumerate(a, 1):
        row, up = up, row
        last, old, across = -1, row[1], far
        row[1] = i
        for j, y in enumerate(b, 1):
            best = min(up[j] + (x != y), row[j] + 1, up[j + 1] + 1)
            if x == y:
                last, before[j + 1], across = j, up[j - 1], old
            else:
                k = seen.get(y, -1)
                if j - last == 1:
                    best = min(best, before[j + 1] + i - k)
                elif i - k == 1:
                    best = min(best, across + j - last)
            old, row[j + 1] = row[j + 1], best
        seen[x] = i
    return row[m + 1]


def alignment_score(a: Sequence, b: Sequence, match: int = 1, mismatch: int = -1, gap: int = 0) -> int:
    row = [gap * j for j in range(len(b) + 1)]
    for i, x in enumerate(a, 1):
        new = [gap * i]
        for j, y in enumerate(b, 1):
            new.append(max(row[j - 1] + (match if x == y else mismatch), row[j] + gap, new[-1] + gap))
        row = new
    return row[-1]


def alignment(a: Sequence, b: Sequence, match: int = 1, mismatch: int = -1, gap: int = 0) -> int:
    """Longer length less the score of the best global alignment."""
    if (match, mismatch, gap) == (1, -1, 0):
        return lcs(a, b)  # two free gaps are never worse than a mismatch, so the score is the common length
    return max(len(a), len(b)) - alignment_score(a, b, match, mismatch, gap)


def jaccard(a: Sequence, b: Sequence) -> float:
    x, y = set(a), set(b)
    return 1 - len(x & y) / len(x | y) if x | y else 0.0


def cosine(a: Sequence, b: Sequence) -> float:
    x, y = Counter(a), Counter(b)
    if not x or not y:
        return 0.0 if not x and not y else 1.0
    dot = sum(n * y[k] for k, n in x.items())
    return 1 - dot / math.sqrt(sum(n * n for n in x.values()) * sum(n * n for n in y.values()))


def ngram(a: Sequence, b: Sequence, n: int = 2) -> float:
    """Share of n-gram occurrences that the other side lacks."""
    x, y = (Counter(tuple(s[i : i + n]) for i in range(len(s) - n + 1)) for s in (a, b))
    total = sum(x.values()) + sum(y.values())
    return 1 - 2 * sum((x & y).values()) / total if total else float(list(a) != list(b))


def jaro_winkler(a: Sequence, b: Sequence) -> float:
    """1 - similarity, with a bonus of a tenth for each of up to four leading equal symbols where it exceeds 0.7."""
    if not a or not b:
        return 0.0 if not a and not b else 1.0
    reach = max(0, max(len(a), len(b)) // 2 - 1)
    used, left = [False] * len(b), []
    for i, x in enumerate(a):
        for j in range(max(0, i - reach), min(len(b), i + reach + 1)):
            if not used[j] and b[j] == x:
                used[j] = True
                left.append(x)
                break
    if not left:
        return 1.0
    right = [y for y, hit in zip(b, used, strict=True) if hit]
    swaps = sum(x != y for x, y in zip(left, right, strict=True)) // 2
    m = len(left)
    jaro = (m / len(a) + m / len(b) + (m - swaps) / m) / 3
    if jaro <= 0.7:
        return 1 - jaro
    lead = 0
    for x, y in zip(a[:4], b[:4], strict=False):
        if x != y:
            break
        lead += 1
    return 1 - (jaro + 0.1 * lead * (1 - jaro))


#: name -> (kernel, whether it is a count to be divided by the longer length, lower bound by common symbols holds, is a metric)
REGISTRY = {
    "exact": (exact, False, False, True), "hamming": (hamming, True, True, True), "hamming_free": (hamming_free, True, False, False), "levenshtein": (levenshtein, True, True, True),
    "damerau": (damerau, True, True, True), "alignment": (alignment, True, True, True), "lcs": (lcs, True, True, True), "lcs_mod": (lcs, True, True, False),
    "ngram": (ngram, False, False, False), "jaccard": (jaccard, False, False, True), "cosine": (cosine, False, False, False), "jaro_winkler": (jaro_winkler, False, False, False),
}


def path_distance(a: Sequence, b: Sequence, metric: str, tau: float = 0.3, normalise: str = "longer", sub_slack: float = 0.1, sub_min_len: int = 10, max_len_diff: int | None = None) -> float:
    """Distance of two paths; the modified LCS takes a path embedded in a longer one at the shorter's length.

    Paths whose lengths differ by more than ``max_len_diff`` are as far apart as can be, but for embedded ones.
    """
    kernel, counts, _, _ = REGISTRY[metric]
    longer, shorter = max(len(a), len(b)), min(len(a), len(b))
    capped = max_len_diff is not None and longer - shorter > max_len_diff
    if capped and metric != "lcs_mod":
        return float(longer) if counts and normalise == "none" else 1.0
    d = kernel(a, b)
    if not counts:
        return float(d)
    plain = float(d) if normalise == "none" else (d / longer if longer else 0.0)
    if capped:
        plain = float(longer) if normalise == "none" else 1.0
    if metric == "lcs_mod" and plain >= tau and shorter >= sub_min_len:
        common = longer - d
        if 100 * common >= round(100 * (1 - sub_slack)) * shorter:
            return float(shorter - common) if normalise == "none" else (shorter - common) / shorter
    return plain


def set_distance(a: list, b: list, metric: str, tau: float = 0.3, tie: str = "min", max_len_diff: int | None = None, cutoff: float | None = None, known: dict | None = None, **kw) -> float:
    """Mean over the smaller set of each path's distance to its nearest path; ``a`` and ``b`` hold ``(path, times)``.

    With ``cutoff`` a mean that is sure to reach it may be returned as any value from it on. ``known`` carries
    path distances from call to call. Paths whose lengths alone put them behind the nearest so far are skipped.
    """
    if not a or not b:
        return 0.0 if not a and not b else 1.0
    size = lambda s: sum(n for _, n in s)
    known = {} if known is None else known
    by_length = REGISTRY[metric][2] and metric != "lcs_mod" and kw.get("normalise", "longer") == "longer"

    def d(p: tuple, q: tuple) -> float:
        key = (p, q) if p <= q else (q, p)
        if key not in known:
            known[key] = path_distance(p, q, metric, tau, max_len_diff=max_len_diff, **kw)
        return known[key]

    def one_way(x: list, y: list) -> float:
        total, n = 0.0, size(x)
        for p, times in x:
            best = math.inf
            for q, _ in y:
                if by_length and abs(len(p) - len(q)) >= best * max(len(p), len(q)):
                    continue
                best = min(best, d(p, q))
                if not best:
                    break
            total += times * best
            if cutoff is not None and total >= (cutoff + 1e-6) * n:
                break
        return total / n

    x, y = size(a), size(b)
    if x < y or x == y and tie == "first":
        return one_way(a, b)
    return one_way(b, a) if y < x else min(one_way(a, b), one_way(b, a))
