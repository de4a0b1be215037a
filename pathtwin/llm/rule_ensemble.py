"""Quality classifier: a sparse ensemble of rules over text statistics, compiled into Column expressions.

Shallow boosted trees are grown on a bounded sample of labelled rows; every path of a tree from its root
becomes a conjunctive rule; a logistic model with a lasso penalty, fitted by accelerated proximal
gradient steps, keeps few of them. The kept rules and weights are compiled into one Column, so scoring
all documents is a projection over statistics that Spark works out itself.

A null or empty text has statistics of zero and gets the score of such texts. Ties in the sample order
are broken by the id's hash; conflicting labels of one id count by their largest. Without labels the
score is 0.5 everywhere; labels of one class alone give a constant. An empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathtwin.llm import text_stats as S
from pathtwin.llm.common import fold, least_by_hash
from pathtwin.plans.lineage import cut

#: Labelled rows that the model is fitted on, the least by hash of the id.
SAMPLE = 20_000
FEATURES = (
    "words", "mean_word", "symbol_share", "upper_share", "digit_share", "mark_share", "dup_line_share", "repeat_share", "distinct_share",
    "line_words", "bang_share", "long_words",
)


def with_features(docs: DataFrame) -> DataFrame:
    """``doc_id`` and the statistics of whole texts."""
    text = F.coalesce(F.col("text"), F.lit(""))
    d = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"))
    d = d.withColumns({"w": S.words(F.col("text")), "l": S.worded_lines(F.col("text"))})
    d = d.withColumns({
        "n": F.size("w"), "wc": S.word_chars(F.col("text")), "sym": S.n_symbols(F.col("text")), "up": S.chars_of(F.col("text"), r"[^\p{Lu}]+"),
        "dig": S.chars_of(F.col("text"), r"[^0-9]+"), "mark": S.chars_of(F.col("text"), r"[\p{L}\p{N}\x20\x09-\x0D]+"), "bang": S.chars_of(F.col("text"), r"[^!?]+"),
        "dup": S.n_dup_lines(F.col("l")), "rep": S.n_repeat_words(F.col("w")), "nl": F.size("l"), "dist": F.size(F.array_distinct("w")),
        "long": F.size(F.filter("w", lambda x: F.length(x) > 15)),
    })
    share = lambda a, b: F.when(F.col(b) > 0, F.col(a) / F.col(b)).otherwise(0.0)
    made = (
        F.log1p("n"), share("wc", "n"), share("sym", "wc"), share("up", "wc"), share("dig", "wc"), share("mark", "wc"), share("dup", "nl"), share("rep", "n"), share("dist", "n"),
        share("n", "nl"), share("bang", "wc"), share("long", "n"),
    )
    return d.select("doc_id", *[c.cast("double").alias(name) for name, c in zip(FEATURES, made, strict=True)])


@dataclass
class RuleModel:
    """Weights of conjunctions of ``(feature, is_greater, threshold)``."""

    intercept: float
    rules: list[tuple[tuple[tuple[int, bool, float], ...], float]] = field(default_factory=list)
    names: tuple[str, ...] = FEATURES

    def column(self) -> Column:
        """Probability as an expression over the statistics."""
        total = F.lit(self.intercept)
        for terms, weight in self.rules:
            hit = None
            for f, greater, cutoff in terms:
                c = F.col(self.names[f]) > cutoff if greater else F.col(self.names[f]) <= cutoff
                hit = c if hit is None else hit & c
            total = total + F.when(hit, F.lit(weight)).otherwise(F.lit(0.0))
        return 1.0 / (1.0 + F.exp(-total))

    def predict(self, x: np.ndarray) -> np.ndarray:
        z = np.full(len(x), self.intercept)
        for terms, weight in self.rules:
            z += weight * _hits(x, terms)
        return 1 / (1 + np.exp(-z))


def _hits(x: np.ndarray, terms: tuple) -> np.ndarray:
    out = np.ones(len(x), bool)
    for f, greater, cutoff in terms:
        out &= (x[:, f] > cutoff) == greater
    return out


def _grow(x: np.ndarray, g: np.ndarray, h: np.ndarray, rows: np.ndarray, path: tuple, depth: int, least: int, out: list, leaves: list) -> None:
    """One node of a boosted tree; every node but the root leaves its path in ``out``, every leaf its path and step in ``leaves``."""
    if path:
        out.append(path)
    score = lambda a, b: a * a / (b + 1.0)
    best = (1e-6, None)
    total_g, total_h = g[rows].sum(), h[rows].sum()
    if depth and len(rows) >= 2 * least:
        for f in range(x.shape[1]):
            v = x[rows, f]
            for cutoff in np.unique(np.quantile(v, np.linspace(0.04, 0.96, 24), method="lower")):
                left = v <= cutoff
                n = left.sum()
                if least <= n <= len(rows) - least:
                    a, b = g[rows][left].sum(), h[rows][left].sum()
                    gain = score(a, b) + score(total_g - a, total_h - b) - score(total_g, total_h)
                    if gain > best[0]:
                        best = (gain, (f, float(cutoff), left))
    if best[1] is None:
        leaves.append((path, -total_g / (total_h + 1.0)))
        return
    f, cutoff, left = best[1]
    _grow(x, g, h, rows[left], (*path, (f, False, cutoff)), depth - 1, least, out, leaves)
    _grow(x, g, h, rows[~left], (*path, (f, True, cutoff)), depth - 1, least, out, leaves)


def fit_rules(x: np.ndarray, y: np.ndarray, trees: int = 12, depth: int = 3, penalty: float = 2e-3, steps: int = 400, seed: int = 7) -> RuleModel:
    """Trees on random halves, then the lasso over their paths."""
    if not len(y):
        return RuleModel(0.0)
    rate = (y.sum() + 0.5) / (len(y) + 1)
    base = float(np.log(rate / (1 - rate)))
    if y.min() == y.max():
        return RuleModel(base)
    rng, z, paths = np.random.default_rng(seed), np.full(len(y), base), []
    for _ in range(trees):
        p = 1 / (1 + np.exp(-z))
        g, h = p - y, p * (1 - p)
        rows = np.sort(rng.permutation(len(y))[: min(len(y), max(2000, len(y) // 4))])
        found, leaves = [], []
        _grow(x, g, h, rows, (), depth, max(5, len(rows) // 200), found, leaves)
        paths += found
        for terms, step in leaves:
            z[_hits(x, terms)] += 0.5 * step
    paths = list(dict.fromkeys(paths))
    if not paths:
        return RuleModel(base)
    m = np.stack([_hits(x, p) for p in paths], 1).astype(np.float64)
    scale = np.maximum(m.std(0), 1e-3)
    m /= scale
    center = m.mean(0)
    lipschitz = 0.25 * (np.linalg.norm(m - center, 2) ** 2 / len(y) + 1.0)
    w = v = np.zeros(m.shape[1])
    b = c = base
    t = 1.0
    for _ in range(steps):
        p = 1 / (1 + np.exp(-((m - center) @ v + c)))
        new_w = v - (m - center).T @ (p - y) / len(y) / lipschitz
        new_w = np.sign(new_w) * np.maximum(np.abs(new_w) - penalty / lipschitz, 0)
        new_b = c - (p - y).mean() / lipschitz
        t, old = (1 + (1 + 4 * t * t) ** 0.5) / 2, t
        v, c = new_w + (old - 1) / t * (new_w - w), new_b + (old - 1) / t * (new_b - b)
        w, b = new_w, new_b
    kept = np.flatnonzero(w)
    return RuleModel(float(b - center @ w), [(paths[i], float(w[i] / scale[i])) for i in kept])


def labelled_sample(labels: DataFrame, name: str, folds: int, held_out: int, rows: int) -> DataFrame:
    """At most ``rows`` labelled ids outside the held-out fold, the least by hash: ``doc_id, y``."""
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col(name).cast("int").alias("y")).dropna().filter(fold("doc_id", folds) != held_out)
    known = known.groupBy("doc_id").agg(F.max("y").alias("y"))
    return least_by_hash(known, rows, "doc_id").drop("h")


def quality_scores(docs: DataFrame, labels: DataFrame, folds: int = 3, held_out: int = 1, rows: int = SAMPLE) -> DataFrame:
    """Rows ``doc_id, held_out, score, predicted`` and the statistics, for every document.

    Statistics are worked out once and written; the driver sees those of the sampled rows alone.
    """
    stats = cut(with_features(docs))
    seen = stats.join(labelled_sample(labels, "quality", folds, held_out, rows), "doc_id").dropDuplicates(["doc_id"]).toPandas()
    seen = seen.sort_values("doc_id")
    model = fit_rules(seen[list(FEATURES)].to_numpy(np.float64), seen["y"].to_numpy(np.float64))
    scored = stats.withColumn("score", model.column())
    held = F.coalesce(fold("doc_id", folds) == held_out, F.lit(False))
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), *FEATURES)
