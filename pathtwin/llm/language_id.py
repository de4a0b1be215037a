"""Language identification by sparse multinomial logistic regression on TF-IDF character n-grams.

n-grams of one to three characters of the lower-cased text are hashed into a fixed number of buckets.
Document frequencies cover all documents that may be learned from. The weights are trained online, by
follow-the-regularised-leader with an elastic-net penalty, on a bounded sample of them that one task streams
through once; a part of the sample is left out of training and sets the temperature of the final weights. A
prediction is the mean of one table row for each n-gram occurrence, so texts of any length are scored in pieces.

A null text, or one without a letter, gets ``und`` with score 1. With no learned language all others
get ``und`` with score 0. Repeated rows and ties change nothing; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathtwin.llm.common import fold, least_by_hash, map_slices
from pathtwin.plans.lineage import cut

#: Buckets are 2**BITS; half as many for each doubling of the languages beyond WIDE, so that the table stays bounded.
BITS, WIDE = 15, 256
#: Labelled rows that are streamed through the trainer, the least by hash of the id.
SAMPLE = 9_000
#: Characters worked on at once.
STEP = 1 << 18


def bits_for(languages: int) -> int:
    return max(8, BITS - max(0, (languages - 1) // WIDE).bit_length())


def grams(text: str, bits: int = BITS) -> Iterator[np.ndarray]:
    """Bucket of every n-gram occurrence, in pieces; fewer bits join neighbouring buckets."""
    c = np.frombuffer(text.lower().encode("utf-32-le", "surrogatepass"), "<u4")
    for at in range(0, len(c), STEP):
        x = c[at : at + STEP + 2]
        n = min(STEP, len(c) - at)
        one = x * np.uint32(0x9E3779B1)
        two = (one[:-1] ^ np.uint32(0x7F4A7C15)) * np.uint32(0x85EBCA6B) + one[1:]
        three = (two[:-1] ^ np.uint32(0x2545F491)) * np.uint32(0xC2B2AE35) + one[2:]
        yield np.concatenate([one[:n], two[:n], three[:n]]) >> np.uint32(32 - bits)


def document_frequencies(docs: DataFrame, bits: int = BITS) -> tuple[np.ndarray, int]:
    """Documents of ``docs`` that hold each bucket, and their number."""
    size = 1 << bits

    def run(parts: Iterator[dict]) -> Iterator[dict]:
        df, n, marks = np.zeros(size, np.int64), 0, np.zeros(size, np.uint8)
        for p in parts:
            for text in p["text"]:
                if text:
                    for g in grams(text, bits):
                        marks[g] = 1
                    df += marks
                    marks[:] = 0
                n += 1
        found = np.flatnonzero(df)
        yield {"bucket": np.append(found, -1), "n": np.append(df[found], n)}

    counted = map_slices(docs.select(F.col("text").cast("string").alias("text")), run, "bucket long, n long")
    summed = counted.groupBy("bucket").agg(F.sum("n").alias("n")).toPandas()
    out, total = np.zeros(size, np.int64), 0
    for bucket, n in zip(summed["bucket"], summed["n"], strict=True):
        if bucket < 0:
            total = int(n)
        else:
            out[bucket] = n
    return out, total


class Ftrl:
    """Per-coordinate follow-the-regularised-leader for a softmax over sparse rows."""

    def __init__(self, classes: int, size: int = 1 << BITS, alpha: float = 0.8, beta: float = 1.0, l1: float = 0.02, l2: float = 0.02):
        self.alpha, self.beta, self.l1, self.l2 = alpha, beta, l1, l2
        self.z, self.n = np.zeros((size, classes)), np.zeros((size, classes))

    def weights(self, at: np.ndarray | slice) -> np.ndarray:
        z, n = self.z[at], self.n[at]
        w = -(z - np.sign(z) * self.l1) / ((self.beta + np.sqrt(n)) / self.alpha + self.l2)
        return np.where(np.abs(z) <= self.l1, 0.0, w)

    def learn(self, at: np.ndarray, x: np.ndarray, y: int) -> None:
        w = self.weights(at)
        p = softmax(x @ w)
        p[y] -= 1
        g = x[:, None] * p
        n = self.n[at]
        self.z[at] += g - (np.sqrt(n + g * g) - np.sqrt(n)) / self.alpha * w
        self.n[at] = n + g * g


def softmax(z: np.ndarray) -> np.ndarray:
    e = np.exp(z - z.max(-1, keepdims=True))
    return e / e.sum(-1, keepdims=True)


#: Scale of the relative term frequencies, so that steps are of the usual size.
GAIN = 20.0
#: Temperatures that are tried.
TEMPERATURES = np.geomspace(0.05, 20, 121)


def row_of(text: str, idf: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Buckets of a text and their TF-IDF values."""
    size, count = len(idf), np.zeros(len(idf), np.int64)
    for g in grams(text, size.bit_length() - 1):
        count += np.bincount(g, minlength=size)
    at = np.flatnonzero(count)
    return at, count[at] / count.sum() * idf[at] * GAIN


def best_temperature(z: np.ndarray, y: np.ndarray) -> float:
    """The temperature under which the logits ``z`` give the labels ``y`` the least log loss."""
    loss = lambda t: -np.log(softmax(z / t)[np.arange(len(y)), y] + 1e-12).mean()
    return float(min(TEMPERATURES, key=loss))


def train(sample: Iterator[tuple[str, str]], idf: np.ndarray, languages: list[str]) -> tuple[np.ndarray, float]:
    """Table ``bucket x language`` whose mean over a text's occurrences is its logit, and the temperature.

    Every tenth row is kept out; the final weights score it, and the temperature is fitted to that.
    """
    model, kept = Ftrl(len(languages), len(idf)), []
    index = {x: i for i, x in enumerate(languages)}
    for k, (text, lang) in enumerate(sample):
        if lang not in index or not text:
            continue
        at, x = row_of(text, idf)
        if k % 10 == 9:
            kept.append((at.astype(np.int32), x.astype(np.float32), index[lang]))
        else:
            model.learn(at, x, index[lang])
    table = model.weights(slice(None))
    temperature = best_temperature(np.stack([x @ table[at] for at, x, _ in kept]), np.array([y for _, _, y in kept])) if kept else 1.0
    return table * idf[:, None] * GAIN, temperature


def identify(docs: DataFrame, folds: int = 4, held_out: int = 2, rows: int = SAMPLE) -> DataFrame:
    """Rows ``doc_id, held_out, lang_pred, score`` for every document.

    The sample is chosen by ids and hashes alone, which the driver sees; only its texts move, to one task.
    """
    d = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang"))
    held = F.coalesce(fold("doc_id", folds) == held_out, F.lit(False))
    known = d.filter(~held & F.col("lang").isNotNull() & F.col("text").isNotNull()).withColumn("th", F.xxhash64("text"))
    key = ["doc_id", "th", "lang"]
    chosen = least_by_hash(cut(known.select(*key)), rows, *key).collect()
    languages = sorted({r["lang"] for r in chosen})
    bits = bits_for(len(languages))
    df, total = document_frequencies(known, bits)
    idf = np.log((1 + total) / (1 + df)) + 0.2

    def fit(parts: Iterator[dict]) -> Iterator[dict]:
        table, temperature = train((r for p in parts for r in zip(p["text"], p["lang"], strict=True)), idf, languages)
        at = np.flatnonzero(np.abs(table).sum(1))
        for k in range(0, len(at), 1024):
            yield {"bucket": at[k : k + 1024], "w": table[at[k : k + 1024]].tolist()}
        yield {"bucket": [-1], "w": [[temperature] * len(languages)]}

    table, temperature = np.zeros((1 << bits, len(languages)), np.float32), 1.0
    if languages:
        picks = docs.sparkSession.createDataFrame([(r["doc_id"], r["th"], r["lang"]) for r in chosen], "k long, t long, l string").distinct()
        match = F.col("doc_id").eqNullSafe(F.col("k")) & (F.col("th") == F.col("t")) & (F.col("lang") == F.col("l"))
        sample = known.join(F.broadcast(picks), match, "left_semi").dropDuplicates(key)
        sample = sample.coalesce(1).sortWithinPartitions(F.xxhash64("doc_id"), *key)
        for r in map_slices(sample.select("text", "lang"), fit, "bucket long, w array<double>").toLocalIterator():
            if r["bucket"] < 0:
                temperature = r["w"][0]
            else:
                table[r["bucket"]] = r["w"]
    columns = [np.ascontiguousarray(table[:, k]) for k in range(len(languages))]

    def best(text: str | None) -> tuple[str, float]:
        if not text or not any(map(str.isalpha, text)):
            return "und", 1.0
        if not languages:
            return "und", 0.0
        z, n = np.zeros(len(languages)), 0
        for g in grams(text, bits):
            n += len(g)
            z += [c[g].sum(dtype=np.float64) for c in columns]
        p = softmax(z / n / temperature)
        return languages[int(p.argmax())], float(p.max())

    def predict(parts: Iterator[dict]) -> Iterator[dict]:
        for p in parts:
            lang, score = zip(*map(best, p["text"]), strict=True)
            yield {"doc_id": p["doc_id"], "held_out": p["held_out"], "lang_pred": list(lang), "score": list(score)}

    named = d.select("doc_id", held.alias("held_out"), "text")
    return map_slices(named, predict, "doc_id long, held_out boolean, lang_pred string, score double")
