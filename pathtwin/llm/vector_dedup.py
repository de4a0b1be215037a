"""Embedding near-duplicates by int8 tile products with per-vector error bounds.

Unit vectors are quantised to int8 with one scale each; the length of what the quantisation loses is kept
beside it. Products of int8 tiles then bound every cosine from both sides; only pairs whose upper bound
reaches the threshold are worked out again in double precision from the stored values. Distinct vectors
belong to the cell of the nearest of a bounded number of pivots, cells are cut into bands of bounded size and
each pair of bands is one task, which sends counts and a spanning forest of its links, at most one row a
vector, never its pairs. A vector too far from a pivot for a link with any vector of that cell, by the triangle
inequality on angles, isn't sent to the bands of the cell; the same holds for tiles inside a task.

Equal vectors are joined first and weigh as often as they occur. Vectors that are null, empty, zero or hold
null or non-finite components link with nothing, and vectors of different length do not link. Rows with a
null vec_id are left out. Repeated ids are rows of their own and share a component. An empty table gives
an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathtwin.llm.common import map_slices
from pathtwin.plans.components import connected_components
from pathtwin.plans.lineage import cut, settled

THRESHOLD = 0.95
#: Distinct vectors a band holds on average.
BAND = 6144
#: Pivots at most.
PIVOTS = 256
TILE = 768


def quantise(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """int8 codes of the unit vectors, their scales, and the length of the error of each."""
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    scale = np.maximum(np.abs(u).max(1) / 127, 1e-30)
    q = np.rint(u / scale[:, None]).astype(np.int8)
    return q, scale, np.linalg.norm(u - q * scale[:, None], axis=1)


def _forest(n: int, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Smallest index in the component of each of ``n`` nodes."""
    label = np.arange(n)
    while True:
        new = label.copy()
        np.minimum.at(new, i, label[j])
        np.minimum.at(new, j, label[i])
        new = new[new]
        if (new == label).all():
            return label
        label = new


def tile_links(x: np.ndarray, left: np.ndarray, right: np.ndarray, same: bool, threshold: float, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Weighted link counts and component labels over the rows of ``x``; ``left`` meets ``right``."""
    q, scale, err = quantise(x)
    norm = np.linalg.norm(x, axis=1)
    kind = np.float32 if x.shape[1] <= 1000 else np.float64
    q = q.astype(kind)
    unit = x / norm[:, None]
    angle = np.arccos(threshold) + 1e-6

    def tiles(rows: np.ndarray) -> list[tuple[np.ndarray, np.ndarray, float]]:
        if not len(rows):
            return []
        picks = unit[rows[:: max(1, len(rows) // 32)][:32]]
        order = rows[np.argsort((unit[rows] @ picks.T).argmax(1), kind="stable")]
        out = []
        for at in range(0, len(order), TILE):
            r = order[at : at + TILE]
            c = unit[r].mean(0)
            length = np.linalg.norm(c)
            c = c / length if length else unit[r[0]]
            out.append((r, c, float(np.arccos(np.clip(unit[r] @ c, -1, 1)).max())))
        return out

    counts, label = np.zeros(len(x), np.int64), np.arange(len(x))
    a = tiles(left)
    b = a if same else tiles(right)
    for m, (r, c, radius) in enumerate(a):
        for s, d, other in b[m:] if same else b:
            if np.arccos(np.clip(c @ d, -1, 1)) > radius + other + angle:
                continue
            rough = (q[r] @ q[s].T) * scale[r, None] * scale[s]
            room = err[r, None] + err[s] + 3 * err[r, None] * err[s] + 1e-6
            i, j = np.nonzero(rough >= threshold - room)
            i, j = r[i], s[j]
            if r is s:
                i, j = i[i < j], j[i < j]
            for at in range(0, len(i), 1 << 16):
                p, o = i[at : at + (1 << 16)], j[at : at + (1 << 16)]
                hit = np.einsum("ij,ij->i", x[p], x[o]) / (norm[p] * norm[o]) >= threshold
                p, o = p[hit], o[hit]
                if len(p):
                    np.add.at(counts, p, weight[o])
                    np.add.at(counts, o, weight[p])
                    label = _forest(len(x), np.concatenate([np.arange(len(x)), p]), np.concatenate([label, o]))
    return counts, label


def _met(groups: DataFrame, total: int, threshold: float, band: int) -> DataFrame:
    """``groups`` once for each pair of bands that they take part in: ``id, v, n, g, lo, hi``; ``g`` is the own band."""
    wanted = min(PIVOTS, -(-total // band))
    picked = groups.orderBy(F.xxhash64("id", "v")).limit(wanted).select("v").collect()
    pivots: dict[int, np.ndarray] = {}
    for dim in sorted({len(r["v"]) for r in picked}):
        x = np.array([r["v"] for r in picked if len(r["v"]) == dim])
        pivots[dim] = x / np.linalg.norm(x, axis=1, keepdims=True)
    reach = float(np.arccos(threshold)) + 1e-6

    def angles(v: list) -> np.ndarray:
        """Angles to the pivots of the same length; to none, one cell that all vectors of the length belong to."""
        x = np.array(v, np.float64)
        p = pivots.get(len(v))
        return np.zeros(1) if p is None else np.arccos(np.clip(p @ (x / np.linalg.norm(x)), -1, 1))

    def deal(parts: Iterator[dict]) -> Iterator[dict]:
        for p in parts:
            a = [angles(v) for v in p["v"]]
            yield {**p, "dim": [len(v) for v in p["v"]], "cell": [int(x.argmin()) for x in a], "angle": [float(x.min()) for x in a]}

    dealt = cut(map_slices(groups, deal, "v array<double>, id long, n long, dim int, cell int, angle double"))
    cells, first, span = {}, [], []
    for r in dealt.groupBy("dim", "cell").agg(F.count("*").alias("n"), F.max("angle").alias("radius")).orderBy("dim", "cell").collect():
        cells.setdefault(r["dim"], []).append((r["cell"], r["radius"], len(first)))
        first.append(first[-1] + span[-1] if first else 0)
        span.append(-(-r["n"] // band))
    if not first:
        return dealt.select("id", "v", "n", F.lit(0).alias("g"), F.lit(0).alias("lo"), F.lit(0).alias("hi"))

    def aim(parts: Iterator[dict]) -> Iterator[dict]:
        for p in parts:
            own, met = [], []
            for v, cell in zip(p["v"], p["cell"], strict=True):
                a = angles(v)
                own.append(next(k for c, _, k in cells[len(v)] if c == cell))
                met.append([k for c, radius, k in cells[len(v)] if a[c] <= radius + reach])
            yield {"id": p["id"], "v": p["v"], "n": p["n"], "own": own, "met": met}

    starts, spans = (F.array(*[F.lit(x) for x in xs]) for xs in (first, span))
    bands = lambda k: F.sequence(F.get(starts, k), F.get(starts, k) + F.get(spans, k) - 1)
    aimed = map_slices(dealt.select("id", "v", "n", "cell"), aim, "id long, v array<double>, n long, own int, met array<int>")
    aimed = aimed.withColumn("g", F.get(starts, F.col("own")) + F.pmod(F.xxhash64("id", "v"), F.get(spans, F.col("own")).cast("long")).cast("int"))
    sent = aimed.withColumn("h", F.explode(F.flatten(F.transform("met", bands))))
    return sent.select("id", "v", "n", "g", F.least("g", "h").alias("lo"), F.greatest("g", "h").alias("hi"))


def near_duplicates(vectors: DataFrame, threshold: float = THRESHOLD, band: int = BAND) -> DataFrame:
    """Rows ``vec_id, n_links, component_id, kept``, one a vector with an id."""
    v = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("v")).filter(F.col("vec_id").isNotNull())
    number = lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))
    sound = F.coalesce((F.size("v") > 0) & F.forall("v", number) & F.exists("v", lambda x: x != 0), F.lit(False))
    v = v.withColumn("sound", sound).withColumn("v", F.when(F.col("sound"), F.transform("v", lambda x: x + F.lit(0.0))))
    groups = v.filter("sound").groupBy("v").agg(F.min("vec_id").alias("id"), F.count("*").alias("n"))
    groups = cut(groups)
    sent = _met(groups, groups.count(), threshold, band)

    def meet(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        lo, hi = key
        x = np.stack(rows["v"].to_numpy()).astype(np.float64)
        g, ids = rows["g"].to_numpy(), rows["id"].to_numpy()
        counts, label = tile_links(x, np.flatnonzero(g == lo), np.flatnonzero(g == hi), lo == hi, threshold, rows["n"].to_numpy())
        at = np.flatnonzero(counts)
        return pd.DataFrame({"id": ids[at], "links": counts[at], "to": ids[label[at]]})

    found = cut(sent.groupBy("lo", "hi").applyInPandas(meet, "id long, links long, to long"))
    counts = found.groupBy("id").agg(F.sum("links").alias("links"))
    parts = settled(lambda: connected_components(found.select(F.col("id").alias("a"), F.col("to").alias("b"))))
    groups = groups.join(counts, "id", "left").join(parts.withColumnRenamed("node", "id"), "id", "left")
    groups = groups.select("v", (F.coalesce("links", F.lit(0)) + F.col("n") - 1).alias("n_links"), F.coalesce("component", "id").alias("component_id"))
    out = v.join(groups, "v", "left").select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"))
    return out.withColumn("kept", F.col("vec_id") == F.col("component_id"))


ORACLE = """
WITH RECURSIVE v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS e FROM embeddings),
l AS (SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.vec_id <> b.vec_id AND list_cosine_similarity(a.e, b.e) >= 0.95),
r AS (SELECT vec_id AS a, vec_id AS b FROM v UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a),
c AS (SELECT a, min(b) AS component_id FROM r GROUP BY a),
n AS (SELECT a, count(*) AS n FROM l GROUP BY a)
SELECT c.a AS vec_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_links, component_id, c.a = component_id AS kept FROM c LEFT JOIN n ON c.a = n.a
"""
