"""Rival families against plain Python, and what their plans move."""

import random
from collections import Counter

from pyspark.sql import functions as F

import pathtwin.baselines.families as B
from pathtwin.workloads import variants as V


def test_bags_in_many_blocks_against_every_pair(spark, monkeypatch):
    monkeypatch.setattr(B, "BLOCK_ITEMS", 700)
    rng, bags = random.Random(5), {}
    for i in range(60):
        words = [f"w{int(rng.random() ** 3 * 60)}" for _ in range(rng.choice((3, 9, 30, 42, 60, 90)))]
        bags[i] = words
        bags[100 + i] = [w if rng.random() < 0.85 else f"x{rng.randrange(9)}" for w in words] + ["x1"] * rng.randrange(4)
        bags[200 + i] = list(words) if i % 3 == 0 else words[: len(words) * 7 // 10 or 1]
    rows = [(i, w) for i, w in bags.items()]
    rows += [(300, bags[3][:20]), (300, bags[3][20:]), (301, []), (302, None), (None, ["w1"])]
    bags[300] = bags[3]
    table = spark.createDataFrame(rows, "id long, s array<string>")
    for once in (False, True):
        held = {i: Counter(set(w)) if once else Counter(w) for i, w in bags.items()}
        want = {(i, j) for i in held for j in held if i < j and (held[i] & held[j]).total() >= round(max(held[i].total(), held[j].total()) * 0.7, 9)}
        got = [tuple(r) for r in B._bag_overlap(table, 0.7, once).collect()]
        assert len(got) == len(set(got)) and set(got) == want and len(want) > 60


def test_bags_never_travel_with_pairs(spark):
    """Each pair of candidates once carried both arrays of words."""
    docs = spark.createDataFrame([(i, "\n".join(f"word{j} a" for j in range(15 + i % 3))) for i in range(20)], "doc_id long, text string")
    plan = B.token_bag(docs)._jdf.queryExecution().optimizedPlan().toString()
    assert "array_intersect" not in plan and "FlatMapGroupsInPandas" in plan


def test_training_pairs_of_the_learned_family_grow_with_the_origins(spark, monkeypatch):
    """They once grew with the square: about ten unlike pairs for each variant of these origins."""
    seen = {}
    monkeypatch.setattr(B, "learned", lambda docs, truth: seen.update(truth=truth) or docs)
    v = spark.range(2000).crossJoin(spark.createDataFrame([("ty1",), ("ty2",), ("shift",)], "kind string"))
    lines = F.array(F.concat(F.lit("a1 "), F.col("id").cast("string")), F.lit("b, c"))
    V.learned_pairs(v.select(F.col("id").alias("origin_id"), "kind", lines.alias("s"), F.concat(lines, F.array(F.lit("d"))).alias("v")), v)
    n = {r["y"]: r["count"] for r in seen["truth"].groupBy("y").count().collect()}
    assert n[1] == 4000 and 2000 < n[0] < 8000
    one = seen["truth"].filter("y = 1").first()
    assert one.a[0] == 2 and one.a[4] == 1 and one.b[0] == 3 and one.a[3] in (2, 3, 4, 5)


def test_near_vectors_against_every_pair_that_shares_a_bucket(spark, monkeypatch):
    """Buckets are four radii wide, so they were once joined with most of their pairs far apart."""
    from pyspark.ml.feature import BucketedRandomProjectionLSH
    from pyspark.ml.functions import array_to_vector

    monkeypatch.setattr(B, "TILE", 16)
    monkeypatch.setattr(B, "AT_ONCE", 50)
    rng = random.Random(3)
    rows = [(i % 115, [rng.gauss(0, 4) for _ in range(3)]) for i in range(120)] + [(200 + i, [float(i % 9), 0.0, 1e3]) for i in range(20)] + [(300, [float("nan"), 0.0, 0.0]), (301, [float("inf"), 0.0, 0.0])]
    table = spark.createDataFrame(rows, "id long, v array<double>")
    near = B.tree_vector(table, 2.0)
    v = table.select("id", array_to_vector("v").alias("v"))
    model = BucketedRandomProjectionLSH(inputCol="v", outputCol="h", bucketLength=8.0, numHashTables=6, seed=5).fit(v)
    buckets = [(r.id, list(r.v), [x[0] for x in r.h]) for r in model.transform(v).collect()]
    far = lambda a, b: sum((x - y) ** 2 for x, y in zip(a, b, strict=True)) ** 0.5
    want = {(p, q, round(far(a, b), 6)) for p, a, g in buckets for q, b, h in buckets if p < q and far(a, b) < 2 and any(x == y for x, y in zip(g, h, strict=True))}
    got = [tuple(r) for r in near.collect()]
    assert len(got) == len(set(got)) and set(got) == want and len(want) > 60
    assert "Join" not in near._jdf.queryExecution().optimizedPlan().toString()


def test_blind_lines_are_compared_without_lists(spark, monkeypatch):
    """Blind lines are frequent, so lists of candidates were long."""
    from pathtwin.match import candidates
    from pathtwin.match.detector import detect

    rng, text = random.Random(8), {}
    for i in range(40):
        text[i] = [" ".join(["a"] * rng.randrange(1, 30)) + rng.choice((".", "!", ",")) for _ in range(rng.choice((15, 17, 24)))]
        text[100 + i] = [x if rng.random() < 0.8 else "b?" for x in text[i]]
    docs = spark.createDataFrame([(i, "\n".join(x)) for i, x in text.items()], "doc_id long, text string")
    cfg = B.DetectorConfig.plain().but(metric="lcs", max_set_factor=None)
    want = {tuple(r) for r in detect(B.T.line_paths(docs, "blind"), cfg).select("left_id", "right_id").collect()}
    monkeypatch.setattr(candidates, "candidates", lambda *_: 1 / 0)
    got = [tuple(r) for r in B.line_lcs(docs).collect()]
    assert len(got) == len(set(got)) and set(got) == want and len(want) > 15


def test_small_graphs_share_a_batch(spark):
    """Every graph was once a call of its own, which took most of the time of many small ones."""
    from pathtwin.flow import dominators as D

    rng, graphs = random.Random(4), {}
    for i in range(60):
        graphs[i] = [("entry", "n0")] + [(f"n{rng.randrange(6)}", f"n{rng.randrange(6)}") for _ in range(rng.randint(0, 14))]
    graphs[60] = [("n1", "n2")]
    table = spark.createDataFrame([(i, a, b) for i, g in graphs.items() for a, b in g], "fragment_id long, src string, dst string")
    out = D.dominator_paths(table)
    want = {(i, k, tuple(p[1:])) for i, g in graphs.items() for k, p in enumerate(D.root_to_leaf(D.immediate_dominators(g, "entry"), "entry"))}
    got = [(r.fragment_id, r.path_no, tuple(r.path)) for r in out.collect()]
    assert len(got) == len(set(got)) and set(got) == want
    assert "FlatMapGroups" not in out._jdf.queryExecution().optimizedPlan().toString()


def test_runs_by_chains_against_every_diagonal(spark):
    """Blocks were once joined one by one, and every copy of a text for itself."""
    rng, texts = random.Random(1), {}
    for i in range(25):
        base = [rng.choice("abcdefgh") for _ in range(12)]
        texts[i] = sum([rng.choice((base, ["a", "b"] * rng.randint(1, 6), ["a"] * rng.randint(1, 9), list("abcdefghhg"))) for _ in range(rng.randint(1, 4))], [])
        if i % 3 == 0:
            texts[100 + i] = texts[i]
    texts |= {900: ["a"], 901: []}

    def words(a: list, b: list, block: int) -> int:
        total = 0
        for diag in range(-len(b), len(a)):
            n = 0
            for i in range(max(0, diag), len(a) + 1):
                if i < len(a) and i - diag < len(b) and a[i] == b[i - diag]:
                    n += 1
                else:
                    total += n if n >= block else 0
                    n = 0
        return total

    table = spark.createDataFrame(list(texts.items()), "id long, w array<string>")
    for least in (5, 14, 40):
        want = {(i, j) for i in texts for j in texts if i < j and words(texts[i], texts[j], 5) >= max(least, 5)}
        got = [tuple(r) for r in B.runs(table, 5, least).collect()]
        assert len(got) == len(set(got)) and set(got) == want and len(want) > 20
