"""Encodings of abstract nodes: none, MD5, a 4-byte prime hash, node-level locality-sensitive hashing."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Prime of the 4-byte polynomial, and buckets of each length cluster.
PRIME, BUCKETS = 31, 200
SHORT, LONG = 3, 8
SEED = "a"


def serialise(tokens: Column) -> Column:
    """Token list as bracketed text."""
    return F.concat(F.lit("["), F.array_join(tokens, ", "), F.lit("]"))


def md5(tokens: Column) -> Column:
    return F.md5(serialise(tokens))


def prime4(tokens: Column) -> Column:
    """Polynomial of the character codes by a prime, modulo 2**32."""
    chars = F.transform(F.split(serialise(tokens), ""), F.ascii)
    return F.aggregate(chars, F.lit(0).cast("long"), lambda h, c: F.pmod(h * PRIME + c, F.lit(1 << 32)))


def lsh(tokens: Column) -> Column:
    """Bucket id: cluster by clamped token count, then the MinHash of its tokens, each with its place modulo four; clusters never meet."""
    cluster = F.greatest(F.lit(SHORT), F.least(F.lit(LONG), F.size(tokens)))
    placed = F.transform(tokens, lambda t, i: F.concat_ws(" ", F.pmod(i, F.lit(4)).cast("string"), t))
    least = F.array_min(F.transform(placed, lambda g: F.md5(F.concat(F.lit(SEED), g))))
    number = F.conv(F.substring(F.coalesce(least, F.lit("0")), 1, 8), 16, 10).cast("long")
    return (cluster - SHORT).cast("long") * BUCKETS + F.pmod(number, F.lit(BUCKETS))


def code(tokens: Column, how: str) -> Column:
    """Node code as LONG for matching; equal codes stand for equal encodings."""
    if how == "none":
        return F.xxhash64(F.array_join(tokens, "\x01"))
    if how == "md5":
        return F.xxhash64(md5(tokens))
    if how == "prime4":
        return prime4(tokens)
    if how == "lsh":
        return lsh(tokens)
    raise ValueError(how)


def with_model_codes(paths: DataFrame, seed: int = 5) -> DataFrame:
    """PATHS with ``code`` by the MinHash model of the ML library instead: every distinct node is hashed once and joined back."""
    from pyspark.ml.feature import HashingTF, MinHashLSH
    from pyspark.ml.functions import vector_to_array

    nodes = paths.select("fragment_id", "path_no", F.posexplode("nodes").alias("at", "tokens"))
    distinct = nodes.select("tokens").distinct().withColumn("placed", F.transform("tokens", lambda t, i: F.concat_ws(" ", F.pmod(i, F.lit(4)).cast("string"), t)))
    vectors = HashingTF(inputCol="placed", outputCol="v", binary=True, numFeatures=1 << 16).transform(distinct.filter(F.size("tokens") > 0))
    model = MinHashLSH(inputCol="v", outputCol="h", numHashTables=1, seed=seed).fit(vectors)
    cluster = F.greatest(F.lit(SHORT), F.least(F.lit(LONG), F.size("tokens")))
    number = vector_to_array(F.col("h")[0])[0].cast("long")
    coded = model.transform(vectors).select("tokens", ((cluster - SHORT).cast("long") * BUCKETS + F.pmod(number, F.lit(BUCKETS))).alias("c"))
    code = F.transform(F.array_sort(F.collect_list(F.struct("at", F.coalesce("c", F.lit(0).cast("long")).alias("c")))), lambda x: x["c"])
    made = nodes.join(coded, "tokens", "left").groupBy("fragment_id", "path_no").agg(code.alias("code"))
    return paths.join(made, ["fragment_id", "path_no"])
