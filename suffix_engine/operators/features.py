"""Features of texts for learning: how symbols follow each other in a transform."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from suffix_engine.operators import bwt


def bwt_bigrams(rows: DataFrame, key: str, text: str) -> DataFrame:
    """(key, first, second, cnt): pairs of neighbours in each row's transform."""
    t = bwt.per_row(rows, key, text)
    pairs = F.expr("transform(sequence(1, greatest(char_length(bwt) - 1, 1)), i -> struct(substring(bwt, i, 1) as first, substring(bwt, i + 1, 1) as second))")
    return t.where(F.char_length("bwt") > 1).select(key, F.inline(pairs)).groupBy(key, "first", "second").agg(F.count(F.lit(1)).alias("cnt"))


def distance(bigrams: DataFrame, key: str, pairs: DataFrame) -> DataFrame:
    """(a, b, distance): half the sum of absolute differences of pair shares, for given pairs of keys (a, b); joins on pairs of symbols, no cross join."""
    total = bigrams.groupBy(key).agg(F.sum("cnt").alias("n"))
    share = bigrams.join(total, key).select(key, "first", "second", (F.col("cnt") / F.col("n")).alias("p"))
    left = pairs.join(share.withColumnRenamed(key, "a"), "a").select("a", "b", "first", "second", F.col("p").alias("x"), F.lit(0.0).alias("y"))
    right = pairs.join(share.withColumnRenamed(key, "b"), "b").select("a", "b", "first", "second", F.lit(0.0).alias("x"), F.col("p").alias("y"))
    return left.unionByName(right).groupBy("a", "b", "first", "second").agg(F.sum("x").alias("x"), F.sum("y").alias("y")).groupBy("a", "b").agg((F.sum(F.abs(F.col("x") - F.col("y"))) / 2).alias("distance"))
