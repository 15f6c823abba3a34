"""Longest common prefixes of neighbours in suffix order, and what follows from them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from suffix_engine.model import Corpus
from suffix_engine.operators import kmers
from suffix_engine.operators.corpus import codes_on_driver
from suffix_engine.operators.suffix_array import neighbours
from suffix_engine.session import cut


def build(sa: DataFrame, corpus: Corpus, most: int = 1 << 28) -> DataFrame:
    """(rank, pos, lcp): symbols shared with the suffix one rank above, 0 at rank 0. The text is broadcast if it is within the bound."""
    width = kmers.bits(corpus)
    take = 63 // width
    shared = sa.sparkSession.sparkContext.broadcast(codes_on_driver(corpus, most))

    def packed(codes: np.ndarray, at: np.ndarray) -> np.ndarray:
        out = np.zeros(len(at), np.int64)
        for j in range(take):
            out = (out << width) | np.where(at + j < len(codes), codes[np.minimum(at + j, len(codes) - 1)].astype(np.int64) + 1, 0)
        return out

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        codes = shared.value
        for batch in batches:
            a, b = batch["pos"].to_numpy(), batch["prior_pos"].to_numpy(zero_copy_only=False)
            out, active = np.zeros(len(a), np.int64), np.flatnonzero(~np.isnan(b.astype(float)))
            b = np.nan_to_num(b.astype(float)).astype(np.int64)
            while len(active):
                x, y = packed(codes, a[active] + out[active]), packed(codes, b[active] + out[active])
                same = x == y
                differ = (x ^ y)[~same]
                out[active[~same]] += take - 1 - (np.frexp(differ.astype(float))[1] - 1) // width
                out[active[same]] += take
                active = active[same]
            yield pa.RecordBatch.from_arrays([batch["rank"], batch["pos"], pa.array(out)], ["rank", "pos", "lcp"])

    return neighbours(sa.select("rank", "pos"), "pos").select("rank", "pos", "prior_pos").mapInArrow(run, "rank long, pos long, lcp long")


def by_levels(sa: DataFrame, levels: list[tuple[int, DataFrame]]) -> DataFrame:
    """The same from kept ranks (h, ranks by the first h symbols) with h = 1, 2, 4, ...: for texts of any size, by joins from the longest h down."""
    pairs = cut(neighbours(sa.select("rank", "pos"), "pos").select("rank", "pos", F.col("prior_pos").alias("other"), F.lit(0).cast("long").alias("lcp")))
    for h, ranks in sorted(levels, key=lambda x: -x[0]):
        at = lambda c, out: ranks.select(F.col("pos").alias(c), F.col("rnk").alias(out))
        joined = pairs.withColumn("_a", F.col("pos") + F.col("lcp")).withColumn("_b", F.col("other") + F.col("lcp")).join(at("_a", "ra"), "_a", "left").join(at("_b", "rb"), "_b", "left")
        pairs = cut(joined.select("rank", "pos", "other", (F.col("lcp") + F.when(F.col("ra") == F.col("rb"), h).otherwise(0)).alias("lcp")))
    return pairs.select("rank", "pos", "lcp")


def summary(lcp: DataFrame, n: int) -> DataFrame:
    """(longest_repeat, distinct_substrings) of the text without its terminator. The exact sum is a decimal: it grows as n squared."""
    total = F.lit(n - 1).cast("decimal(38,0)") * F.lit(n) / 2
    return lcp.agg(F.max("lcp").alias("longest_repeat"), F.sum(F.col("lcp").cast("decimal(20,0)")).alias("s")).select("longest_repeat", (total - F.col("s")).cast("decimal(38,0)").alias("distinct_substrings"))


def longest_repeats(lcp: DataFrame) -> DataFrame:
    """(pos, lcp) of the suffixes that begin a longest repeat, as the later of two neighbours."""
    best = lcp.agg(F.max("lcp").alias("best"))
    return lcp.join(F.broadcast(best), F.col("lcp") == F.col("best")).select("pos", "lcp")
