"""Suffix arrays and their inverses, and search on them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from suffix_engine.model import CODE, Corpus
from suffix_engine.operators.corpus import chunks
from suffix_engine.session import cut


def invert(ranks: DataFrame) -> DataFrame:
    """(pos, rnk) as (rank, pos): a renaming."""
    return ranks.select(F.col("rnk").alias("rank"), "pos")


def ranks_of(sa: DataFrame) -> DataFrame:
    return sa.select("pos", F.col("rank").alias("rnk"))


def binary_search(sa: DataFrame, corpus: Corpus, patterns: DataFrame, size: int = 1 << 12) -> DataFrame:
    """(pattern_id, lo, hi, cnt) of all patterns (pattern_id, pattern), of any length: the rank interval of the suffixes that start with
    each, 0 and 0 if none does. Empty patterns match all suffixes.

    Both ends of all intervals are searched at once; a round joins the suffixes in the middle and the chunks of text that they share
    with the pattern, log2 n rounds in all.
    """
    table = F.create_map(*(x for i, s in enumerate(corpus.symbols) if i != corpus.terminator for x in (F.lit(s), F.lit(i))))
    symbols = F.filter(F.split(F.coalesce("pattern", F.lit("")), ""), lambda s: s != "")
    rows = cut(patterns.select(F.col("pattern_id").cast("long").alias("pattern_id"), F.transform(symbols, lambda s: F.coalesce(F.try_element_at(table, s), F.lit(-1))).alias("own"), F.monotonically_increasing_id().alias("key")))
    sa, body = cut(sa), cut(chunks(corpus, size))
    unknown = F.array_contains("own", F.lit(-1))

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            after = []
            for own, parts, side in zip(batch["own"].to_pylist(), batch["parts"].to_pylist(), batch["side"].to_pylist(), strict=True):
                there = np.frombuffer(b"".join(parts), CODE).tolist()
                after.append(there < own or (side == 1 and there == own))
            yield pa.RecordBatch.from_arrays([batch["key"], batch["side"], pa.array(after, pa.bool_())], ["key", "side", "after"])

    state = cut(rows.where(~unknown & (F.size("own") > 0)).select("key", "own", F.explode(F.array(F.lit(0), F.lit(1))).alias("side"), F.lit(0).cast("long").alias("lo"), F.lit(corpus.n).cast("long").alias("hi")))
    for _ in range(int(corpus.n).bit_length()):
        asked = state.where("lo < hi").select("key", "side", "own", F.floor((F.col("lo") + F.col("hi")) / 2).alias("rank")).join(sa, "rank")
        end = F.least(F.col("pos") + F.size("own"), F.lit(corpus.n))
        reach = asked.withColumn("end", end).withColumn("chunk", F.explode(F.sequence(F.floor(F.col("pos") / size), F.floor((F.col("end") - 1) / size))))
        piece = F.expr(f"substring(codes, cast({CODE.itemsize} * (greatest(pos, start) - start) + 1 as int), cast({CODE.itemsize} * (least(end, start + {size}) - greatest(pos, start)) as int))")
        parts = reach.join(body, "chunk").groupBy("key", "side").agg(F.first("own").alias("own"), F.transform(F.array_sort(F.collect_list(F.struct("start", piece.alias("part")))), lambda x: x["part"]).alias("parts"))
        moved = parts.mapInArrow(compare, "key long, side int, after boolean")
        middle = F.floor((F.col("lo") + F.col("hi")) / 2)
        state = cut(state.join(moved, ["key", "side"], "left").select("key", "own", "side", F.when(F.col("after"), middle + 1).otherwise(F.col("lo")).alias("lo"), F.when(~F.col("after"), middle).otherwise(F.col("hi")).alias("hi")))
    ends = state.groupBy("key").agg(F.max(F.when(F.col("side") == 0, F.col("lo"))).alias("_lo"), F.max(F.when(F.col("side") == 1, F.col("lo"))).alias("_hi"))
    ended = rows.join(ends, "key", "left").withColumn("_hi", F.when(F.size("own") == 0, F.lit(corpus.n)).otherwise(F.col("_hi"))).withColumn("_lo", F.coalesce("_lo", F.lit(0)))
    found = F.col("_hi") > F.col("_lo")
    at = lambda x: F.when(found, x).otherwise(0).cast("long")
    return ended.select("pattern_id", at(F.col("_lo")).alias("lo"), at(F.col("_hi")).alias("hi"), at(F.col("_hi") - F.col("_lo")).alias("cnt"))


def search(sa: DataFrame, corpus: Corpus, patterns: DataFrame) -> DataFrame:
    """The patterns of binary_search that occur."""
    return binary_search(sa, corpus, patterns).where("cnt > 0")


def locate(intervals: DataFrame, sa: DataFrame, block: int = 1 << 16) -> DataFrame:
    """(pattern_id, pos) of the suffixes in rank intervals, by an equi-join on blocks of ranks."""
    blocks = intervals.where("hi > lo").withColumn("_b", F.explode(F.sequence(F.floor(F.col("lo") / block), F.floor((F.col("hi") - 1) / block))))
    return blocks.join(sa.withColumn("_b", F.floor(F.col("rank") / block)), "_b").where("rank >= lo and rank < hi").select("pattern_id", "pos")


def neighbours(df: DataFrame, value: str, rank: str = "rank", block: int = 1 << 16) -> DataFrame:
    """Adds prior_<value>: the value one rank above, null at rank 0. Windows lie within blocks of ranks; each block is given its last row's successor."""
    tagged = df.withColumn("_b", F.floor(F.col(rank) / block)).withColumn("_ghost", F.lit(False))
    border = tagged.where(F.pmod(F.col(rank), F.lit(block)) == block - 1).withColumn("_b", F.col("_b") + 1).withColumn("_ghost", F.lit(True))
    own = Window.partitionBy("_b").orderBy(rank)
    return tagged.unionByName(border).withColumn(f"prior_{value}", F.lag(value).over(own)).where("not _ghost").drop("_b", "_ghost")
