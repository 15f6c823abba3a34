"""The definitions themselves, and the baselines that the methods are held against."""

from __future__ import annotations

from collections.abc import Iterator
from functools import cmp_to_key

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from suffix_engine.model import TERMINATOR, Corpus
from suffix_engine.operators import bwt, kmers
from suffix_engine.operators.corpus import codes_on_driver
from suffix_engine.session import cut

#: Sorts behind all other characters, for the terminator as the largest symbol.
_LAST = "\U0010ffff"


def suffix_array(rows: DataFrame, key: str, text: str, order: str = "smallest") -> DataFrame:
    """(key, rank, pos) by sorting all suffixes of each text; texts have no U+10FFFF. Quadratic in the length of a text."""
    end = F.lit("" if order == "smallest" else _LAST)
    own = rows.where(F.col(text).isNotNull()).select(key, F.col(text).alias("_t")).withColumn("pos", F.explode(F.sequence(F.lit(0), F.char_length("_t"))))
    suffix = F.concat(F.expr("substring(_t, pos + 1)"), end)
    place = F.row_number().over(Window.partitionBy(key).orderBy(suffix))
    return own.select(key, (place - 1).cast("long").alias("rank"), F.col("pos").cast("long").alias("pos"))


def rotations_bwt(rows: DataFrame, key: str, text: str, order: str = "smallest") -> DataFrame:
    """(key, bwt, primary) by sorting all rotations and reading their last column. Texts have no U+0000 and no U+10FFFF."""
    end = F.lit("\0" if order == "smallest" else _LAST)
    own = rows.where(F.col(text).isNotNull()).select(key, F.concat(F.col(text), end).alias("_t")).withColumn("pos", F.explode(F.sequence(F.lit(0), F.char_length("_t") - 1)))
    turned = own.withColumn("_r", F.expr("concat(substring(_t, pos + 1), substring(_t, 1, pos))"))
    ranked = turned.select(key, "pos", (F.row_number().over(Window.partitionBy(key).orderBy("_r")) - 1).cast("long").alias("rank"), F.expr("right(_r, 1)").alias("s"))
    shown = F.when(F.col("s") == end, F.lit(TERMINATOR)).otherwise(F.col("s"))
    column = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("rank", shown.alias("s")))), lambda x: x["s"]), "")
    return ranked.groupBy(key).agg(column.alias("bwt"), F.max(F.when(F.col("pos") == 0, F.col("rank"))).alias("primary"))


def whole_order(raw: bytes, positions: np.ndarray) -> list[int]:
    """Positions in the order of the whole suffixes; raw has two bytes for each symbol. A comparison copies no more of two suffixes than
    twice what they have in common, and nothing is kept of it."""

    def compare(a: int, b: int) -> int:
        a, b, step = 2 * a, 2 * b, 64
        while (x := raw[a : a + step]) == (y := raw[b : b + step]) and x:
            a, b, step = a + step, b + step, min(2 * step, 1 << 16)
        return (x > y) - (x < y)

    return sorted(positions.tolist(), key=cmp_to_key(compare))


def mapreduce_sort(corpus: Corpus, k: int | None = None, r: int | None = None) -> DataFrame:
    """(rank, pos): the earlier way, ranges of sampled k-mers and comparison of whole suffixes in each. For texts that fit in a worker."""
    spark = corpus.pieces.sparkSession
    k, r = k or min(4, kmers.widest(corpus)), r or 4 * spark.sparkContext.defaultParallelism
    codes = codes_on_driver(corpus, 1 << 26)
    shared = spark.sparkContext.broadcast((codes.astype(">u2")).tobytes())

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bucket = TaskContext.get().partitionId()
        pos = np.concatenate([np.zeros(0, np.int64), *(b["pos"].to_numpy() for b in batches)])
        order = whole_order(shared.value, pos)
        yield pa.RecordBatch.from_arrays([pa.array(np.full(len(order), bucket, np.int32)), pa.array(np.arange(len(order))), pa.array(order, pa.int64())], ["bucket", "ord", "pos"])

    rows = cut(kmers.extract(corpus, k).repartitionByRange(r, "kmer").mapInArrow(run, "bucket int, ord long, pos long"))
    counts = {b: c for b, c in rows.groupBy("bucket").count().collect()}
    offsets = np.r_[0, np.cumsum([counts.get(b, 0) for b in range(max(counts) + 1)])]
    return rows.select((F.get(F.array(*(F.lit(int(x)) for x in offsets)), "bucket") + F.col("ord")).alias("rank"), "pos")


def split_index(rows: DataFrame, key: str, text: str, r: int = 8, separator: str = "\n", order: str = "smallest") -> DataFrame:
    """(split, n, bwt, primary): only the input is split, by the key's remainder, and each split indexed alone; r transforms without a common order."""

    def run(table: pa.Table) -> pa.Table:
        table = table.sort_by("k")
        b, i = bwt.encode(separator.join(table["t"].to_pylist()), order)
        return pa.table({"split": table["split"].slice(0, 1).cast(pa.int32()), "n": pa.array([len(b)], pa.int64()), "bwt": [b], "primary": pa.array([i], pa.int64())})

    own = rows.where(F.col(text).isNotNull()).select(F.pmod(F.col(key).cast("long"), F.lit(r)).cast("int").alias("split"), F.col(key).alias("k"), F.col(text).alias("t"))
    return own.groupBy("split").applyInArrow(run, "split int, n long, bwt string, primary long")


def local_suffix_array(corpus: Corpus) -> np.ndarray:
    """On one machine, exactly; for texts within a bound."""
    codes = codes_on_driver(corpus, 1 << 26).astype(np.int64)
    out = np.empty(len(codes), np.int64)
    out[bwt.local_ranks(codes)] = np.arange(len(codes))
    return out
