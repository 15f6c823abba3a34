"""Exclusive prefix sums and global row numbers without a window over all rows."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from suffix_engine.session import cut_numbers


def ranged(df: DataFrame, *order: str | Column, partitions: int | None = None) -> DataFrame:
    """Rows in partitions that are in order among and within themselves, written once: a second pass sees the same partitions."""
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return cut_numbers(df.repartitionByRange(n, *order).sortWithinPartitions(*order))


def partition_offsets(df: DataFrame, weight: Column) -> dict[int, int]:
    """By partition that has rows, the sum of the weights in all earlier ones; one number for each partition comes to the driver."""
    rows = sorted((r[0], r[1]) for r in df.groupBy(F.spark_partition_id().alias("p")).agg(F.sum(weight.cast("long")).alias("s")).collect())
    at, out = 0, {}
    for p, s in rows:
        out[p] = at
        at += s
    return out


def exclusive(df: DataFrame, weight: str | None, *order: str | Column, out: str = "offset", partitions: int | None = None) -> DataFrame:
    """Adds the sum of weight (or the number of rows) over all rows that come earlier in the order."""
    parts = ranged(df, *order, partitions=partitions)
    shared = df.sparkSession.sparkContext.broadcast(partition_offsets(parts, F.col(weight) if weight else F.lit(1)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = shared.value.get(TaskContext.get().partitionId(), 0)
        for batch in batches:
            w = batch[weight].to_numpy(zero_copy_only=False).astype(np.int64) if weight else np.ones(batch.num_rows, np.int64)
            total = np.cumsum(w)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(at + total - w, pa.int64())], [*batch.schema.names, out])
            at += int(total[-1]) if len(total) else 0

    return parts.mapInArrow(run, T.StructType([*parts.schema.fields, T.StructField(out, T.LongType())]))
