"""Arrays as compressed binary columns, and how they are dealt out."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F


def packed(**columns: np.ndarray) -> bytes:
    """Arrays of one length as compressed bytes."""
    batch = pa.RecordBatch.from_arrays([pa.array(x) for x in columns.values()], list(columns))
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, batch.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
        out.write_batch(batch)
    return sink.getvalue().to_pybytes()


def unpacked(raw: bytes) -> dict[str, np.ndarray]:
    table = pa.ipc.open_stream(raw).read_all()
    return {name: table[name].to_numpy() for name in table.column_names}


def fewest(values: np.ndarray, most: int) -> np.ndarray:
    """In the narrowest type that holds most."""
    return values.astype(np.uint8 if most < 1 << 8 else np.uint16 if most < 1 << 16 else np.uint32 if most < 1 << 32 else np.int64)


def spread(spark: SparkSession, count: int) -> list[int]:
    """So many numbers whose hashes deal them out to as many partitions, one each."""
    got = spark.range(count * (20 + count.bit_length())).select(F.col("id").cast("int").alias("id")).groupBy(F.pmod(F.hash("id"), F.lit(count)).alias("p")).agg(F.min("id").alias("id")).collect()
    found, taken = {r[0]: r[1] for r in got}, {r[1] for r in got}
    rest = iter(x for x in range(-count, 0) if x not in taken)
    return [found[p] if p in found else next(rest) for p in range(count)]
