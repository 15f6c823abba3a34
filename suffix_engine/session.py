"""Where lineage is cut: the shared folder of the cluster, never a machine's own disk."""

from __future__ import annotations

import gc
import time
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

_WRITTEN: list[str] = []
#: Seconds between two collections of the driver's garbage, at the least.
RELEASE_EVERY = 5.0
_RELEASED = [0.0]
#: Bytes of a batch that is packed for a checkpoint, on average at most.
PACKED = 1 << 24
#: Spark's own estimate of the size of what it knows nothing about, so estimates over it say no more.
_LONGEST = 2**63 - 1


def shared_folder(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir; only where that is unset, as in tests, one in the warehouse, which a cluster shares, too."""
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder:
        folder = spark.sparkContext.getCheckpointDir() or f"{spark.conf.get('spark.sql.warehouse.dir')}/_intermediate"
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(folder)
    return folder


def cut(df: DataFrame) -> DataFrame:
    """Reliable checkpoint: the rows are written once, and executors may be lost from then on. Spark removes it with the DataFrame where
    spark.cleaner.referenceTracking.cleanCheckpoints is set."""
    shared_folder(df.sparkSession)
    out = bounded(df.checkpoint())
    release(df.sparkSession)
    return out


def cut_numbers(df: DataFrame) -> DataFrame:
    """cut, for long tables of numbers and texts: the checkpoint holds compressed batches instead of rows, which take 40 to 50 bytes each there and
    their texts as they are. Partitions and the order within them stay; joins don't know how the rows lie. Other rows are cut as they are."""
    if not all(isinstance(f.dataType, T.NumericType | T.BooleanType | T.StringType | T.BinaryType) for f in df.schema):
        return cut(df)

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = max(1, batch.num_rows * PACKED // max(PACKED, batch.nbytes))
            for i in range(0, batch.num_rows, rows):
                sink = pa.BufferOutputStream()
                with pa.ipc.new_stream(sink, batch.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
                    out.write_batch(batch.slice(i, rows))
                yield pa.RecordBatch.from_arrays([pa.array([sink.getvalue().to_pybytes()], pa.binary())], ["batch"])

    def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for raw in batch["batch"]:
                yield from pa.ipc.open_stream(raw.as_buffer())

    return cut(df.mapInArrow(pack, "batch binary")).mapInArrow(unpack, df.schema)


def bounded(df: DataFrame) -> DataFrame:
    """The checkpointed rows without Spark's estimate of their size, where that is over what a long holds.

    A checkpoint keeps the estimate of the plan that it ends, and a join's is the product of its sides'. Over rounds of joins the number of
    its digits grows by a factor a round (6 in the block form of the doubling), until the driver does nothing but multiply.
    """
    spark, plan = df.sparkSession, df._jdf.queryExecution().logical()
    if plan.getClass().getSimpleName() != "LogicalRDD":
        return df
    try:
        if plan.stats().sizeInBytes() < _LONGEST:
            return df
    except ValueError:  # more digits than Python reads
        pass
    jvm, java = spark.sparkContext._jvm, spark._jsparkSession
    own = (plan.output(), plan.rdd(), plan.outputPartitioning(), plan.outputOrdering(), plan.isStreaming(), plan.stream())
    leaf = jvm.org.apache.spark.sql.execution.LogicalRDD(*own, java, jvm.scala.Option.empty(), jvm.scala.Some(plan.constraints()))
    return DataFrame(jvm.org.apache.spark.sql.classic.Dataset.ofRows(java, leaf), spark)


def release(spark: SparkSession, at_once: bool = False) -> None:
    """Lets Spark delete the shuffle files (and checkpoints) of earlier rounds. It does so when the driver's objects for them are collected,
    which a driver that holds little may not do for a whole run. at_once: however short ago it was done."""
    if at_once or time.monotonic() - _RELEASED[0] >= RELEASE_EVERY:
        gc.collect()
        spark.sparkContext._jvm.System.gc()
        _RELEASED[0] = time.monotonic()


def cut_by(df: DataFrame, column: str | None = None) -> DataFrame:
    """cut, with equal values of a column in one partition (None: the rows stay where the plan leaves them), which joins on it then know.

    For columns without a hot value: it is planned without adaptive execution, whose plans don't tell how they leave their rows.
    """
    spark, n = df.sparkSession, int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    adaptive = spark.conf.get("spark.sql.adaptive.enabled")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        return cut(df.repartition(n, column) if column else df)
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", adaptive)


def cut_sorted(df: DataFrame, partitions: int, column: str) -> DataFrame:
    """cut of Spark's global sort by a column into so many ranges, however small they are: adaptive execution would put them together."""
    spark, own = df.sparkSession, {"spark.sql.adaptive.enabled": "false", "spark.sql.shuffle.partitions": str(partitions)}
    before = {name: spark.conf.get(name) for name in own}
    df = cut(df)
    try:
        for name, value in own.items():
            spark.conf.set(name, value)
        return cut(df.orderBy(column))
    finally:
        for name, value in before.items():
            spark.conf.set(name, value)


def new_path(spark: SparkSession, name: str) -> str:
    """A folder of its own for a table, to be deleted by scratch or clear."""
    _WRITTEN.append(f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}")
    return _WRITTEN[-1]


def written(df: DataFrame, name: str, compression: str = "snappy") -> DataFrame:
    """The rows as a Parquet table in the shared folder, for wide rows and for reading single columns again."""
    path = new_path(df.sparkSession, name)
    df.write.option("compression", compression).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def discard(spark: SparkSession, path: str) -> None:
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(where, True)


def clear(spark: SparkSession, since: int = 0) -> None:
    """Deletes the tables that written has made (from the given number on); no DataFrame that reads them may be used after this."""
    for path in _WRITTEN[since:]:
        discard(spark, path)
    del _WRITTEN[since:]


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Deletes at its end what written has made inside: for work whose result is stored by then."""
    before = len(_WRITTEN)
    try:
        yield
    finally:
        clear(spark, before)
