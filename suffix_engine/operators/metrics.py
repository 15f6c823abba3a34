"""Costs: time with a cut-off, balance, blocks, shuffle and spill, sizes, scale-out, and ratios to published times."""

from __future__ import annotations

import threading
import time
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from suffix_engine.model import Corpus
from suffix_engine.operators import bucketed, partial


def timed(make: Callable[[], DataFrame], limit: float | None = None) -> tuple[float, bool]:
    """Seconds until all rows are made (nothing is stored), and whether that was within the limit.

    At the limit all jobs of the run are cancelled, those that it starts later, too; the limit is then returned as a censored figure.
    """
    spark, tag, over, done = SparkSession.active(), f"timed-{uuid.uuid4().hex}", threading.Event(), threading.Event()

    def stop() -> None:
        if not done.wait(limit):
            over.set()
        while not done.wait(0.2):
            spark.sparkContext.cancelJobsWithTag(tag)

    began = time.perf_counter()
    spark.sparkContext.addJobTag(tag)
    watch = threading.Thread(target=stop, daemon=True)
    if limit is not None:
        watch.start()
    try:
        make().write.format("noop").mode("overwrite").save()
    except Exception:
        if not over.is_set():
            raise
    finally:
        done.set()
        spark.sparkContext.removeJobTag(tag)
    return (limit, False) if over.is_set() else (time.perf_counter() - began, True)


def balance(buckets: DataFrame) -> DataFrame:
    """(buckets, largest, mean, ratio)."""
    sizes = buckets.groupBy("bucket").count()
    return sizes.agg(F.count(F.lit(1)).alias("buckets"), F.max("count").alias("largest"), F.avg("count").alias("mean")).withColumn("ratio", F.col("largest") / F.col("mean"))


def block_costs(corpus: Corpus, k: int, r: int, splitters: str = "histogram") -> DataFrame:
    """(bucket, members, l_max, touched): symbols that a full-width kernel must touch, members times (l_max + k - 1)."""
    gaps = partial.bucket_gaps(bucketed.partition(corpus, k, r, splitters), corpus.n)
    return gaps.withColumn("touched", F.col("members") * (F.col("l_max") + k - 1))


def stage_costs(spark: SparkSession, make: Callable[[], DataFrame]) -> dict[str, int]:
    """Bytes shuffled and spilled, and CPU nanoseconds, of all stages that a run makes, from Spark's own status store. Not on Connect."""
    store, array = spark.sparkContext._jsc.sc().statusStore(), spark.sparkContext._gateway.new_array

    def stages() -> dict[tuple[int, int], tuple[int, ...]]:
        rows = store.stageList(None, False, False, array(spark.sparkContext._jvm.double, 0), None)
        each = (rows.apply(i) for i in range(rows.size()))
        return {(x.stageId(), x.attemptId()): (x.shuffleWriteBytes(), x.shuffleReadBytes(), x.memoryBytesSpilled(), x.diskBytesSpilled(), x.executorCpuTime()) for x in each}

    before = set(stages())
    make().write.format("noop").mode("overwrite").save()
    names = ("shuffle_written", "shuffle_read", "memory_spilled", "disk_spilled", "cpu_ns")
    own = [v for k, v in stages().items() if k not in before]
    return dict(zip(names, (sum(x) for x in zip(*own, strict=True)), strict=True)) if own else dict.fromkeys(names, 0)


def scale_out(make: Callable[[int], DataFrame], widths: tuple[int, ...] = (1, 2, 4, 8)) -> dict[int, float]:
    """Speed-up over the first width, where make(w) works in w buckets and so on w cores at most."""
    seconds = {w: timed(lambda w=w: make(w))[0] for w in widths}
    return {w: seconds[widths[0]] / s for w, s in seconds.items()}


def megabytes_per_second(corpus: Corpus, seconds: float) -> float:
    """Symbols count as bytes, as in the published figures."""
    return corpus.n / 1e6 / seconds


def bits_per_symbol(stored_bytes: int, corpus: Corpus) -> float:
    return 8 * stored_bytes / corpus.n


def speed_up(seconds: dict[str, float], base: str) -> dict[str, float]:
    return {k: seconds[base] / v for k, v in seconds.items()}
