"""Streams: arriving documents indexed batch by batch, live symbol counts, sequences by session, k-mers with carried state."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from suffix_engine.operators import bwt
from suffix_engine.session import shared_folder


def read_events(spark: SparkSession, path: str, files: int = 1) -> DataFrame:
    """Events as a stream of files (one file or a folder of them, as a pattern, which both are fine for); times without a zone become timestamps, which watermarks need."""
    schema = spark.read.parquet(path).schema
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files).parquet(f"{path[:-1]}[{path[-1]}]").withColumn("ts", F.col("ts").cast("timestamp"))


def symbol_counts(events: DataFrame, window: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(start, symbol, cnt) in tumbling or sliding windows; rows later than the watermark are dropped."""
    span = F.window("ts", window, slide) if slide else F.window("ts", window)
    return events.withWatermark("ts", late).groupBy(span.alias("w"), F.substring("event_type", 1, 1).alias("symbol")).agg(F.count(F.lit(1)).alias("cnt")).select(F.col("w.start").alias("start"), "symbol", "cnt")


def session_texts(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """(user_id, start, text): the letters of each session in order of time."""
    letters = F.transform(F.array_sort(F.collect_list(F.struct("ts", "event_id", F.substring("event_type", 1, 1).alias("s")))), lambda x: x["s"])
    return events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.array_join(letters, "").alias("text")).select("user_id", F.col("w.start").alias("start"), "text")


def kmer_counts(events: DataFrame, k: int = 3) -> DataFrame:
    """(user_id, kmer, cnt) of new k-mers in each batch; the last k - 1 letters of a user are carried over to the next one."""

    def step(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
        text = (state.get[0] if state.exists else "") + "".join(rows["event_type"].str[0])
        state.update((text[-(k - 1) :] if k > 1 else "",))
        found = pd.Series([text[i : i + k] for i in range(len(text) - k + 1)], dtype=object).value_counts()
        yield pd.DataFrame({"user_id": key[0], "kmer": found.index.astype(object), "cnt": found.to_numpy()})

    return events.groupBy("user_id").applyInPandasWithState(step, "user_id long, kmer string, cnt long", "tail string", "update", GroupStateTimeout.NoTimeout)


def index_documents(docs: DataFrame, path: str, key: str = "doc_id", text: str = "text"):
    """Starts a query that writes each batch's transforms under its own number: a repeated batch overwrites itself."""

    def write(batch: DataFrame, number: int) -> None:
        bwt.per_row(batch, key, text).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return docs.writeStream.foreachBatch(write).option("checkpointLocation", f"{path}-progress").trigger(availableNow=True).start()


def run_to_table(df: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a stream over all that is there and returns the rows: the last state for complete, all rows for append and update."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    last: list[int] = []

    def write(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")
        last.append(number)

    query = df.writeStream.outputMode(mode).foreachBatch(write).option("checkpointLocation", f"{path}-progress").trigger(availableNow=True).start()
    query.awaitTermination()
    if not last:
        return spark.createDataFrame([], df.schema)
    if mode == "complete":
        return spark.read.schema(df.schema).parquet(f"{path}/batch={last[-1]}")
    return spark.read.schema(df.schema).parquet(*(f"{path}/batch={n}" for n in last))
