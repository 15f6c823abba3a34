"""Text inputs in order, and sinks for transforms."""

from __future__ import annotations

import os
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from suffix_engine.model import Corpus
from suffix_engine.operators import prefix


def read_lines(spark: SparkSession, path: str, separator: str = "\n") -> DataFrame:
    """(line, text): lines numbered over all files in order of their paths, however they were split for reading.

    A row's place is that of its split and its order in the split, both known without a shuffle of the texts' order.
    """
    raw = spark.read.option("lineSep", separator).text(path).select(F.col("value").alias("text"), F.col("_metadata.file_path").alias("file"), F.col("_metadata.file_block_start").alias("split"), F.monotonically_increasing_id().alias("place"))
    return prefix.exclusive(raw, None, "file", "split", "place", out="line").select("line", "text")


def read_fasta(spark: SparkSession, path: str) -> DataFrame:
    """(sequence, name, text): records of a header line with > and lines of symbols. Lines before the first header have sequence 0 and no name."""
    lines = read_lines(spark, path).where("text <> ''").withColumn("head", F.col("text").startswith(">").cast("int"))
    numbered = prefix.exclusive(lines, "head", "line", out="before").withColumn("sequence", F.col("before") + F.col("head"))
    body = F.transform(F.array_sort(F.collect_list(F.when(F.col("head") == 0, F.struct("line", "text")))), lambda x: x["text"])
    return numbered.groupBy("sequence").agg(F.max(F.when(F.col("head") == 1, F.expr("substring(text, 2)"))).alias("name"), F.array_join(body, "").alias("text"))


def read_table(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, columns: list[str] | None = None) -> DataFrame:
    """Parquet, ORC, JSON or CSV with a given schema (never inferred for the last two); only the columns asked for are read."""
    reader = spark.read.schema(schema) if schema else spark.read
    df = reader.option("header", True).csv(path) if kind == "csv" else reader.format(kind).load(path)
    return df.select(columns) if columns else df


class ByteRangeSource(DataSource):
    """Format "byte_ranges": (pos long, bytes binary) of one large file on storage that all workers mount; options path and size."""

    @classmethod
    def name(cls) -> str:
        return "byte_ranges"

    def schema(self) -> str:
        return "pos long, bytes binary"

    def reader(self, schema) -> DataSourceReader:
        return ByteRangeReader(self.options)


class _Range(InputPartition):
    def __init__(self, start: int, end: int):
        self.start, self.end = start, end


class ByteRangeReader(DataSourceReader):
    def __init__(self, options):
        self.path, self.size = options["path"], int(options.get("size", 1 << 24))

    def partitions(self):
        n = os.path.getsize(self.path)
        return [_Range(i, min(n, i + self.size)) for i in range(0, n, self.size)] or [_Range(0, 0)]

    def read(self, partition):
        with open(self.path, "rb") as f:
            f.seek(partition.start)
            yield (partition.start, f.read(partition.end - partition.start))


def write_sorted(df: DataFrame, path: str, column: str = "rank", files: int | None = None) -> None:
    """Parquet files in order of a column, so that readers of a range skip all other files."""
    n = files or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    df.repartitionByRange(n, column).sortWithinPartitions(column).write.mode("errorifexists").parquet(path)


def write_symbols(bwt: DataFrame, corpus: Corpus, path: str, block: int = 1 << 16) -> None:
    """The transform as JSON lines (block, symbols), a line for each block of ranks."""
    names = corpus.symbols

    def gather(table: pa.Table) -> pa.Table:
        code = table["code"].to_numpy()[np.argsort(table["rank"].to_numpy())]
        return pa.table({"block": table["block"].slice(0, 1), "symbols": ["".join(names[c] for c in code)]})

    bwt.select(F.floor(F.col("rank") / block).alias("block"), "rank", "code").groupBy("block").applyInArrow(gather, "block long, symbols string").write.json(path)


def rows_of_blocks(rows: DataFrame) -> DataFrame:
    """(pos, byte) of byte ranges."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for pos, raw in zip(batch["pos"].to_pylist(), batch["bytes"].to_pylist(), strict=True):
                b = np.frombuffer(raw, np.uint8)
                yield pa.RecordBatch.from_arrays([pa.array(pos + np.arange(len(b))), pa.array(b.astype(np.int32))], ["pos", "byte"])

    return rows.mapInArrow(run, "pos long, byte int")
