"""The experiments' texts, made from the given tables by DataFrame functions; every one takes whole tables."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from suffix_engine.model import Corpus
from suffix_engine.operators import corpus

#: The letters of nucleotides and of amino acids; letters a-z are mapped to them cyclically.
NUCLEOTIDES, AMINO_ACIDS = "ACGT", "ACDEFGHIKLMNPQRSTVWY"
_LETTERS = "abcdefghijklmnopqrstuvwxyz"


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def without_terminator(column: str):
    return F.regexp_replace(column, r"\$", "")


def english_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _table(spark, sf_dir, "documents").where("lang = 'en'").select("doc_id", without_terminator("text").alias("text"))


def letters_rows(spark: SparkSession, sf_dir: str, alphabet: str) -> DataFrame:
    """The letters of each text in lower case, mapped; all else is left out. Letters a-z are one byte each, and no byte of other characters is one."""
    table = np.zeros(256, np.uint8)
    table[[ord(x) for x in _LETTERS]] = [ord(alphabet[i % len(alphabet)]) for i in range(len(_LETTERS))]
    rows = _table(spark, sf_dir, "documents").select("doc_id", F.lower("text").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch["text"].cast(pa.large_binary())
            valid = texts.is_valid()
            texts = texts.fill_null(b"")
            _, offsets, data = texts.buffers()
            at = np.frombuffer(offsets, np.int64)[texts.offset : texts.offset + len(texts) + 1]
            mapped = table[np.frombuffer(data or b"", np.uint8)[at[0] : at[-1]]] if len(at) else np.zeros(0, np.uint8)
            keep = mapped != 0
            ends = np.r_[0, np.cumsum(keep)][at - at[0]] if len(at) else np.zeros(1, np.int64)
            out = pa.Array.from_buffers(pa.large_string(), len(texts), [pa.array(valid, pa.bool_()).buffers()[1], pa.py_buffer(ends.astype(np.int64)), pa.py_buffer(mapped[keep])])
            yield pa.RecordBatch.from_arrays([batch["doc_id"], out.cast(batch["text"].type)], ["doc_id", "text"])

    return rows.mapInArrow(run, rows.schema)


def english(spark: SparkSession, sf_dir: str, order: str = "smallest") -> Corpus:
    return corpus.assemble(english_rows(spark, sf_dir), "doc_id", "text", order=order)


def dna(spark: SparkSession, sf_dir: str, order: str = "smallest") -> Corpus:
    return corpus.assemble(letters_rows(spark, sf_dir, NUCLEOTIDES), "doc_id", "text", order=order)


def proteins(spark: SparkSession, sf_dir: str, order: str = "smallest") -> Corpus:
    return corpus.assemble(letters_rows(spark, sf_dir, AMINO_ACIDS), "doc_id", "text", order=order)


def items_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _table(spark, sf_dir, "benchmark").select("item_id", without_terminator("text").alias("text"))


def items(spark: SparkSession, sf_dir: str, order: str = "smallest") -> Corpus:
    """All passages of the benchmark as one text: small enough for the definitions, real enough for repeats."""
    return corpus.assemble(items_rows(spark, sf_dir), "item_id", "text", order=order)


def random_bases_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A text without repeats: signs of neighbouring components as bases."""
    e = _table(spark, sf_dir, "embeddings")
    two = F.transform(F.sequence(F.lit(0), F.floor(F.size("embedding") / 2).cast("int") - 1), lambda i: F.substring(F.lit(NUCLEOTIDES), F.when(F.get("embedding", 2 * i) >= 0, 2).otherwise(0) + F.when(F.get("embedding", 2 * i + 1) >= 0, 1).otherwise(0) + 1, F.lit(1)))
    return e.select("vec_id", F.array_join(two, "").alias("text"))


def random_bases(spark: SparkSession, sf_dir: str) -> Corpus:
    return corpus.assemble(random_bases_rows(spark, sf_dir), "vec_id", "text", separator="")


def event_sequences(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(user_id, text): one letter for each type of event, in order of time."""
    e = _table(spark, sf_dir, "events")
    letter = F.substring("event_type", 1, 1)
    return e.groupBy("user_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("ts", "event_id", letter.alias("s")))), lambda x: x["s"]), "").alias("text"))


def line_flags(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(l_suppkey, text): a skewed alphabet of one or two letters a row, in the order of all columns."""
    t = _table(spark, sf_dir, "lineitem")
    flags = F.concat("l_returnflag", "l_linestatus")
    rest = [c for c in t.columns if c not in ("l_suppkey", "l_orderkey", "l_linenumber")]
    return t.groupBy("l_suppkey").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("l_orderkey", "l_linenumber", *rest, flags.alias("_s")))), lambda x: x["_s"]), "").alias("text"))


def chats(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(conv_id, text): the turns of each conversation, joined."""
    t = _table(spark, sf_dir, "conversations")
    return t.groupBy("conv_id").agg(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("turn", "role", without_terminator("text").alias("s")))), lambda x: x["s"]), "\n").alias("text"))


def item_patterns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return items_rows(spark, sf_dir).select(F.col("item_id").alias("pattern_id"), F.col("text").alias("pattern"))


def word_patterns(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The distinct words of part names, as short patterns."""
    words = _table(spark, sf_dir, "part").select(F.explode(F.split("p_name", " ")).alias("pattern")).distinct()
    return words.select(F.abs(F.xxhash64("pattern")).alias("pattern_id"), "pattern")
