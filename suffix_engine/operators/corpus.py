"""Corpora: rows joined to one text in key order, coded by a dense alphabet; texts, chunks and maps back to the rows."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from suffix_engine.model import CHUNK, CODE, TERMINATOR, TEXT, Corpus
from suffix_engine.operators import prefix
from suffix_engine.session import cut_numbers, written

#: Symbols in a piece at most; a longer row is cut.
PIECE = 1 << 18


def _points(text: str) -> np.ndarray:
    return np.frombuffer(text.encode("utf-32-le"), "<u4")


def symbol_counts(texts: DataFrame, text: str = "text") -> list[tuple[int, int]]:
    """(code point, count), counted in each batch first; as many rows as there are distinct characters come to the driver."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            joined = "".join(x for x in batch[text].to_pylist() if x)
            c, k = np.unique(_points(joined), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int32()), pa.array(k, pa.int64())], ["c", "k"])

    return sorted((r[0], r[1]) for r in texts.select(text).mapInArrow(run, "c int, k long").groupBy("c").agg(F.sum("k")).collect())


def assemble(rows: DataFrame, key: str, text: str, separator: str = "\n", order: str = "smallest") -> Corpus:
    """The non-null texts in key order, separated, with a terminator at the end. Keys are taken as distinct; ties are put in text order.

    An empty table gives the terminator alone.
    """
    spark = rows.sparkSession
    # ranges are sampled, so the texts are made once, before
    own = cut_numbers(rows.select(F.col(key).alias("key"), F.col(text).alias("text")).where("text is not null"))
    placed = prefix.exclusive(own.withColumn("len", F.char_length("text") + F.lit(len(separator))), "len", "key", "text", out="start")
    placed = written(placed, "texts", "zstd")
    total, last, number = placed.agg(F.sum("len"), F.max("start"), F.count(F.lit(1))).first()
    n = (total - len(separator) if number else 0) + 1
    found = dict(symbol_counts(placed))
    if number > 1 and separator:
        for c in separator:
            found[ord(c)] = found.get(ord(c), 0) + number - 1
    points = np.array(sorted(found), np.int64)
    counts = np.array([found[int(c)] for c in points], np.int64)
    symbols = [chr(c) for c in points]
    if order == "smallest":
        symbols, counts, end = [TERMINATOR, *symbols], np.r_[1, counts], 0
    else:
        symbols, counts, end = [*symbols, TERMINATOR], np.r_[counts, 1], len(symbols)
    first = 1 if order == "smallest" else 0
    shared = spark.sparkContext.broadcast(points)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            starts, codes = [], []
            for start, value in zip(batch["start"].to_pylist(), batch["text"].to_pylist(), strict=True):
                c = (np.searchsorted(shared.value, _points(value + ("" if start == last else separator))) + first).astype(CODE)
                if start == last:
                    c = np.append(c, CODE.type(end))
                for i in range(0, len(c), PIECE):
                    starts.append(start + i)
                    codes.append(c[i : i + PIECE].tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(starts, pa.int64()), pa.array(codes, pa.binary())], ["start", "codes"])

    pieces = placed.select("start", "text").mapInArrow(run, "start long, codes binary")
    if not number:
        pieces = spark.createDataFrame([(0, CODE.type(end).tobytes())], "start long, codes binary")
    return Corpus(cut_numbers(pieces), n, symbols, counts, order, placed.select("key", "start", (F.col("len") - len(separator)).alias("len")))


def literal(spark: SparkSession, text: str, order: str = "smallest") -> Corpus:
    return assemble(spark.createDataFrame([(0, text)], "k long, t string"), "k", "t", order=order)


def text(corpus: Corpus) -> DataFrame:
    """(pos, code), a row for each symbol."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start, raw in zip(batch["start"].to_pylist(), batch["codes"].to_pylist(), strict=True):
                c = np.frombuffer(raw, CODE)
                yield pa.RecordBatch.from_arrays([pa.array(start + np.arange(len(c)), pa.int64()), pa.array(c.astype(np.int32))], ["pos", "code"])

    return corpus.pieces.mapInArrow(run, TEXT)


def chunks(corpus: Corpus, size: int, halo: int = 0) -> DataFrame:
    """(chunk, start, codes): chunk i has the symbols from i * size on, and halo more, so work on size starts needs no neighbour."""

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, starts, parts = [], [], []
            for start, raw in zip(batch["start"].to_pylist(), batch["codes"].to_pylist(), strict=True):
                c = np.frombuffer(raw, CODE)
                for i in range(max(0, (start - halo - size + 1) // size), (start + len(c) - 1) // size + 1):
                    a, z = max(i * size, start), min((i + 1) * size + halo, start + len(c))
                    if a < z:
                        ids.append(i)
                        starts.append(a)
                        parts.append(c[a - start : z - start].tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(starts, pa.int64()), pa.array(parts, pa.binary())], ["chunk", "start", "codes"])

    parts = corpus.pieces.mapInArrow(split, CHUNK)
    joined = F.array_sort(F.collect_list(F.struct("start", "codes")))
    body = F.aggregate(joined, F.lit(b""), lambda s, x: F.concat(s, x["codes"]))
    return parts.groupBy("chunk").agg(body.alias("codes"), F.min("start").alias("start")).select("chunk", "start", "codes")


def prefix_of(corpus: Corpus, length: int) -> Corpus:
    """The corpus of the first symbols of this one, at most all of them, with a terminator of its own; codes stay."""
    keep, end = min(length, corpus.n - 1), corpus.terminator

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [(s, np.frombuffer(c, CODE)) for s, c in zip(batch["start"].to_pylist(), batch["codes"].to_pylist(), strict=True) if s < keep]
            parts = [(s, np.append(c[: keep - s], CODE.type(end)) if s + len(c) >= keep else c) for s, c in rows]
            yield pa.RecordBatch.from_arrays([pa.array([s for s, _ in parts], pa.int64()), pa.array([c.tobytes() for _, c in parts], pa.binary())], ["start", "codes"])

    pieces = cut_numbers(corpus.pieces.mapInArrow(run, "start long, codes binary")) if keep else corpus.pieces.sparkSession.createDataFrame([(0, CODE.type(end).tobytes())], "start long, codes binary")
    part = Corpus(pieces, keep + 1, corpus.symbols, corpus.counts, corpus.order, corpus.documents)
    got = {r[0]: r[1] for r in text(part).groupBy("code").count().collect()}
    part.counts = np.array([got.get(c, 0) for c in range(corpus.sigma)], np.int64)
    return part


def locate_documents(hits: DataFrame, corpus: Corpus, pos: str = "pos", block: int = 1 << 16) -> DataFrame:
    """Adds key and offset of the row that holds a position: an equi-join on blocks of positions and a filter, no nested loop.

    A row that spans many blocks is listed in each; the separator behind a row counts as its last symbol.
    """
    ends = F.col("start") + F.col("len")
    spans = corpus.documents.withColumn("_b", F.explode(F.sequence(F.floor(F.col("start") / block), F.floor(ends / block))))
    near = hits.withColumn("_b", F.floor(F.col(pos) / block))
    return near.join(spans, "_b").where((F.col(pos) >= F.col("start")) & (F.col(pos) <= ends)).withColumn("offset", F.col(pos) - F.col("start")).drop("_b", "start", "len")


def codes_on_driver(corpus: Corpus, most: int = 1 << 28) -> np.ndarray:
    """The whole text as one array, only if its size is within the given bound."""
    if corpus.n > most:
        raise ValueError(f"{corpus.n} symbols are over the bound of {most} for one machine")
    out = np.zeros(corpus.n, CODE)
    for start, raw in corpus.pieces.select("start", "codes").toLocalIterator():
        c = np.frombuffer(raw, CODE)
        out[start : start + len(c)] = c
    return out
