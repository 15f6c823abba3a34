"""Bucketed suffix sort: buckets by leading k-mers, a kernel in each bucket, offsets of the buckets."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from suffix_engine.model import BWT, CODE, Corpus
from suffix_engine.operators import anchors, kmers, partial, prefix
from suffix_engine.operators.corpus import chunks, codes_on_driver
from suffix_engine.session import cut, cut_numbers, cut_sorted, release

SPLITTERS = ("sampled", "histogram", "orderby")
READERS = ("broadcast", "chunk_join")
#: Symbols up to which the text itself may be broadcast; beyond it the chunks are joined.
BROADCAST_SYMBOLS = 1 << 28
CHUNK_SYMBOLS = 1 << 16
#: A bucket must fit in one worker; texts with more suffixes under one key are for the hybrid.
MOST_IN_BUCKET = 1 << 26
#: Suffixes in a bucket on average at most, if the number of buckets isn't given.
SUFFIXES = 1 << 20


def partition(corpus: Corpus, k: int, r: int, splitters: str = "sampled") -> DataFrame:
    """(bucket, kmer, pos): buckets in the order of their k-mers, and no k-mer in two of them."""
    keys = kmers.extract(corpus, k)
    if splitters == "histogram":
        table = prefix.exclusive(kmers.histogram(corpus, k), "cnt", "kmer", out="before")
        bucket = F.floor(F.col("before") * r / F.lit(corpus.n)).cast("int")
        return keys.join(table.select("kmer", bucket.alias("bucket")), "kmer").select("bucket", "kmer", "pos")
    dealt = keys.orderBy("kmer") if splitters == "orderby" else keys.repartitionByRange(r, "kmer")
    return cut_numbers(dealt).select(F.spark_partition_id().alias("bucket"), "kmer", "pos")


def _width_of_keys(corpus: Corpus, k: int | str | None, r: int) -> int:
    return kmers.suggest_k(corpus, r) if k == "suggested" else k or min(kmers.widest(corpus), 8)


def borders(corpus: Corpus, k: int, r: int, splitters: str) -> np.ndarray:
    """The first words (of as many symbols as 63 bits hold) of r buckets but the first one, by the histogram of all k-mers: even shares of
    it, or where Spark's own sort parts the k-mers, a frequent one being as many rows as it has shares of 1 / (64 r)."""
    table, width = kmers.histogram(corpus, k), kmers.bits(corpus)
    if splitters == "histogram":
        bucket = F.floor(F.col("before") * r / F.lit(corpus.n))
        first = prefix.exclusive(table, "cnt", "kmer", out="before").groupBy(bucket.alias("bucket")).agg(F.min("kmer").alias("kmer"))
    else:
        share = max(1, corpus.n // (64 * r))
        rows = table.select("kmer", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("cnt") - 1) / share))).alias("share"))
        first = cut_sorted(rows.select("kmer"), r, "kmer").groupBy(F.spark_partition_id().alias("bucket")).agg(F.min("kmer").alias("kmer"))
    found = np.unique(np.array([x[0] for x in first.select("kmer").collect()], np.int64))
    return found[1:] << width * (63 // width - k)


def turns(corpus: Corpus, count: int = anchors.TURNS, k: int | str | None = None, r: int | None = None, kernel: str = "refine", splitters: str = "sampled", reader: str | None = None, reduction: str | None = None) -> anchors.Turns | None:
    """The buckets of the refining kernel over joined chunks, a few at a time and without a table of all positions; None for what is sorted in
    another way. The options are suffix_order's."""
    if kernel != "refine" or (reader or _reader(corpus)) != "chunk_join" or reduction not in (None, "gap_rename"):
        return None
    split = None if splitters == "sampled" else lambda buckets: borders(corpus, _width_of_keys(corpus, k, buckets), buckets, splitters)
    return anchors.turns(corpus, count, r, split=split)


def _reader(corpus: Corpus) -> str:
    return "broadcast" if corpus.n <= BROADCAST_SYMBOLS else "chunk_join"


def suffix_order(corpus: Corpus, k: int | str | None = None, r: int | None = None, kernel: str = "refine", splitters: str = "sampled", reader: str | None = None, reduction: str | None = None) -> DataFrame:
    """(bucket, ord, pos, code): the order within each bucket, and the symbol before each suffix.

    k: None takes what a key holds, up to 8; "suggested" the least k under which no k-mer has more than an even share of the suffixes.
    A broadcast text (up to BROADCAST_SYMBOLS) and joined chunks of it give the same rows. With chunks a bucket gets those that its blocks
    reach into, widest gap + k symbols behind a position, and equal blocks are renamed, in any kernel. The refining kernel over joined chunks
    takes its own way: the chunks deal out what it reads, first symbols and the ranks of anchors, which are joined to them (anchors).
    """
    spark = corpus.pieces.sparkSession
    r = r or max(4 * spark.sparkContext.defaultParallelism, -(-corpus.n // SUFFIXES))
    reader = reader or _reader(corpus)
    reduction = reduction or ("none" if kernel == "refine" and reader == "broadcast" else "gap_rename")
    if reduction == "none" and (kernel != "refine" or reader != "broadcast"):
        raise ValueError("only the refining kernel over a broadcast text needs no renaming")
    own = turns(corpus, 1, k, r, kernel, splitters, reader, reduction)
    if own is not None:
        return anchors.suffix_order(own)
    k = _width_of_keys(corpus, k, r)
    n, width, corpus_end = corpus.n, kmers.bits(corpus), corpus.terminator
    schema = "bucket int, ord long, pos long, code int"
    rows = partition(corpus, k, r, splitters)

    def work(bucket: int, pos: np.ndarray, keys: np.ndarray, padded: np.ndarray, base: int) -> pa.RecordBatch:
        if len(pos) > MOST_IN_BUCKET:
            raise ValueError(f"{len(pos)} suffixes in bucket {bucket}: take a larger k or the hybrid")
        out = partial.sort_bucket(pos, keys, partial.padded_reader(padded, base), n, k, width, kernel, reduction)
        before = np.where(out > 0, padded[np.maximum(out - 1 - base, 0)].astype(np.int32) - 1, corpus_end)
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(out), bucket, np.int32)), pa.array(np.arange(len(out))), pa.array(out.astype(np.int64)), pa.array(before.astype(np.int32))], ["bucket", "ord", "pos", "code"])

    if reader == "broadcast":
        shared = spark.sparkContext.broadcast(partial.padded_codes(codes_on_driver(corpus, BROADCAST_SYMBOLS)))
        if splitters == "histogram":

            def sort_group(table: pa.Table) -> pa.Table:
                return pa.Table.from_batches([work(table["bucket"][0].as_py(), table["pos"].to_numpy(), table["kmer"].to_numpy(), shared.value, 0)])

            return rows.groupBy("bucket").applyInArrow(sort_group, schema)

        def sort_part(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            own = [b for b in batches if b.num_rows]
            if own:
                whole = pa.Table.from_batches(own)
                yield work(TaskContext.get().partitionId(), whole["pos"].to_numpy(), whole["kmer"].to_numpy(), shared.value, 0)

        return rows.mapInArrow(sort_part, schema)
    size = CHUNK_SYMBOLS
    rows = cut_numbers(rows)
    near = chunks_needed(rows, n, k, reduction, size).join(chunks(corpus, size), "chunk").select(F.col("bucket").alias("of"), "start", "codes")

    def sort_cogroup(left: pa.Table, right: pa.Table) -> pa.Table:
        starts, parts = right["start"].to_pylist(), right["codes"].to_pylist()
        base = min(starts)
        codes = np.zeros(max(s + len(c) // CODE.itemsize for s, c in zip(starts, parts, strict=True)) - base, CODE)
        for s, c in zip(starts, parts, strict=True):
            own = np.frombuffer(c, CODE)
            codes[s - base : s - base + len(own)] = own
        return pa.Table.from_batches([work(left["bucket"][0].as_py(), left["pos"].to_numpy(), left["kmer"].to_numpy(), partial.padded_codes(codes), base)])

    return rows.groupBy("bucket").cogroup(near.groupBy("of")).applyInArrow(sort_cogroup, schema)


def chunks_needed(rows: DataFrame, n: int, k: int, reduction: str, size: int) -> DataFrame:
    """(bucket, chunk): the chunks that hold a bucket's blocks and the symbol before each."""
    reach = partial.bucket_gaps(rows, n).withColumn("reach", F.col("l_max") + k if reduction == "gap_rename" else F.lit(n))
    need = rows.select("bucket", F.floor(F.greatest(F.col("pos") - 1, F.lit(0)) / size).alias("a"), "pos").join(reach.select("bucket", "reach"), "bucket")
    need = need.groupBy("bucket", "a").agg(F.max(F.least(F.col("pos") + F.col("reach"), F.lit(n - 1))).alias("z"))
    return need.select("bucket", F.explode(F.sequence("a", F.floor(F.col("z") / size))).alias("chunk")).distinct()


def build(corpus: Corpus, **options) -> DataFrame:
    """(rank, pos, code): suffix array and transform."""
    rows = cut_numbers(suffix_order(corpus, **options))
    counts = {r[0]: r[1] for r in rows.groupBy("bucket").count().collect()}
    at, offsets = 0, {}
    for b in sorted(counts):
        offsets[b] = at
        at += counts[b]
    array = F.array(*(F.lit(offsets.get(b, 0)).cast("long") for b in range(max(counts) + 1)))
    return rows.select((F.get(array, "bucket") + F.col("ord")).alias("rank"), "pos", "code")


def transform(corpus: Corpus, count: int = anchors.TURNS, **options) -> DataFrame:
    """(rank, code) of build alone. What is sorted in turns is kept as the symbols of each bucket, compressed, and no position is."""
    own, sigma = turns(corpus, count, **options), corpus.sigma
    if own is None:
        return cut_numbers(build(corpus, **options).select("rank", "code"))
    spark, parts, sizes = corpus.pieces.sparkSession, None, {}

    def symbols(bucket: int, pos: np.ndarray, first: np.ndarray, before: np.ndarray) -> pa.Table:
        codes = anchors.packed(c=anchors.fewest(before, sigma))
        return pa.table({"bucket": pa.array([bucket], pa.int32()), "rows": pa.array([len(pos)], pa.int64()), "codes": pa.array([codes], pa.binary())})

    for turn in range(own.count):
        part = cut(own.each(turn, symbols, "bucket int, rows long, codes binary"))
        sizes |= {x[0]: x[1] for x in part.select("bucket", "rows").collect()}
        parts = part if parts is None else parts.unionByName(part)
        release(spark, at_once=True)
    at, offsets = 0, {}
    for b in sorted(sizes):
        offsets[b] = at
        at += sizes[b]
    if at != corpus.n:
        raise AssertionError(f"{at} of {corpus.n} suffixes are in the buckets")

    def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b, raw in zip(batch["bucket"].to_pylist(), batch["codes"].to_pylist(), strict=True):
                c = anchors.unpacked(raw)["c"].astype(np.int32)
                yield pa.RecordBatch.from_arrays([pa.array(offsets[b] + np.arange(len(c))), pa.array(c)], ["rank", "code"])

    return parts.select("bucket", "codes").mapInArrow(unpack, BWT)
