"""The transform from a suffix array, for one text or for each row, and back."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from suffix_engine.model import CODE, TERMINATOR, TEXT, Corpus
from suffix_engine.operators import doubling, prefix
from suffix_engine.operators.corpus import text
from suffix_engine.session import cut

#: Rows up to which a transform may be broadcast to be inverted; a worker then holds ten bytes for each.
BROADCAST_ROWS = 1 << 26
#: One row in so many begins a walk, and how many walks go on side by side in a task.
STEP, WALKS = 1 << 10, 1 << 11


def from_ranks(ranks: DataFrame, corpus: Corpus) -> DataFrame:
    """(rank, code): the symbol before each suffix, the last one before the first; one equi-join on positions."""
    before = text(corpus).select(F.pmod(F.col("pos") + 1, F.lit(corpus.n)).alias("pos"), "code")
    return ranks.join(before, "pos").select(F.col("rnk").alias("rank"), "code")


def from_suffix_array(sa: DataFrame, corpus: Corpus) -> DataFrame:
    return from_ranks(sa.select("pos", F.col("rank").alias("rnk")), corpus)


def primary_index(ranks: DataFrame) -> int:
    """The 0-based row of the text itself among its sorted rotations."""
    return ranks.where("pos = 0").first()["rnk"]


def symbols(bwt: DataFrame, corpus: Corpus) -> DataFrame:
    """(rank, symbol)."""
    return bwt.select("rank", F.get(F.array(*(F.lit(s) for s in corpus.symbols)), "code").alias("symbol"))


def as_string(bwt: DataFrame, corpus: Corpus, most: int = 1 << 20) -> str:
    """For texts within a bound."""
    if corpus.n > most:
        raise ValueError("too long for one string")
    return "".join(r.symbol for r in symbols(bwt, corpus).orderBy("rank").collect())


def last_to_first(bwt: DataFrame, corpus: Corpus) -> DataFrame:
    """(rank, code, next): next is the rank of the suffix that starts one symbol earlier."""
    counts = bwt.groupBy("code").agg(F.count(F.lit(1)).alias("cnt"))
    if counts.count() != sum(1 for c in corpus.counts if c):
        raise ValueError("not a transform of this corpus")
    return prefix.exclusive(bwt, None, "code", "rank", out="next").select("rank", "code", "next")


def invert(bwt: DataFrame, corpus: Corpus, most: int = BROADCAST_ROWS, step: int = STEP) -> DataFrame:
    """(pos, code): the text again. Up to most rows the transform is broadcast and walked in many places at once; beyond it, by jumps. The
    rows are the same."""
    return invert_by_walks(bwt, corpus, step) if corpus.n <= most else invert_by_jumps(bwt, corpus)


def invert_by_walks(bwt: DataFrame, corpus: Corpus, step: int = STEP) -> DataFrame:
    """(pos, code): from one row in step (by a hash, so that no text sets them close together) each walk goes back through the text to the next
    such row. Every row is in one walk, so all walks together are as long as the text; where they belong follows from their ends, which alone
    come to the driver."""
    spark, n, end = bwt.sparkSession, corpus.n, corpus.terminator
    codes = _codes_by_rank(bwt, corpus)
    whole, tasks = int(np.flatnonzero(codes == end)[0]), max(1, min(spark.sparkContext.defaultParallelism, n >> 16))
    shared = spark.sparkContext.broadcast(codes)
    del codes

    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = [i for batch in batches for i in batch["id"].to_pylist()]
        back = _back(shared.value) if own else None
        for i in own:
            for a in range(i * n // tasks, (i + 1) * n // tasks, 1 << 20):
                rows = np.arange(a, min(a + (1 << 20), (i + 1) * n // tasks))
                starts = rows[_starts(rows, step) | (rows == whole)]
                for j in range(0, len(starts), WALKS):
                    yield _walked(shared.value, back, starts[j : j + WALKS], whole, step)

    walks = cut(spark.range(0, tasks, 1, tasks).mapInArrow(walk, "start long, next long, codes binary"))
    ends = {r[0]: (r[1], r[2]) for r in walks.select("start", "next", F.octet_length("codes")).collect()}
    at, row, offset = {}, whole, 0
    while row not in at:
        at[row] = offset
        row, size = ends[row]
        offset += size // CODE.itemsize
    if offset != n:
        raise ValueError("not a transform of one text")
    offsets = spark.sparkContext.broadcast(at)

    def place(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start, raw in zip(batch["start"].to_pylist(), batch["codes"].to_pylist(), strict=True):
                c = np.frombuffer(raw, CODE)
                yield pa.RecordBatch.from_arrays([pa.array(n - 1 - offsets.value[start] - np.arange(len(c))), pa.array(c.astype(np.int32))], ["pos", "code"])

    return walks.select("start", "codes").mapInArrow(place, TEXT)


def _codes_by_rank(bwt: DataFrame, corpus: Corpus) -> np.ndarray:
    """The transform as one array on the driver, packed on the way."""

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                yield pa.RecordBatch.from_arrays([pa.array([batch["rank"].to_numpy().tobytes()], pa.binary()), pa.array([batch["code"].to_numpy().astype(CODE).tobytes()], pa.binary())], ["ranks", "codes"])

    out, rows = np.zeros(corpus.n, CODE), 0
    for ranks, raw in bwt.select(F.col("rank").cast("long").alias("rank"), F.col("code").cast("int").alias("code")).mapInArrow(pack, "ranks binary, codes binary").toLocalIterator():
        at = np.frombuffer(ranks, np.int64)
        if at.min() < 0 or at.max() >= corpus.n:
            raise ValueError("not a transform of this corpus")
        out[at] = np.frombuffer(raw, CODE)
        rows += len(at)
    if rows != corpus.n or not np.array_equal(np.bincount(out, minlength=corpus.sigma), corpus.counts):
        raise ValueError("not a transform of this corpus")
    return out


def _back(codes: np.ndarray) -> np.ndarray:
    """For each row, that of the suffix one symbol longer; symbol by symbol, so that little is held beside the result."""
    out, at = np.empty(len(codes), np.uint32 if len(codes) < 1 << 32 else np.int64), 0
    for c in np.flatnonzero(np.bincount(codes)):
        own = np.flatnonzero(codes == c)
        out[own] = np.arange(at, at + len(own))
        at += len(own)
    return out


def _starts(rows: np.ndarray, step: int) -> np.ndarray:
    return (rows.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(32) < np.uint64((1 << 32) // step)


def _walked(codes: np.ndarray, back: np.ndarray, starts: np.ndarray, whole: int, step: int) -> pa.RecordBatch:
    """The symbols from each start to the next one on its way, in the order met."""
    walk, row, ends = np.arange(len(starts)), starts, np.empty(len(starts), np.int64)
    walks, met = [], []
    while len(walk):
        walks.append(walk)
        met.append(codes[row])
        row = back[row].astype(np.int64)
        over = _starts(row, step) | (row == whole)
        if over.any():
            ends[walk[over]] = row[over]
            walk, row = walk[~over], row[~over]
    walks, met = np.concatenate(walks), np.concatenate(met)
    met = met[np.argsort(walks, kind="stable")].tobytes()
    bounds = np.r_[0, np.cumsum(np.bincount(walks, minlength=len(starts)))] * CODE.itemsize
    return pa.RecordBatch.from_arrays([pa.array(starts), pa.array(ends), pa.array([met[a:z] for a, z in zip(bounds[:-1], bounds[1:], strict=True)], pa.binary())], ["start", "next", "codes"])


def invert_by_jumps(bwt: DataFrame, corpus: Corpus) -> DataFrame:
    """(pos, code): the text again, by jumps of doubling length towards the row of the whole text; log2 n joins and no sequential walk.

    The row whose symbol is the terminator is that of the whole text, so nothing else but the transform is needed.
    """
    lf = cut(last_to_first(bwt, corpus))
    end = F.col("code") == corpus.terminator
    jumps = cut(lf.select("rank", F.when(end, F.col("rank")).otherwise(F.col("next")).alias("next"), F.when(end, 0).otherwise(1).cast("long").alias("dist")))
    for _ in range(int(np.ceil(np.log2(max(corpus.n, 2))))):
        ahead = jumps.select(F.col("rank").alias("next"), F.col("next").alias("_n"), F.col("dist").alias("_d"))
        jumps = cut(jumps.join(ahead, "next").select("rank", F.col("_n").alias("next"), (F.col("dist") + F.col("_d")).alias("dist")))
    return jumps.join(lf.select("rank", "code"), "rank").select(F.pmod(F.col("dist") - 1, F.lit(corpus.n)).alias("pos"), "code")


def per_row(rows: DataFrame, key: str, text_: str, order: str = "smallest") -> DataFrame:
    """(key, bwt, primary): each row's own transform, by doubling inside the row. Null texts have no row; an empty one gives the terminator and 0."""
    out = pa.schema([("key", pa.string()), ("bwt", pa.string()), ("primary", pa.int64())])
    kind = dict(rows.dtypes)[key]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = [encode(t, order) for t in batch["t"].to_pylist()]
            yield pa.RecordBatch.from_arrays([batch["key"], pa.array([g[0] for g in got], pa.string()), pa.array([g[1] for g in got], pa.int64())], out.names)

    return rows.where(F.col(text_).isNotNull()).select(F.col(key).alias("key"), F.col(text_).alias("t")).mapInArrow(run, f"key {kind}, bwt string, primary long").withColumnRenamed("key", key)


def per_row_relational(rows: DataFrame, key: str, text_: str, order: str = "smallest") -> DataFrame:
    """The same by windows and joins alone (doubling.build_rows)."""
    ranks = doubling.build_rows(rows, key, text_, order)
    n = ranks.groupBy(key).agg(F.count(F.lit(1)).alias("n"))
    before = ranks.join(n, key).select(key, F.pmod(F.col("pos") + 1, F.col("n")).alias("pos"), F.when((F.col("code") < 0) | (F.col("code") == 2**31 - 1), F.lit(TERMINATOR)).otherwise(F.expr("decode(unhex(lpad(hex(code), 8, '0')), 'UTF-32')")).alias("s"))
    joined = ranks.select(key, "pos", "rnk").join(before, [key, "pos"])
    text_of = F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("rnk", "s"))), lambda x: x["s"]), "")
    return joined.groupBy(key).agg(text_of.alias("bwt"), F.max(F.when(F.col("pos") == 0, F.col("rnk"))).alias("primary"))


def local_ranks(codes: np.ndarray) -> np.ndarray:
    """Ranks of all suffixes of a text with a unique terminator on one machine, by doubling."""
    n, h = len(codes), 1
    rank = np.unique(codes, return_inverse=True)[1].astype(np.int64)
    while True:
        second = np.zeros(n, np.int64)
        if h < n:
            second[:-h] = rank[h:] + 1
        key = rank * (n + 1) + second
        rank = np.unique(key, return_inverse=True)[1].astype(np.int64)
        if len(rank) == 0 or rank.max() == n - 1:
            return rank
        h *= 2


def encode(text_: str, order: str = "smallest") -> tuple[str, int]:
    points = np.frombuffer(text_.encode("utf-32-le"), "<u4").astype(np.int64)
    codes = np.append(points, -1 if order == "smallest" else 1 << 31)
    rank = local_ranks(codes)
    out = np.empty(len(codes), np.int64)
    out[rank] = np.roll(codes, 1)
    return "".join(TERMINATOR if c in (-1, 1 << 31) else chr(c) for c in out), int(rank[0])


def decode(bwt: str, primary: int, order: str = "smallest") -> str:
    points = np.frombuffer(bwt.encode("utf-32-le"), "<u4").astype(np.int64)
    codes = points.copy()
    codes[primary] = -1 if order == "smallest" else 1 << 31
    lf = np.empty(len(codes), np.int64)
    lf[np.argsort(codes, kind="stable")] = np.arange(len(codes))
    out, row = [], int(lf[primary])
    for _ in range(len(codes) - 1):
        out.append(chr(points[row]))
        row = int(lf[row])
    return "".join(reversed(out))
