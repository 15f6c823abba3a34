"""Full-text index over the transform: symbol ranks at block borders, backward search, location by sampled positions."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from suffix_engine.model import CODE, Corpus
from suffix_engine.operators import prefix
from suffix_engine.session import cut

BLOCK, SAMPLE = 1 << 12, 32
#: Symbols up to which the whole index may be broadcast; beyond it searches go by joins.
BROADCAST_SYMBOLS = 1 << 26


@dataclass
class Index:
    corpus: Corpus
    blocks: DataFrame  # (block, codes): the transform, by blocks of ranks
    before: DataFrame  # (block, code, before) of every code and block, and one block more: occurrences of a code ahead of a block
    sampled: DataFrame  # (rank, pos) of every SAMPLE-th position
    block: int
    sample: int


def build(bwt: DataFrame, sa: DataFrame, corpus: Corpus, block: int = BLOCK, sample: int = SAMPLE) -> Index:
    """bwt (rank, code), sa (rank, pos). Block counts per code are summed up in two levels; no task holds more than a block of text."""

    def gather(table: pa.Table) -> pa.Table:
        rank, code = table["rank"].to_numpy(), table["code"].to_numpy()
        return pa.table({"block": table["block"].slice(0, 1), "codes": pa.array([code[np.argsort(rank)].astype(CODE).tobytes()], pa.binary())})

    tagged = bwt.select(F.floor(F.col("rank") / block).alias("block"), "rank", "code")
    blocks = cut(tagged.groupBy("block").applyInArrow(gather, "block long, codes binary"))
    counts = tagged.groupBy("code", "block").agg(F.count(F.lit(1)).alias("cnt"))
    every = F.explode(F.array(*(F.lit(c) for c in range(corpus.sigma)))).alias("code")
    grid = bwt.sparkSession.range(corpus.n // block + 2).select(F.col("id").alias("block"), every)
    summed = prefix.exclusive(grid.join(counts, ["code", "block"], "left").fillna(0, ["cnt"]), "cnt", "code", "block", out="ahead")
    base = F.array(*(F.lit(int(x)) for x in corpus.smaller))
    before = cut(summed.select("block", "code", (F.col("ahead") - F.get(base, "code")).cast("long").alias("before")))
    return Index(corpus, blocks, before, cut(sa.where(F.col("pos") % sample == 0).select("rank", "pos")), block, sample)


class Local:
    """The index in one worker's memory."""

    def __init__(self, index: Index):
        c = index.corpus
        if c.n > BROADCAST_SYMBOLS:
            raise ValueError("over the bound for one worker: use the joined search")
        self.block, self.sample, self.n, self.smaller, self.counts = index.block, index.sample, c.n, c.smaller, c.counts
        self.terminator = c.terminator
        self.code_of = {s: i for i, s in enumerate(c.symbols) if i != c.terminator}
        self.codes = np.zeros(c.n, CODE)
        for b, raw in index.blocks.toLocalIterator():
            own = np.frombuffer(raw, CODE)
            self.codes[b * index.block : b * index.block + len(own)] = own
        edge = np.arange(0, c.n, index.block)
        self.before = np.stack([np.r_[0, np.cumsum(np.add.reduceat(self.codes == s, edge, dtype=np.int64))] for s in range(c.sigma)])
        self.position: dict[int, int] = {}

    def with_positions(self, index: Index) -> Local:
        self.position = {r: p for r, p in index.sampled.toLocalIterator()}
        return self

    def occurrences(self, code: int, rank: int) -> int:
        b = rank // self.block
        return int(self.before[code, b]) + int(np.count_nonzero(self.codes[b * self.block : rank] == code))

    def step(self, lo: int, hi: int, code: int) -> tuple[int, int]:
        return int(self.smaller[code]) + self.occurrences(code, lo), int(self.smaller[code]) + self.occurrences(code, hi)

    def count(self, pattern: str) -> tuple[int, int]:
        lo, hi = 0, self.n
        for symbol in reversed(pattern):
            if symbol not in self.code_of or lo >= hi:
                return 0, 0
            lo, hi = self.step(lo, hi, self.code_of[symbol])
        return (lo, hi) if lo < hi else (0, 0)

    def near(self, pattern: str, mismatches: int) -> list[tuple[int, int, int]]:
        """(lo, hi, mismatches) of all words of the pattern's length that differ from it in so many places at most."""
        out, todo = [], [(len(pattern), 0, self.n, 0)]
        while todo:
            i, lo, hi, used = todo.pop()
            if lo >= hi:
                continue
            if not i:
                out.append((lo, hi, used))
                continue
            wanted = self.code_of.get(pattern[i - 1], -1)
            for code in self.code_of.values() if used < mismatches else [wanted]:
                if code >= 0:
                    todo.append((i - 1, *self.step(lo, hi, code), used + (code != wanted)))
        return out

    def locate(self, rank: int) -> int:
        steps = 0
        while rank not in self.position:
            code = int(self.codes[rank])
            rank, steps = int(self.smaller[code]) + self.occurrences(code, rank), steps + 1
        return (self.position[rank] + steps) % self.n


def count(index: Index, patterns: DataFrame) -> DataFrame:
    """(pattern_id, lo, hi, cnt) of patterns (pattern_id, pattern), each searched in one worker, or by joins if the index is too large for
    one. Empty patterns match all suffixes."""
    if index.corpus.n > BROADCAST_SYMBOLS:
        rows = cut(patterns.select(F.col("pattern_id").cast("long").alias("_id"), "pattern", F.monotonically_increasing_id().alias("pattern_id")))
        return count_joined(index, rows).join(rows, "pattern_id").select(F.col("_id").alias("pattern_id"), "lo", "hi", "cnt")
    shared = patterns.sparkSession.sparkContext.broadcast(Local(index))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            got = [shared.value.count(p or "") for p in batch["pattern"].to_pylist()]
            lo, hi = (pa.array([g[i] for g in got], pa.int64()) for i in (0, 1))
            yield pa.RecordBatch.from_arrays([batch["pattern_id"], lo, hi, pa.array([b - a for a, b in got], pa.int64())], ["pattern_id", "lo", "hi", "cnt"])

    return patterns.select(F.col("pattern_id").cast("long").alias("pattern_id"), "pattern").mapInArrow(run, "pattern_id long, lo long, hi long, cnt long")


def _coded(index: Index, pattern: str):
    """The codes of a pattern's symbols from the last one on, -1 for symbols that the text lacks."""
    c = index.corpus
    code_of = F.create_map(*(x for i, s in enumerate(c.symbols) if i != c.terminator for x in (F.lit(s), F.lit(i))))
    return F.transform(F.reverse(F.filter(F.split(pattern, ""), lambda s: s != "")), lambda s: F.coalesce(F.try_element_at(code_of, s), F.lit(-1)))


def _bodies(index: Index) -> DataFrame:
    return index.blocks.select(F.col("block").alias("_b"), F.col("codes").alias("body"))


def _stepped(index: Index, asked: DataFrame) -> DataFrame:
    """(key, side, rank) one step back from asked (key, side, code, rank), each rank looked up by equi-joins with the blocks."""
    block, smaller = index.block, F.array(*(F.lit(int(x)) for x in index.corpus.smaller))

    def counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            inside = [int(np.count_nonzero(np.frombuffer(raw or b"", CODE)[:k] == code)) for raw, k, code in zip(batch["body"].to_pylist(), batch["k"].to_pylist(), batch["code"].to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch["key"], batch["side"], batch["block"], batch["code"], pa.array(inside, pa.int64())], ["key", "side", "block", "code", "inside"])

    ahead = index.before.select(F.col("block").alias("_at"), F.col("code").alias("_c"), "before")
    placed = asked.select("key", "side", "code", F.floor(F.col("rank") / block).alias("block"), F.pmod("rank", F.lit(block)).cast("int").alias("k"))
    inside = placed.join(_bodies(index), F.col("block") == F.col("_b"), "left").mapInArrow(counted, "key long, side int, block long, code int, inside long")
    joined = inside.join(ahead, (F.col("code") == F.col("_c")) & (F.col("block") == F.col("_at")), "left")
    own = F.coalesce(F.get(smaller, F.when(F.col("code") >= 0, F.col("code"))), F.lit(0))
    return joined.select("key", "side", (F.col("inside") + F.coalesce("before", F.lit(0)) + own).alias("rank"))


def _sides(index: Index, asked: DataFrame) -> DataFrame:
    """(key, _lo, _hi) of intervals asked (key, code, lo, hi)."""
    place = _stepped(index, asked.select("key", "code", F.posexplode(F.array("lo", "hi")).alias("side", "rank")))
    return place.groupBy("key").agg(F.max(F.when(F.col("side") == 0, F.col("rank"))).alias("_lo"), F.max(F.when(F.col("side") == 1, F.col("rank"))).alias("_hi"))


def count_joined(index: Index, patterns: DataFrame) -> DataFrame:
    """The same for indexes of any size: one symbol of all patterns a round, two ranks each looked up by equi-joins with the blocks."""
    state = cut(patterns.select(F.col("pattern_id").cast("long").alias("pattern_id"), _coded(index, "pattern").alias("codes"), F.lit(0).cast("long").alias("lo"), F.lit(index.corpus.n).cast("long").alias("hi")))
    longest = state.agg(F.max(F.size("codes"))).first()[0] or 0
    for i in range(longest):
        code = F.get("codes", F.lit(i))
        live = state.where((F.size("codes") > i) & (F.col("lo") < F.col("hi")))
        sides = _sides(index, live.select(F.col("pattern_id").alias("key"), code.alias("code"), "lo", "hi"))
        next_ = state.join(sides.withColumnRenamed("key", "pattern_id"), "pattern_id", "left")
        unknown = (F.size("codes") > i) & (F.coalesce(code, F.lit(0)) < 0)
        state = cut(next_.select("pattern_id", "codes", F.when(unknown, 0).otherwise(F.coalesce("_lo", "lo")).cast("long").alias("lo"), F.when(unknown, 0).otherwise(F.coalesce("_hi", "hi")).cast("long").alias("hi")))
    found = F.col("lo") < F.col("hi")
    return state.select("pattern_id", F.when(found, F.col("lo")).otherwise(0).cast("long").alias("lo"), F.when(found, F.col("hi")).otherwise(0).cast("long").alias("hi"), F.when(found, F.col("hi") - F.col("lo")).otherwise(0).cast("long").alias("cnt"))


def locate_joined(index: Index, intervals: DataFrame) -> DataFrame:
    """locate for indexes of any size: all ranks go back a position a round, until each is at a sampled one."""

    def symbol(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            codes = [int(np.frombuffer(raw, CODE)[k]) for raw, k in zip(batch["body"].to_pylist(), batch["k"].to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch["key"], batch["rank"], pa.array(codes, pa.int32())], ["key", "rank", "code"])

    sampled = index.sampled.select(F.col("rank").alias("_r"), "pos")
    ranks = intervals.where("hi > lo").select("pattern_id", F.explode(F.sequence(F.col("lo"), F.col("hi") - 1)).alias("rank"))
    state, out = cut(ranks.select("pattern_id", "rank", F.monotonically_increasing_id().alias("key"))), None
    for steps in range(index.sample):
        met = cut(state.join(sampled, F.col("rank") == F.col("_r"), "left").drop("_r"))
        hits = met.where("pos is not null").select("pattern_id", F.pmod(F.col("pos") + steps, F.lit(index.corpus.n)).cast("long").alias("pos"))
        out = hits if out is None else out.unionByName(hits)
        rest = met.where("pos is null")
        if rest.isEmpty():
            break
        placed = rest.select("key", "rank", F.floor(F.col("rank") / index.block).alias("_at"), F.pmod("rank", F.lit(index.block)).cast("int").alias("k"))
        coded = placed.join(_bodies(index), F.col("_at") == F.col("_b")).select("key", "rank", "k", "body").mapInArrow(symbol, "key long, rank long, code int")
        back = _stepped(index, coded.select("key", F.lit(0).alias("side"), "code", "rank"))
        state = cut(rest.select("pattern_id", "key").join(back, "key").select("pattern_id", "rank", "key"))
    return out


def count_approx_joined(index: Index, patterns: DataFrame, mismatches: int) -> DataFrame:
    """count_approx for indexes of any size: all words that are still near enough go back a symbol a round."""
    c = index.corpus
    every = F.array(*(F.lit(i) for i in range(c.sigma) if i != c.terminator))
    coded = patterns.select(F.col("pattern_id").cast("long").alias("pattern_id"), _coded(index, "pattern").alias("codes"))
    state = cut(coded.select("pattern_id", "codes", F.lit(0).alias("used"), F.lit(0).cast("long").alias("lo"), F.lit(c.n).cast("long").alias("hi")))
    longest = state.agg(F.max(F.size("codes"))).first()[0] or 0
    for i in range(longest):
        wanted = F.get("codes", F.lit(i))
        options = state.where(F.size("codes") > i).withColumn("code", F.explode(F.when(F.col("used") < mismatches, every).otherwise(F.array(wanted)))).where("code >= 0")
        tried = cut(options.withColumn("used", F.col("used") + (F.col("code") != wanted).cast("int")).withColumn("key", F.monotonically_increasing_id()))
        ahead = tried.drop("lo", "hi", "code").join(_sides(index, tried), "key").where("_lo < _hi")
        done = state.where(F.size("codes") <= i)
        state = cut(ahead.select("pattern_id", "codes", "used", F.col("_lo").alias("lo"), F.col("_hi").alias("hi")).unionByName(done))
    return state.groupBy("pattern_id", F.col("used").alias("mismatches")).agg(F.sum(F.col("hi") - F.col("lo")).alias("cnt"))


def locate(index: Index, intervals: DataFrame) -> DataFrame:
    """(pattern_id, pos) for rank intervals (pattern_id, lo, hi): steps back from each rank to the next sampled position."""
    if index.corpus.n > BROADCAST_SYMBOLS:
        return locate_joined(index, intervals)
    shared = intervals.sparkSession.sparkContext.broadcast(Local(index).with_positions(index))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch["pattern_id"], pa.array([shared.value.locate(r) for r in batch["rank"].to_pylist()], pa.int64())], ["pattern_id", "pos"])

    ranks = intervals.where("hi > lo").select("pattern_id", F.explode(F.sequence(F.col("lo"), F.col("hi") - 1)).alias("rank"))
    return ranks.mapInArrow(run, "pattern_id long, pos long")


def count_approx(index: Index, patterns: DataFrame, mismatches: int) -> DataFrame:
    """(pattern_id, mismatches, cnt): occurrences of words that differ in exactly so many places, up to the given number."""
    if index.corpus.n > BROADCAST_SYMBOLS:
        return count_approx_joined(index, patterns, mismatches)
    shared = patterns.sparkSession.sparkContext.broadcast(Local(index))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [(i, used, hi - lo) for i, p in zip(batch["pattern_id"].to_pylist(), batch["pattern"].to_pylist(), strict=True) for lo, hi, used in shared.value.near(p, mismatches)]
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int32()), pa.array([r[2] for r in rows], pa.int64())], ["pattern_id", "mismatches", "cnt"])

    found = patterns.select(F.col("pattern_id").cast("long").alias("pattern_id"), "pattern").mapInArrow(run, "pattern_id long, mismatches int, cnt long")
    return found.groupBy("pattern_id", "mismatches").agg(F.sum("cnt").alias("cnt"))
