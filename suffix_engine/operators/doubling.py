"""Rank doubling: rounds of shift, pair and re-rank over DataFrames, in all the forms that the inventory lists."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from suffix_engine.model import RANKS, Corpus
from suffix_engine.operators import kmers, prefix
from suffix_engine.operators.corpus import text
from suffix_engine.operators.packing import fewest, packed, spread, unpacked
from suffix_engine.session import cut, cut_numbers, release

PAIRINGS = ("join", "union_reduce", "block", "lead")
RERANKS = ("group", "global", "distinct")
#: Pairing and re-ranking of whole rounds that go over arrays instead of rows.
PACKED = (("union_reduce", "global"), ("join", "group"))
#: Ranks in a row of the block form; shifts by whole blocks then move rows and not ranks.
BLOCK = 1 << 14
#: Stands for the rank of what lies past the end.
PAST = -1
#: Suffixes of a group that one task may re-rank; larger groups are sorted by range over many tasks.
MOST_IN_GROUP = 1 << 20
#: Positions in a block of the packed form, pairs in a range of it on average at most, sampled pairs for each range, and the longest text
#: whose pairs are one number each.
PACKED_BLOCK, RANGE, SAMPLED, MOST_PACKED = 1 << 16, 1 << 19, 64, 1 << 31


@dataclass
class Round:
    number: int
    reach: int
    groups: int
    unresolved: int
    rows: int
    seconds: float


@dataclass
class Result:
    ranks: DataFrame
    rounds: list[Round] = field(default_factory=list)


def init_ranks(corpus: Corpus, h0: int = 1) -> DataFrame:
    """Rank by the first h0 symbols: how many suffixes have smaller ones; tied if another suffix has the same."""
    if h0 == 1:
        smaller = F.array(*(F.lit(int(x)) for x in corpus.smaller))
        counts = F.array(*(F.lit(int(x)) for x in corpus.counts))
        return text(corpus).select("pos", F.get(smaller, "code").cast("long").alias("rnk"), (F.get(counts, "code") > 1).alias("tied"))
    keys = kmers.extract(corpus, h0)
    table = prefix.exclusive(keys.groupBy("kmer").agg(F.count(F.lit(1)).alias("cnt")), "cnt", "kmer", out="rnk")
    return keys.join(table, "kmer").select("pos", "rnk", (F.col("cnt") > 1).alias("tied"))


def shift(ranks: DataFrame, h: int) -> DataFrame:
    """The ranks moved h to the front; what would come before the start is dropped."""
    return ranks.select((F.col("pos") - h).alias("pos"), F.col("rnk").alias("r2")).where("pos >= 0")


def pair_by_union(ranks: DataFrame, h: int) -> DataFrame:
    both = ranks.select("pos", F.lit(0).alias("side"), F.col("rnk").alias("r")).unionByName(shift(ranks, h).select("pos", F.lit(1).alias("side"), F.col("r2").alias("r")))
    of = lambda side: F.max(F.when(F.col("side") == side, F.col("r")))
    return both.groupBy("pos").agg(of(0).alias("r1"), F.coalesce(of(1), F.lit(PAST)).cast("long").alias("r2"))


def pair_by_join(own: DataFrame, ranks: DataFrame, h: int) -> DataFrame:
    """Only the ranks of own are paired; ranks has all of them. Own rows go to where the rank they need is, so ranks that lie by pos stay there."""
    there = ranks.select(F.col("pos").alias("_at"), F.col("rnk").alias("r2"))
    asked = own.select("pos", F.col("rnk").alias("r1"), (F.col("pos") + h).alias("_to"))
    return asked.join(there, F.col("_to") == F.col("_at"), "left").select("pos", "r1", F.coalesce("r2", F.lit(PAST)).cast("long").alias("r2"))


def pair_by_lead(ranks: DataFrame, h: int, key: str) -> DataFrame:
    """For many texts of bounded length, each under its own key."""
    own = Window.partitionBy(key).orderBy("pos")
    return ranks.select(key, "pos", F.col("rnk").alias("r1"), F.lead("rnk", h, PAST).over(own).cast("long").alias("r2"))


def pair_by_block(ranks: DataFrame, h: int, block: int = BLOCK) -> DataFrame:
    """Ranks of block positions stand in one row; a shift joins each row with the two that hold its shifted ranks."""

    def gather(table: pa.Table) -> pa.Table:
        b, pos, r = table["b"][0].as_py(), table["pos"].to_numpy(), table["rnk"].to_numpy()
        out = np.full(int(pos.max()) - b * block + 1, PAST, np.int64)
        out[pos - b * block] = r
        return pa.table({"b": pa.array([b], pa.int64()), "r": pa.array([out.tobytes()], pa.binary())})

    rows = cut(ranks.select(F.floor(F.col("pos") / block).alias("b"), "pos", "rnk").groupBy("b").applyInArrow(gather, "b long, r binary"))
    a, rest = divmod(h, block)
    near = rows.select((F.col("b") - a).alias("b"), F.col("r").alias("near"))
    far = rows.select((F.col("b") - a - 1).alias("b"), F.col("r").alias("far"))

    def splice(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b, own, one, two in zip(*(batch[c].to_pylist() for c in ("b", "r", "near", "far")), strict=True):
                r1 = np.frombuffer(own, np.int64)
                one, two = (np.frombuffer(x or b"", np.int64) for x in (one, two))
                r2 = np.full(block, PAST, np.int64)
                head = one[rest:]
                r2[: len(head)] = head
                tail = two[:rest]
                r2[block - rest : block - rest + len(tail)] = tail
                yield pa.RecordBatch.from_arrays([pa.array(b * block + np.arange(len(r1))), pa.array(r1), pa.array(r2[: len(r1)])], ["pos", "r1", "r2"])

    return rows.join(near, "b", "left").join(far, "b", "left").mapInArrow(splice, "pos long, r1 long, r2 long")


def rerank_in_groups(pairs: DataFrame, key: list[str] | None = None) -> DataFrame:
    """A rank counts all that is smaller, so the new one is the old one plus the place within the old group: no sampling, no driver."""
    keys = [*(key or []), "r1"]
    place = F.rank().over(Window.partitionBy(*keys).orderBy("r2"))
    alike = F.count(F.lit(1)).over(Window.partitionBy(*keys, "r2"))
    return pairs.select(*(key or []), "pos", (F.col("r1") + place - 1).alias("rnk"), (alike > 1).alias("tied"))


def rerank_globally(pairs: DataFrame, keep_old: bool = False) -> DataFrame:
    """Range partitions in order, a running rank in each, and the number of pairs in earlier partitions. Equal pairs share a partition."""
    parts = prefix.ranged(pairs, "r1", "r2")
    shared = pairs.sparkSession.sparkContext.broadcast(prefix.partition_offsets(parts, F.lit(1)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        at = shared.value.get(TaskContext.get().partitionId(), 0)
        held = None  # rows of the last pair seen, which may go on
        for batch in batches:
            pos, r1, r2 = (batch[c].to_numpy() for c in ("pos", "r1", "r2"))
            if held is not None:
                pos, r1, r2 = np.r_[held[0], pos], np.r_[held[1], r1], np.r_[held[2], r2]
            new = np.flatnonzero(np.r_[True, (np.diff(r1) != 0) | (np.diff(r2) != 0)]) if len(pos) else np.zeros(1, np.int64)
            last = new[-1]
            held = (pos[last:], r1[last:], r2[last:])
            if last:
                yield _ranked(at, pos[:last], r1[:last], new[:-1], last)
            at += int(last)
        if held is not None and len(held[0]):
            yield _ranked(at, held[0], held[1], np.zeros(1, np.int64), len(held[0]))

    out = parts.mapInArrow(run, f"{RANKS}, r1 long")
    return out if keep_old else out.drop("r1")


def _ranked(at: int, pos: np.ndarray, r1: np.ndarray, first: np.ndarray, n: int) -> pa.RecordBatch:
    size = np.diff(np.r_[first, n])
    return pa.RecordBatch.from_arrays([pa.array(pos), pa.array(at + np.repeat(first, size)), pa.array(np.repeat(size > 1, size)), pa.array(r1)], ["pos", "rnk", "tied", "r1"])


def rerank_distinct(pairs: DataFrame) -> DataFrame:
    """Counts of distinct pairs, their prefix sum, joined back."""
    counts = pairs.groupBy("r1", "r2").agg(F.count(F.lit(1)).alias("cnt"))
    table = prefix.exclusive(counts, "cnt", "r1", "r2", out="rnk")
    # what the counts were dealt by goes before they are joined back
    release(pairs.sparkSession, at_once=True)
    return pairs.join(table, ["r1", "r2"]).select("pos", "rnk", (F.col("cnt") > 1).alias("tied"))


def rerank_mixed(pairs: DataFrame, most: int = MOST_IN_GROUP) -> DataFrame:
    """As rerank_in_groups, without ever holding a large group in one task."""
    sizes = pairs.groupBy("r1").agg(F.count(F.lit(1)).alias("members"))
    large = cut(sizes.where(F.col("members") > most).select(F.col("r1").alias("_r1")))
    if not large.limit(1).count():
        return rerank_in_groups(pairs)
    light = pairs.join(large, F.col("r1") == F.col("_r1"), "left_anti")
    heavy = cut(rerank_globally(pairs.join(large, F.col("r1") == F.col("_r1"), "left_semi"), keep_old=True))
    first = heavy.groupBy("r1").agg(F.min("rnk").alias("first"))
    placed = heavy.join(first, "r1").select("pos", (F.col("r1") + F.col("rnk") - F.col("first")).alias("rnk"), "tied")
    return rerank_in_groups(light).unionByName(placed)


def with_new(ranks: DataFrame, new: DataFrame) -> DataFrame:
    """The ranks with those that are new put in; ranks that lie by pos stay where they are."""
    own = new.select(F.col("pos").alias("_pos"), F.col("rnk").alias("_rnk"), F.col("tied").alias("_tied"))
    return ranks.join(own, F.col("pos") == F.col("_pos"), "left").select("pos", F.coalesce("_rnk", "rnk").alias("rnk"), F.coalesce("_tied", "tied").alias("tied"))


def one_round(ranks: DataFrame, h: int, pairing: str = "join", rerank: str = "group", active_only: bool = False) -> DataFrame:
    own = ranks.where("tied") if active_only else ranks
    if pairing == "union_reduce":
        pairs = pair_by_union(ranks, h)
        pairs = pairs.join(own.select("pos"), "pos", "left_semi") if active_only else pairs
    elif pairing == "block":
        pairs = pair_by_block(ranks, h)
        pairs = pairs.join(own.select("pos"), "pos", "left_semi") if active_only else pairs
    elif pairing == "join":
        pairs = pair_by_join(own, ranks, h)
    else:
        raise ValueError(f"no pairing {pairing!r} for one text")
    if rerank == "group":
        new = rerank_mixed(cut_numbers(pairs))
    elif active_only:
        raise ValueError("only re-ranking in groups keeps ranks that it doesn't see")
    else:
        # the ranks of distinct pairs are joined back, so what is costly to pair is paired once
        new = rerank_globally(pairs) if rerank == "global" else rerank_distinct(pairs if pairing == "block" else cut_numbers(pairs))
    return new.unionByName(ranks.where("not tied")) if active_only else new


def build(corpus: Corpus, pairing: str = "join", rerank: str = "group", rounds: str | int = "early_stop", h0: int | None = None, active_only: bool | None = None) -> Result:
    """Inverse suffix array (pos, rnk) by doubling.

    rounds: "paper" runs a fixed number, ceil(log2 n) + 1, as the published loop does; "early_stop" ends when no rank is shared; a number
    ends after that many. h0: symbols that the first ranks take in (None: as many as fit in a key; 1: as published).
    Each round is written to the shared folder, so a lost executor costs one round at most. PACKED forms over all
    ranks go by packed blocks (build_packed).
    """
    h = kmers.widest(corpus) if h0 is None else h0
    active = (rerank == "group" and pairing == "join") if active_only is None else active_only
    if (pairing, rerank) in PACKED and not active and corpus.n < MOST_PACKED:
        return build_packed(corpus, rounds, h, pairing, rerank)
    began = time.perf_counter()
    ranks = cut_numbers(init_ranks(corpus, h))
    history = [_measured(ranks, 0, h, began)]
    most = _most(corpus.n, rounds)
    for number in range(1, most + 1):
        if rounds == "early_stop" and not history[-1].unresolved:
            break
        began = time.perf_counter()
        ranks = cut_numbers(one_round(ranks, h, pairing, rerank, active))
        # only now does nothing hold the round's own plan any more
        release(corpus.pieces.sparkSession, at_once=True)
        h *= 2
        history.append(_measured(ranks, number, h, began))
    return Result(ranks.select("pos", "rnk"), history)


def _most(n: int, rounds: str | int) -> int:
    return int(np.ceil(np.log2(max(n, 2)))) + 1 if rounds in ("paper", "early_stop") else int(rounds)


def build_packed(corpus: Corpus, rounds: str | int, h: int, pairing: str = "union_reduce", rerank: str = "global", block: int | None = None, ranges: int | None = None) -> Result:
    """build over arrays: a row is a block of positions, not one.

    A block's own ranks and the shifted ones that fall into it are tagged, united and reduced to pairs, or joined. Its distinct pairs and their counts are
    dealt to ranges in order (by splitters from a sample) and ranked there by running counts: "global" adds the numbers of pairs in earlier ranges, "group"
    keeps old groups in one range and adds the place within the group to the old rank. Each block is answered. Every pair of every round is
    sorted; a pair that is frequent goes once from each block, so no range is long.
    """
    spark, n = corpus.pieces.sparkSession, corpus.n
    block = block or PACKED_BLOCK
    ranges = ranges or max(2 * spark.sparkContext.defaultParallelism, -(-n // RANGE))
    salts, blocks, many = spread(spark, ranges), -(-n // block), np.int64(n + 1)
    sampled = max(1, -(-SAMPLED * ranges // blocks))
    began = time.perf_counter()

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Ranks of positions in any order as pieces of blocks; many rows at a time."""
        held, rows = [], 0

        def flush() -> pa.RecordBatch:
            pos, rank = (np.concatenate(x) for x in zip(*held, strict=True))
            held.clear()
            if (pos[1:] < pos[:-1]).any():
                order = np.argsort(pos)
                pos, rank = pos[order], rank[order]
            first = np.flatnonzero(np.r_[True, np.diff(pos // block) != 0])
            parts = [packed(at=np.diff(pos[i:j] % block, prepend=0).astype(np.uint32), r=fewest(rank[i:j], n)) for i, j in zip(first, np.r_[first[1:], len(pos)], strict=True)]
            return pa.RecordBatch.from_arrays([pa.array(pos[first] // block), pa.array(parts, pa.binary())], ["b", "batch"])

        for batch in batches:
            held.append((batch["pos"].to_numpy(), batch["rnk"].to_numpy()))
            rows += batch.num_rows
            if rows >= 1 << 18:
                yield flush()
                rows = 0
        if rows:
            yield flush()

    def gather(table: pa.Table) -> pa.Table:
        parts = [unpacked(x) for x in table["batch"].to_pylist()]
        out = np.empty(sum(len(p["at"]) for p in parts), np.int64)
        for p in parts:
            out[np.cumsum(p["at"].astype(np.int64))] = p["r"]
        return pa.table({"b": table["b"][:1], "batch": pa.array([packed(r=fewest(out, n))], pa.binary())})

    def tag(h: int) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                rows = []
                for b, raw in zip(batch["b"].to_pylist(), batch["batch"].to_pylist(), strict=True):
                    rows.append((b, 0, 0, raw))
                    own, low = unpacked(raw)["r"], b * block - h  # where the first rank of the block is needed
                    for to in range(max(0, low // block), (low + len(own) - 1) // block + 1):
                        i, j = max(0, to * block - low), min(len(own), (to + 1) * block - low)
                        rows.append((to, 1, low + i - to * block, packed(r=own[i:j])))
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), (pa.int64(), pa.int32(), pa.int64(), pa.binary()), strict=True)] if rows else [pa.array([], t) for t in (pa.int64(), pa.int32(), pa.int64(), pa.binary())], ["b", "side", "at", "batch"])

        return run

    schema = "b long, pairs binary, own binary, sample binary"

    def reduce(table: pa.Table) -> pa.Table:
        b, shifted = table["b"][0].as_py(), []
        for side, at, raw in zip(*(table[c].to_pylist() for c in ("side", "at", "batch")), strict=True):
            if side == 0:
                first = unpacked(raw)["r"].astype(np.int64)
            else:
                shifted.append((at, unpacked(raw)["r"]))
        second = np.full(len(first), PAST, np.int64)
        for at, r in shifted:
            second[at : at + len(r)] = r
        return pa.Table.from_batches([paired(b, first, second)])

    def paired(b: int, first: np.ndarray, second: np.ndarray) -> pa.RecordBatch:
        pairs, own, counts = np.unique(first * many + (second + 1), return_inverse=True, return_counts=True)
        sample = np.random.default_rng(b).choice(pairs, sampled, p=counts / len(own))
        columns = [packed(pair=pairs, count=fewest(counts, block + 1)), packed(i=fewest(own, block)), sample.tobytes()]
        return pa.RecordBatch.from_arrays([pa.array([b], pa.int64()), *(pa.array([x], pa.binary()) for x in columns)], ["b", "pairs", "own", "sample"])

    def joined(state: DataFrame, h: int) -> DataFrame:
        a, rest = divmod(h, block)
        near = state.select((F.col("b") - a).alias("b"), F.col("batch").alias("near"))
        far = state.select((F.col("b") - a - 1).alias("b"), F.col("batch").alias("far"))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for b, own, one, two in zip(*(batch[c].to_pylist() for c in ("b", "batch", "near", "far")), strict=True):
                    first = unpacked(own)["r"].astype(np.int64)
                    second = np.full(len(first), PAST, np.int64)
                    for at, raw, begin in ((0, one, rest), (block - rest, two, 0)):
                        if raw is not None and at < len(first):
                            r = unpacked(raw)["r"][begin : begin + (rest if at else block)][: len(first) - at]
                            second[at : at + len(r)] = r
                    yield paired(b, first, second)

        return state.join(near, "b", "left").join(far, "b", "left").mapInArrow(run, schema)

    def deal(borders: np.ndarray) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                rows = []
                for b, raw in zip(batch["b"].to_pylist(), batch["pairs"].to_pylist(), strict=True):
                    c = unpacked(raw)
                    at = np.r_[0, np.searchsorted(c["pair"], borders), len(c["pair"])]
                    rows += [(p, salts[p], b, packed(pair=np.diff(c["pair"][at[p] : at[p + 1]], prepend=0), count=c["count"][at[p] : at[p + 1]])) for p in range(len(at) - 1) if at[p] < at[p + 1]]
                yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), (pa.int32(), pa.int32(), pa.int64(), pa.binary()), strict=True)] if rows else [pa.array([], t) for t in (pa.int32(), pa.int32(), pa.int64(), pa.binary())], ["p", "salt", "b", "batch"])

        return run

    def rank(table: pa.Table) -> pa.Table:
        parts = [unpacked(x) for x in table["batch"].to_pylist()]
        pair, count = np.concatenate([np.cumsum(p["pair"]) for p in parts]), np.concatenate([p["count"] for p in parts]).astype(np.int64)
        order = np.argsort(pair, kind="stable")
        new = np.flatnonzero(np.r_[True, np.diff(pair[order]) != 0])
        members = np.add.reduceat(count[order], new)
        place = np.cumsum(members) - members
        if rerank == "group":
            group = pair[order][new] // many
            first = np.flatnonzero(np.r_[True, np.diff(group) != 0])
            place += group - np.repeat(place[first], np.diff(np.r_[first, len(group)]))
        out = np.empty(len(pair), np.int64)
        out[order] = np.repeat(place, np.diff(np.r_[new, len(pair)]))
        ends, zeros, tied = np.cumsum([len(p["pair"]) for p in parts]), [0] * (len(parts) - 1), int(members[members > 1].sum())
        answers = [packed(r=fewest(out[z - len(p["pair"]) : z], n)) for p, z in zip(parts, ends, strict=True)]
        numbers = {k: pa.array([x, *zeros], pa.int64()) for k, x in (("rows", int(members.sum())), ("tied", tied), ("groups", len(members)))}
        return pa.table({"p": table["p"], "b": table["b"], **numbers, "batch": pa.array(answers, pa.binary())})

    def merge(before: dict[int, int]) -> Callable[[pa.Table, pa.Table], pa.Table]:
        def run(left: pa.Table, right: pa.Table) -> pa.Table:
            answers = sorted(zip(right["p"].to_pylist(), right["batch"].to_pylist()))
            ranks = np.concatenate([unpacked(raw)["r"].astype(np.int64) + before[p] for p, raw in answers])
            return pa.table({"b": left["b"], "batch": pa.array([packed(r=fewest(ranks[unpacked(left["own"][0].as_py())["i"]], n))], pa.binary())})

        return run

    def unpack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b, raw in zip(batch["b"].to_pylist(), batch["batch"].to_pylist(), strict=True):
                r = unpacked(raw)["r"].astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(b * block + np.arange(len(r))), pa.array(r)], ["pos", "rnk"])

    first = init_ranks(corpus, h)
    state = cut(first.select("pos", "rnk").mapInArrow(pieces, "b long, batch binary").groupBy("b").applyInArrow(gather, "b long, batch binary"))
    tied = state.mapInArrow(unpack, "pos long, rnk long").groupBy("rnk").agg(F.count(F.lit(1)).alias("members"))
    groups, left = tied.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.when(F.col("members") > 1, F.col("members"))), F.lit(0))).first()
    history = [Round(0, h, groups, left, n, time.perf_counter() - began)]
    for number in range(1, _most(n, rounds) + 1):
        if rounds == "early_stop" and not history[-1].unresolved:
            break
        began = time.perf_counter()
        if pairing == "join":
            pairs = cut(joined(state, h))
        else:
            pairs = cut(state.mapInArrow(tag(h), "b long, side int, at long, batch binary").groupBy("b").applyInArrow(reduce, schema))
        sample = np.sort(np.concatenate([np.frombuffer(x[0], np.int64) for x in pairs.select("sample").collect()]))
        sample = sample[np.arange(1, ranges) * len(sample) // ranges]
        borders = np.unique(sample // many * many if rerank == "group" else sample)
        dealt = pairs.select("b", "pairs").mapInArrow(deal(borders), "p int, salt int, b long, batch binary").repartition(ranges, "salt")
        ranked = cut(dealt.groupBy("salt").applyInArrow(rank, "p int, b long, rows long, tied long, groups long, batch binary"))
        sums, before, at = {x[0]: x[1:] for x in ranked.groupBy("p").agg(F.sum("rows"), F.sum("tied"), F.sum("groups")).collect()}, {}, 0
        for p in sorted(sums):
            before[p] = at if rerank == "global" else 0
            at += sums[p][0]
        answers = ranked.select("p", "b", "batch").groupBy("b")
        state = cut(pairs.select("b", "own").groupBy("b").cogroup(answers).applyInArrow(merge(before), "b long, batch binary"))
        del pairs, dealt, ranked, answers
        release(spark, at_once=True)
        h *= 2
        history.append(Round(number, h, sum(x[2] for x in sums.values()), sum(x[1] for x in sums.values()), at, time.perf_counter() - began))
    return Result(state.mapInArrow(unpack, "pos long, rnk long"), history)


def _measured(ranks: DataFrame, number: int, reach: int, began: float, n: int | None = None) -> Round:
    """Groups are distinct ranks; those that aren't tied are a group each. n: of all ranks, if only those that were tied are given."""
    rows, unresolved, shared = ranks.agg(F.count(F.lit(1)), F.sum(F.col("tied").cast("long")), F.count_distinct(F.when(F.col("tied"), F.col("rnk")))).first()
    rows = n or rows
    groups = rows - (unresolved or 0) + shared
    return Round(number, reach, groups, unresolved or 0, rows, time.perf_counter() - began)


def rounds_table(spark, result: Result) -> DataFrame:
    return spark.createDataFrame([(r.number, r.reach, r.groups, r.unresolved, r.rows, r.seconds) for r in result.rounds], "round int, reach long, groups long, unresolved long, rows long, seconds double")


def build_rows(rows: DataFrame, key: str, text_: str, order: str = "smallest", longest: int | None = None) -> DataFrame:
    """(key, pos, code, rnk): the inverse suffix array of each row's text with a terminator of its own, all rows at once, relationally.

    code is the code point, -1 or 2**31 - 1 for the terminator. Texts of bounded length: a window holds one text.
    """
    end = -1 if order == "smallest" else 2**31 - 1
    symbols = F.array_append(F.transform(F.filter(F.split(text_, ""), lambda s: s != ""), lambda s: F.ascii(s)), F.lit(end))
    base = cut(rows.where(F.col(text_).isNotNull()).select(F.col(key), F.posexplode(symbols).alias("pos", "code")).withColumn("pos", F.col("pos").cast("long")))
    ranks = cut(base.select(key, "pos", (F.rank().over(Window.partitionBy(key).orderBy("code")) - 1).cast("long").alias("rnk"), (F.count(F.lit(1)).over(Window.partitionBy(key, "code")) > 1).alias("tied")))
    h = 1
    while ranks.where("tied").limit(1).count():
        ranks = cut(rerank_in_groups(pair_by_lead(ranks, h, key), [key]))
        h *= 2
    return base.join(ranks.select(key, "pos", "rnk"), [key, "pos"])
