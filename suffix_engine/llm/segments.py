"""What the two window operators share: runs of windows with one minimiser, asked about by bucket, answered by bits."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from suffix_engine.llm.blocks import BLOCK_BYTES, Docs, Items, Kernel, block_count, exchange, gathered, mix, numbered, own_columns, portions, range_hashes, spread, text_bytes

#: Bytes of pieces under one minimiser from which on it is avoided; one of so many contents is counted for that, in rounds.
HOT_BYTES, ONE_OF, HOT_ROUNDS = BLOCK_BYTES // 4, 256, 3
#: Bytes of pieces that are marked at once.
BATCH = 1 << 20


@dataclass
class Runs:
    """Runs of window starts of a block. Units are bytes or words; document numbers follow the order of the ids."""

    bytes: np.ndarray  # the buffer that begin and end refer to
    begin: np.ndarray  # of the run's content
    end: np.ndarray
    first: np.ndarray  # unit at which the first window starts
    count: np.ndarray  # of windows
    doc: np.ndarray
    start: np.ndarray  # of the first window in its document, in units
    at: np.ndarray  # byte of the minimiser, from begin
    key: np.ndarray  # hash of the minimiser


@dataclass
class Known:
    """What a block remembers of its items: the item of each run, and the run that holds each item first."""

    runs: Runs
    item: np.ndarray
    holder: np.ndarray


@dataclass
class SegmentKernel(Kernel):
    """A run with equal content goes to its bucket once for each block, under its first holder there.

    The bucket answers with a bit for each window: it is also held by something earlier than that first holder.
    Later holders in the block are covered in any case, so the answer is complete for all of them.
    """

    #: Minimisers that come after all others, sorted.
    avoid: np.ndarray = field(default_factory=lambda: np.zeros(0, np.uint64), kw_only=True)
    #: Whether an occurrence counts as earlier by its document alone.
    by_document = False

    def runs(self, docs: Docs) -> Runs:
        raise NotImplementedError

    def mark(self, data: np.ndarray, begin: np.ndarray, count: np.ndarray, doc: np.ndarray, start: np.ndarray) -> np.ndarray:
        """For the windows of all given distinct pieces, one piece after another: also held by something earlier.

        begin has one more entry than there are pieces; doc are ids; all pieces with one minimiser are given.
        """
        raise NotImplementedError

    def minimiser(self, data: np.ndarray, begin: np.ndarray, at: np.ndarray) -> np.ndarray:
        """A hash of the minimiser of each piece, for grouping in a bucket."""
        raise NotImplementedError

    def may_match(self, data: np.ndarray, begin: np.ndarray, end: np.ndarray, at: np.ndarray, key: np.ndarray) -> np.ndarray:
        """Which of the distinct pieces may share a window with another one, as far as a glance tells: none that does is left out."""
        return shared_keys(key)

    def items(self, docs, n_buckets):
        r = self.runs(docs)
        raw = r.bytes.tobytes()
        number, holder = numbered(raw, r.begin, r.end)
        bucket = (mix(r.key[holder]) % np.uint64(n_buckets)).astype(np.int64)
        # the items of a bucket stand in order of their place: ids and starts then compress well
        rank = np.argsort(bucket, kind="stable")
        place = np.empty(len(rank), np.int64)
        place[rank] = np.arange(len(rank))
        own = holder[rank]
        size = r.end[own] - r.begin[own]
        columns = [r.count[own].astype(np.uint16), r.at[own].astype(np.uint32), docs.ids[r.doc[own]].view(np.uint64), r.start[own].astype(np.uint32)]
        return Items(bucket[rank], columns, size, gathered(raw, r.begin[own], r.end[own])), Known(r, place[number], own)

    def answers(self, items):
        return items.columns[0].astype(np.int64)

    def resolve(self, items):
        count, at, doc, start = items.columns[0].astype(np.int64), items.columns[1].astype(np.int64), items.columns[2].view(np.int64), items.columns[3].astype(np.int64)
        data, begin = items.data, np.r_[0, np.cumsum(items.size)]
        key = self.minimiser(data, begin[:-1], at)
        flags, window = np.zeros(int(count.sum()), np.uint8), np.r_[0, np.cumsum(count)]
        # equal pieces of several blocks: all that come later than the first are covered whole
        some = np.flatnonzero(shared_keys(key))
        order = some[np.lexsort((start[some], doc[some]))]
        raw = data.tobytes()
        number, first = numbered(raw, begin[order], begin[order + 1])
        own = order[first]
        of = own[number]
        later = doc[order] > doc[of] if self.by_document else (doc[order] > doc[of]) | (start[order] > start[of])
        flags[spread(window[order[later]], count[order[later]])] = 1
        many = self.may_match(data, begin[own], begin[own + 1], at[own], key[own])
        left = own[many][np.argsort(key[own[many]], kind="stable")]
        for i, j in _batches(key[left], items.size[left]):
            k = left[i:j]
            got = self.mark(gathered(raw, begin[k], begin[k + 1]), np.r_[0, np.cumsum(items.size[k])], count[k], doc[k], start[k])
            flags[spread(window[k], count[k])] = got
        # what holds for the first of equal pieces holds for one at the same place, too
        same = ~later & (order != of)
        flags[spread(window[order[same]], count[order[same]])] = flags[spread(window[of[same]], count[order[same]])]
        return flags

    def starts(self, docs: Docs, items: Items, known: Known, answers: np.ndarray) -> np.ndarray:
        """The unit of each window start that is to go."""
        r, count = known.runs, items.columns[0].astype(np.int64)
        window = np.r_[0, np.cumsum(count)]
        own = known.holder[known.item]
        id_, id_first = docs.ids[r.doc], docs.ids[r.doc[own]]
        later = id_ > id_first if self.by_document else (id_ > id_first) | (r.start > r.start[own])
        gone = answers[spread(window[known.item], r.count)].astype(bool) | np.repeat(later, r.count)
        return spread(r.first, r.count)[gone]


def shared_keys(key: np.ndarray) -> np.ndarray:
    """Which entries have a key that another one has, too."""
    order = np.argsort(key, kind="stable")
    k = key[order]
    same = np.r_[False, k[1:] == k[:-1]] if len(k) else np.zeros(0, bool)
    out = np.empty(len(k), bool)
    out[order] = same | np.r_[same[1:], False] if len(k) else same
    return out


def _batches(key: np.ndarray, length: np.ndarray) -> Iterator[tuple[int, int]]:
    """Cuts sorted keys into batches of about BATCH bytes, never inside a key; hot keys have been avoided before."""
    edges = np.flatnonzero(np.r_[True, key[1:] != key[:-1], True]) if len(key) else np.zeros(1, np.int64)
    sums = np.r_[0, np.cumsum(length)][edges]
    i = 0
    while i < len(edges) - 1:
        j = max(i + 1, int(np.searchsorted(sums, sums[i] + BATCH, side="right")) - 1)
        yield int(edges[i]), int(edges[j])
        i = j


def merged(starts: np.ndarray, reach: int) -> tuple[np.ndarray, np.ndarray]:
    """The union of [s, s + reach) over sorted starts, as begins and ends of its maximal ranges."""
    if not len(starts):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    cut = np.flatnonzero(np.diff(starts) > reach)
    return starts[np.r_[0, cut + 1]], starts[np.r_[cut, len(starts) - 1]] + reach


def hot_minimisers(docs: DataFrame, kernel: SegmentKernel, hot_bytes: int, one_of: int) -> np.ndarray:
    """Minimisers of pieces with over hot_bytes of different contents, estimated from the one in so many contents with the least hashes.

    The estimate only decides which bucket a window goes to, and never whether it is found. At most text bytes / hot_bytes times the
    few-fold overlap of pieces are over the bound: 8 bytes come to the driver for each 4 MB of a corpus at the very worst.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (part for whole in batches for part in portions(whole, "text", BLOCK_BYTES // 4)):
            r = kernel.runs(Docs(pa.Table.from_batches([batch])))
            # the content's hash need not be exact here: its ends, its middle and its length
            ends = [range_hashes(r.bytes, a, a + 8) for a in (r.begin, (r.begin + r.end) // 2 - 4, r.end - 8)]
            content = mix(ends[0] * np.uint64(3) + ends[1] * np.uint64(5) + ends[2] * np.uint64(7) + (r.end - r.begin).astype(np.uint64))
            own = np.flatnonzero(content % np.uint64(one_of) == 0)
            both = np.unique(np.column_stack([r.key[own], content[own], (r.end - r.begin)[own].astype(np.uint64)]), axis=0).view(np.int64)
            yield pa.RecordBatch.from_arrays([pa.array(both[:, 0]), pa.array(both[:, 1]), pa.array(both[:, 2])], ["key", "content", "size"])

    found = docs.mapInArrow(run, "key long, content long, size long").distinct().groupBy("key").agg(F.sum("size").alias("size"))
    rows = found.where(F.col("size") * one_of > hot_bytes).select("key").collect()
    return np.sort(np.array([r[0] for r in rows], np.int64).view(np.uint64))


def exchange_runs(docs: DataFrame, kernel: SegmentKernel, n_blocks: int | None = None, hot_bytes: int = HOT_BYTES, one_of: int = ONE_OF) -> DataFrame:
    """The exchange, after minimisers that would draw too much into one bucket have been set aside, in rounds, as the next best may be hot, too."""
    own, _ = own_columns(docs)
    size = text_bytes(own)
    if size > hot_bytes:
        for _ in range(HOT_ROUNDS):
            hot = hot_minimisers(own, kernel, hot_bytes, one_of)
            if not len(hot):
                break
            kernel.avoid = np.union1d(kernel.avoid, hot)
    return exchange(docs, kernel, n_blocks or block_count(own, size), buckets_per_block=2)
