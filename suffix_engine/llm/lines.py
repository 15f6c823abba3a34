"""Line dedup over a sharded minimal perfect hash."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from suffix_engine.llm.blocks import Docs, Items, Kernel, digests, exchange, mix, numbered

_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
#: No line's last holder: the least number, which is no id of a table.
NOT_THERE = np.iinfo(np.int64).min


class PerfectHash:
    """A minimal perfect hash over distinct 64-bit keys: levels of bits, where a key takes the first level in which no other key shares its bit, and the rank of that bit is its number."""

    LOAD = 1.5

    def __init__(self, keys: np.ndarray):
        #: Of each level: its slots, its bits by 64, the number of the first key of each 64.
        self.levels: list[tuple[int, np.ndarray, np.ndarray]] = []
        self.count = 0
        while len(keys):
            size = max(64, int(self.LOAD * len(keys)))
            at = self._slot(keys, len(self.levels), size)
            alone = np.zeros(-(-size // 64) * 64, bool)
            alone[:size] = np.bincount(at, minlength=size) == 1
            bits = np.packbits(alone, bitorder="little").view(np.uint64)
            ones = np.bitwise_count(bits).astype(np.int64)
            self.levels.append((size, bits, self.count + np.cumsum(ones) - ones))
            self.count += int(ones.sum())
            keys = keys[~alone[at]]

    @staticmethod
    def _slot(keys: np.ndarray, level: int, size: int) -> np.ndarray:
        return (mix(keys + np.uint64((level + 1) * 0x9E3779B97F4A7C15 % (1 << 64))) % np.uint64(size)).astype(np.int64)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """The number of each key; one that was never put in gets any number, or -1."""
        out, left = np.full(len(keys), -1, np.int64), np.arange(len(keys))
        for level, (size, bits, ranks) in enumerate(self.levels):
            at = self._slot(keys[left], level, size)
            word, below = bits[at // 64], (at % 64).astype(np.uint64)
            hit = (word >> below) & np.uint64(1) == 1
            inside = np.bitwise_count(word & ((np.uint64(1) << below) - np.uint64(1)))
            out[left[hit]] = (ranks[at // 64] + inside)[hit]
            left = left[~hit]
        return out


@dataclass
class LineIndex:
    """A shard over the lines of at least so many documents: a perfect hash of 64 bits of each line's digest, and arrays of the other
    64 (the fingerprint), the number of documents and the largest id. A line outside it finds some slot, whose fingerprint is another.

    Of lines that agree in the first 64 bits, one is in the arrays and the others are listed beside them.
    """

    slots: PerfectHash
    fingerprint: np.ndarray
    count: np.ndarray
    last: np.ndarray
    beside: dict[tuple[int, int], int]

    @classmethod
    def build(cls, key: np.ndarray, print_: np.ndarray, counts: np.ndarray, largest: np.ndarray, least: int) -> LineIndex:
        order = np.lexsort((print_, key))
        k, p = key[order], print_[order]
        first = np.flatnonzero(np.r_[True, (k[1:] != k[:-1]) | (p[1:] != p[:-1])]) if len(k) else np.zeros(0, np.int64)
        total = np.add.reduceat(counts[order], first) if len(k) else np.zeros(0, np.int64)
        last = np.maximum.reduceat(largest[order], first) if len(k) else np.zeros(0, np.int64)
        often = total >= least
        k, p, total, last = k[first][often], p[first][often], total[often], last[often]
        alone = np.r_[True, k[1:] != k[:-1]] if len(k) else np.zeros(0, bool)
        slots = PerfectHash(k[alone])
        at = slots.find(k[alone])
        arrays = [np.empty(int(alone.sum()), x.dtype) for x in (p, total, last)]
        for out, x in zip(arrays, (p, total, last), strict=True):
            out[at] = x[alone]
        return cls(slots, *arrays, {(int(a), int(b)): int(c) for a, b, c in zip(k[~alone], p[~alone], last[~alone], strict=True)})

    def last_holder(self, key: np.ndarray, print_: np.ndarray) -> np.ndarray:
        """The largest id that holds each line, NOT_THERE for lines that aren't in the shard."""
        out = np.full(len(key), NOT_THERE, np.int64)
        if len(self.fingerprint):
            at = self.slots.find(key)
            there = (at >= 0) & (self.fingerprint[at] == print_)
            out[there] = self.last[at[there]]
        if self.beside:
            for i in np.flatnonzero(out == NOT_THERE).tolist():
                out[i] = self.beside.get((int(key[i]), int(print_[i])), NOT_THERE)
        return out


def split_lines(docs: Docs) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Begin and end of each line in the buffer, and the document it belongs to."""
    breaks = np.flatnonzero(docs.bytes == 10)
    starts = np.sort(np.concatenate([docs.bounds[:-1], breaks + 1]), kind="stable")
    ends = np.sort(np.concatenate([docs.bounds[1:], breaks]), kind="stable")
    counts = 1 + np.searchsorted(breaks, docs.bounds[1:]) - np.searchsorted(breaks, docs.bounds[:-1])
    return starts, ends, np.repeat(np.arange(len(docs)), counts)


def trimmed(b: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The ranges without white space at both ends; one of white space only becomes empty."""
    solid = np.flatnonzero(~_SPACE[b])
    if not len(solid):
        return starts, starts
    first = np.searchsorted(solid, starts)
    last = np.searchsorted(solid, ends)
    any_ = first < last
    return np.where(any_, solid[np.minimum(first, len(solid) - 1)], starts), np.where(any_, solid[np.maximum(last - 1, 0)] + 1, starts)


@dataclass
class LineKernel(Kernel):
    """Drops lines whose trimmed, lower-cased key of at least min_chars is in min_docs documents, but for the largest id."""

    min_chars: int = 20
    min_docs: int = 3
    schema = "doc_id long, n_lines long, n_dropped long, text string"

    def items(self, docs, n_buckets):
        starts, ends, doc = split_lines(docs)
        a, z = trimmed(docs.bytes, starts, ends)
        heads = np.r_[np.int32(0), np.cumsum((docs.bytes & 0xC0) != 0x80, dtype=np.int32)]
        long = np.flatnonzero(heads[z] - heads[a] >= self.min_chars)
        raw = _LOWER[docs.bytes].tobytes()
        number, first = numbered(raw, a[long], z[long])
        key = digests(raw[i:j] for i, j in zip(a[long[first]].tolist(), z[long[first]].tolist(), strict=True))
        # of each distinct key of the block: documents that hold it, and the largest of them; lines come in the order of the ids
        pair = np.unique(number * (len(docs) + 1) + doc[long])
        counts = np.bincount(pair // (len(docs) + 1), minlength=len(first))
        largest = np.zeros(len(first), np.int64)
        largest[number] = docs.ids[doc[long]]
        bucket = (key[:, 0] >> np.uint64(32)).astype(np.int64) % n_buckets
        rank = np.lexsort((key[:, 0], bucket))
        place = np.empty(len(rank), np.int64)
        place[rank] = np.arange(len(rank))
        columns = [key[rank, 0], key[rank, 1], counts[rank].astype(np.uint32), largest[rank].view(np.uint64)]
        return Items(bucket[rank], columns, np.zeros(len(rank), np.int64), np.zeros(0, np.uint8)), (starts, ends, doc, long, place[number])

    def resolve(self, items):
        """Builds the shard's index of repeated lines, which all keys then probe: 1 where the line is in it, 2 where this is its last holder."""
        key, print_, counts, largest = items.columns
        index = LineIndex.build(key, print_, counts.astype(np.int64), largest.view(np.int64), self.min_docs)
        last = index.last_holder(key, print_)
        return np.where(last == NOT_THERE, 0, np.where(last == largest.view(np.int64), 2, 1)).astype(np.uint8)

    def apply(self, docs, items, known, answers):
        starts, ends, doc, long, item = known
        drop = np.zeros(len(starts), bool)
        keeps = (answers[item] == 2) & (items.columns[3].view(np.int64)[item] == docs.ids[doc[long]])
        drop[long] = (answers[item] > 0) & ~keeps
        n_lines, n_dropped = np.bincount(doc, minlength=len(docs)), np.bincount(doc[drop], minlength=len(docs))
        edges = np.r_[0, np.cumsum(n_lines)]
        whole, texts = docs.bytes.tobytes(), []
        for i in range(len(docs)):
            if not n_dropped[i]:
                texts.append(whole[docs.bounds[i] : docs.bounds[i + 1]])
            else:
                texts.append(b"\n".join(whole[starts[j] : ends[j]] for j in range(edges[i], edges[i + 1]) if not drop[j]))
        return {"n_lines": pa.array(n_lines, pa.int64()), "n_dropped": pa.array(n_dropped, pa.int64()), "text": pa.array(texts, pa.binary()).cast(pa.string())}


def dedup_lines(docs: DataFrame, min_chars: int = 20, min_docs: int = 3, n_blocks: int | None = None, keep: tuple[str, ...] = ()) -> DataFrame:
    """doc_id, n_lines, n_dropped and the text that is left, one row for each document.

    A null or empty text is one empty line. Each row counts as a document, also where an id repeats or is null; a null id counts as the
    largest, and all rows with the largest id keep a line. Short keys are never dropped. An empty table gives an empty result. Of the other
    columns only those to keep are read.
    """
    return exchange(docs, LineKernel(min_chars, min_docs), n_blocks, keep=keep)


def line_digests(docs: DataFrame) -> DataFrame:
    return dedup_lines(docs).select("doc_id", "n_lines", "n_dropped", F.sha2(F.col("text").cast("binary"), 256).alias("kept_sha256"))
