"""Substring dedup over run-compressed Burrows-Wheeler indexes of the repetitive parts of a corpus."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from suffix_engine.llm.blocks import Docs, minimiser_runs, mix, range_hashes, spread, words_at
from suffix_engine.llm.segments import Runs, SegmentKernel, exchange_runs, merged, shared_keys

#: Bytes of a gram: two words of eight.
GRAM = 16

#: Symbols that fit in a key of 63 bits at 9 bits each; code 0 stands for all that lies past a piece's end.
_SEED = 7


@dataclass
class RunLengthIndex:
    """Run-compressed transform of a collection of pieces, each ended by a terminator of its own.

    A run of the transform is kept as its symbol and length, with the text positions sampled at its first and last row, and the length
    that the suffix at its first row shares with the one a row above. The suffix order itself is not kept: between two sampled
    positions, the suffix a row above is found by the same shift, and the length shared falls by one with each symbol.
    """

    size: int
    symbols: np.ndarray
    lengths: np.ndarray
    heads: np.ndarray
    ends: np.ndarray
    lcp_heads: np.ndarray

    @classmethod
    def build(cls, text: np.ndarray, begin: np.ndarray) -> RunLengthIndex:
        n = len(text)
        piece = np.repeat(np.arange(len(begin) - 1), np.diff(begin))
        left = begin[1:][piece] - np.arange(n)
        codes = np.r_[text.astype(np.int64) + 1, np.zeros(_SEED, np.int64)]
        key = np.zeros(n, np.int64)
        for j in range(_SEED):
            key |= np.where(left > j, codes[j : n + j], 0) << 9 * (_SEED - 1 - j)
        reach, longest, levels = _SEED, int(left.max(initial=0)), []
        while True:
            rows = np.argsort(key)
            k = key[rows]
            new = np.r_[True, k[1:] != k[:-1]]
            rank = np.empty(n + 1, np.int64)
            rank[rows], rank[n] = np.cumsum(new), 0
            levels.append((reach, rank))
            if reach >= longest or new.all():
                break
            key = rank[:n] * (n + 1) + np.where(left > reach, rank[np.minimum(np.arange(n) + reach, n)], 0)
            reach *= 2
        if not new.all():  # equal to the ends of their pieces: the terminators decide, in the order of the pieces
            rows = np.argsort(rank[:n] * len(begin) + piece)
        first = np.zeros(n, bool)
        first[begin[:-1][np.diff(begin) > 0]] = True
        before = np.where(first[rows], -1, text[rows - 1].astype(np.int64))
        at = np.flatnonzero(np.r_[True, (before[1:] != before[:-1]) | (before[1:] < 0)])
        lcp = np.zeros(len(at), np.int64)
        lcp[1:] = cls._shared(text, left, levels, rows[at[1:] - 1], rows[at[1:]])
        last = np.r_[at[1:], n]
        return cls(n, before[at], last - at, rows[at], rows[last - 1], lcp)

    @staticmethod
    def _shared(text, left, levels, a, b) -> np.ndarray:
        """Length of the prefix that the suffixes at a and b share; ranks of doubling make the long steps."""
        n, most, done = len(text), np.minimum(left[a], left[b]), np.zeros(len(a), np.int64)
        for reach, rank in reversed(levels):
            for _ in range(2 if reach == levels[-1][0] else 1):
                step = (done + reach <= most) & (rank[np.minimum(a + done, n)] == rank[np.minimum(b + done, n)])
                done[step] += reach
        active = np.flatnonzero(done < most)
        while len(active):
            active = active[text[a[active] + done[active]] == text[b[active] + done[active]]]
            done[active] += 1
            active = active[done[active] < most[active]]
        return done

    def matching(self) -> tuple[np.ndarray, np.ndarray]:
        """Matching statistics, streamed in text order: for each position the longest match that stands a row above, as its place and length.

        Place and length are known at the heads of runs: the last row of the run above, and what is shared with it. Within
        a run both suffixes go on alike, so the next position's match is the next place, one symbol shorter.
        """
        above = np.r_[-1, self.ends[:-1]]
        order = np.argsort(self.heads)
        head = self.heads[order]
        gap = np.diff(np.r_[head, self.size])
        step = spread(np.zeros(len(gap), np.int64), gap)
        length = np.repeat(self.lcp_heads[order], gap) - step
        place = np.where(length > 0, np.repeat(above[order], gap) + step, -1)
        return place, np.maximum(length, 0)


def chain_ends(to: np.ndarray) -> np.ndarray:
    """Where each chain of pointers ends (an end points to itself), by jumps of doubled length."""
    while not np.array_equal(to, to[to]):
        to = to[to]
    return to


def gram_hashes(word: np.ndarray, first, second) -> np.ndarray:
    return mix(mix(word[first]) + word[second])


@dataclass
class SubstringKernel(SegmentKernel):
    """Runs of window starts whose leftmost least gram is the same one; grams of 16 bytes, windows of any length from GRAM on."""

    length: int = 100
    schema = "doc_id long, n_bytes long, spans array<struct<begin:bigint,end:bigint>>, kept binary"

    def runs(self, docs: Docs) -> Runs:
        b, n = docs.bytes, len(docs.bytes)
        word = words_at(b)

        def valid(low: int, high: int) -> np.ndarray:
            ok = np.ones(high - low, bool)
            i, j = np.searchsorted(docs.bounds, (low, high + self.length), side="right")
            for bound in docs.bounds[max(i - 1, 0) : j]:
                ok[max(0, bound - self.length + 1 - low) : max(0, bound - low)] = False
            return ok

        def hashes(low: int, high: int) -> np.ndarray:
            return gram_hashes(word, slice(low, max(low, min(high, n - GRAM + 1))), slice(low + 8, max(low, min(high, n - GRAM + 1)) + 8))

        first, count, at, key = minimiser_runs(n, self.length - GRAM + 1, hashes, valid, self.avoid)
        doc = np.searchsorted(docs.bounds, first, side="right") - 1
        return Runs(b, first, first + count + self.length - 1, first, count, doc, first - docs.bounds[doc], at - first, key)

    def minimiser(self, data, begin, at):
        return gram_hashes(words_at(data), begin + at, begin + at + 8)

    def may_match(self, data, begin, end, at, key):
        """Of two equal windows, what lies around the gram is the same, and half of it or more lies on one side."""
        half, gram = (self.length - GRAM) // 2, begin + at
        out = np.zeros(len(begin), bool)
        for own, a in ((np.flatnonzero(at >= half), gram - half), (np.flatnonzero(end - gram - GRAM >= half), gram + GRAM)):
            out[own] |= shared_keys(mix(range_hashes(data, a[own], a[own] + half) + key[own]))
        return out

    def mark(self, data, begin, count, doc, start):
        match, length = RunLengthIndex.build(data, begin).matching()
        piece = np.repeat(np.arange(len(count)), np.diff(begin))
        offset = np.arange(len(data)) - begin[piece]
        whole = offset < count[piece]  # a window starts here
        order = np.unique(doc, return_inverse=True)[1].astype(np.int64)
        place = (order[piece] << 40) | (start[piece] + offset)
        # equal windows are a chain of long matches
        group = chain_ends(np.where(length >= self.length, match, np.arange(len(data))))
        least = np.full(len(data), np.iinfo(np.int64).max)
        np.minimum.at(least, group[whole], place[whole])
        return (place > least[group])[whole]

    def apply(self, docs, items, known, answers):
        gone = self.starts(docs, items, known, answers)
        begin, end = merged(gone, self.length)
        # ranges that touch in the buffer but lie in different documents are apart
        doc = np.searchsorted(docs.bounds, gone, side="right") - 1
        if len(gone):
            cut = np.flatnonzero((np.diff(gone) > self.length) | (np.diff(doc) > 0))
            begin, end = gone[np.r_[0, cut + 1]], gone[np.r_[cut, len(gone) - 1]] + self.length
        of = np.searchsorted(docs.bounds, begin, side="right") - 1
        edges = np.searchsorted(of, np.arange(len(docs) + 1))
        whole, kept = docs.bytes.tobytes(), []
        for i in range(len(docs)):
            at, parts = docs.bounds[i], []
            for j in range(edges[i], edges[i + 1]):
                parts.append(whole[at : begin[j]])
                at = end[j]
            parts.append(whole[at : docs.bounds[i + 1]])
            kept.append(b"".join(parts))
        spans = pa.StructArray.from_arrays([pa.array(begin - docs.bounds[of], pa.int64()), pa.array(end - docs.bounds[of], pa.int64())], ["begin", "end"])
        return {"n_bytes": pa.array(np.diff(docs.bounds), pa.int64()), "spans": pa.ListArray.from_arrays(pa.array(edges, pa.int32()), spans), "kept": pa.array(kept, pa.binary())}


def dedup_substrings(docs: DataFrame, length: int = 100, n_blocks: int | None = None) -> DataFrame:
    """doc_id, n_bytes, the removed spans (begin, end in bytes) and the kept bytes, one row for each document.

    Every byte in a string of that length that also starts earlier goes. Kept bytes need not be valid UTF-8.
    Null and empty texts have no bytes. A row that repeats an id and its text is at the same place, not earlier;
    a null id counts as the largest. An empty table gives an empty result. Other columns aren't read.
    """
    return exchange_runs(docs, SubstringKernel(length), n_blocks)


def substring_digests(docs: DataFrame) -> DataFrame:
    removed = F.aggregate("spans", F.lit(0).cast("long"), lambda s, x: s + x["end"] - x["begin"])
    return dedup_substrings(docs).select("doc_id", "n_bytes", removed.alias("n_removed"), F.size("spans").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))
