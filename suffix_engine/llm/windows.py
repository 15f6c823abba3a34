"""Removal of repeated word windows by super-k-mer partitioning."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from suffix_engine.llm.blocks import Docs, chained, minimiser_runs, range_hashes, spread
from suffix_engine.llm.lines import _SPACE
from suffix_engine.llm.segments import Runs, SegmentKernel, exchange_runs, merged


def word_ranges(b: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Begin and end of each word, and the first word of each document (one more entry than documents)."""
    solid = ~_SPACE[b]
    start = solid.copy()
    start[1:] &= ~solid[:-1]
    stop = solid.copy()
    stop[:-1] &= ~solid[1:]
    inner = bounds[1:-1]
    inner = inner[(inner > 0) & (inner < len(b))]
    start[inner] = solid[inner]
    stop[inner - 1] = solid[inner - 1]
    begin, end = np.flatnonzero(start), np.flatnonzero(stop) + 1
    return begin, end, np.searchsorted(begin, bounds)


def packed_words(b: np.ndarray, begin: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The words one after another, a space behind each, and where each begins there."""
    solid = ~_SPACE[b]
    # a byte is kept if it is in a word; each word's last byte is followed by one space
    length = end - begin + 1
    at = np.cumsum(length) - length
    out = np.full(int(length.sum()), 32, np.uint8)
    keep = np.ones(len(out), bool)
    keep[at + length - 1] = False
    out[keep] = b[solid]
    return out, at


@dataclass
class WindowKernel(SegmentKernel):
    """Consecutive windows that share a minimiser of gram words travel as one string of words to its bucket."""

    size: int = 13
    gram: int = 3
    by_document = True
    schema = "doc_id long, n_words long, n_removed long, text string"

    def runs(self, docs: Docs) -> Runs:
        begin, end, first_word = word_ranges(docs.bytes, docs.bounds)
        word = range_hashes(docs.bytes, begin, end)
        text, at = packed_words(docs.bytes, begin, end)
        n = len(word)

        def valid(low: int, high: int) -> np.ndarray:
            ok = np.ones(high - low, bool)
            i, j = np.searchsorted(first_word, (low, high + self.size), side="right")
            for bound in np.unique(first_word[max(i - 1, 0) : j]):
                ok[max(0, bound - self.size + 1 - low) : max(0, bound - low)] = False
            return ok

        def hashes(low: int, high: int) -> np.ndarray:
            return chained(word[low : high + self.gram - 1], self.gram)

        first, count, place, key = minimiser_runs(n, self.size - self.gram + 1, hashes, valid, self.avoid)
        edge = np.r_[at, len(text)]
        doc = np.searchsorted(first_word, first, side="right") - 1
        run = Runs(text, edge[first], edge[first + count + self.size - 1], first, count, doc, first - first_word[doc], edge[place] - edge[first], key)
        run.words, run.first_word = (begin, end), first_word
        return run

    def minimiser(self, data, begin, at):
        # the words of the gram end at the third space after its place
        spaces = np.flatnonzero(data == 32)
        place = begin + at
        return range_hashes(data, place, spaces[np.searchsorted(spaces, place) + self.gram - 1])

    def mark(self, data, begin, count, doc, start):
        """Words are numbered by their bytes and windows by their words, in steps of doubled length, so equal numbers are equal windows."""
        words = data.tobytes().split(b" ")[:-1]
        seen: dict[bytes, int] = {}
        name = np.fromiter((seen.setdefault(w, len(seen)) for w in words), np.int64, len(words))
        ends = np.flatnonzero(data == 32) + 1
        own = np.searchsorted(np.r_[0, ends[:-1]], begin[:-1])
        reach = 1
        while reach < self.size:
            step = min(reach, self.size - reach)
            pair = name[: len(name) - step] * (int(name.max()) + 1) + name[step:]
            name, reach = np.unique(pair, return_inverse=True)[1], reach + step
        window = name[spread(own, count)]
        holder = np.repeat(doc, count)
        order = np.lexsort((holder, window))
        x, d = window[order], holder[order]
        new = np.r_[True, x[1:] != x[:-1]]
        out = np.empty(len(order), bool)
        out[order] = d > d[np.flatnonzero(new)[np.cumsum(new) - 1]]
        return out

    def apply(self, docs, items, known, answers):
        r, gone = known.runs, self.starts(docs, items, known, answers)
        begin, end = r.words
        low, high = merged(gone, self.size)
        edge = np.zeros(len(begin) + 1, np.int64)
        np.add.at(edge, low, 1)
        np.add.at(edge, high, -1)
        drop = np.cumsum(edge[:-1]) > 0
        total = np.r_[0, np.cumsum(drop)]
        removed = total[r.first_word[1:]] - total[r.first_word[:-1]]
        words = np.diff(r.first_word)
        keep = ~drop
        at = np.r_[0, np.cumsum(np.where(keep, end - begin + 1, 0))]
        kept_bytes = np.repeat(keep, end - begin + 1)
        packed = r.bytes[kept_bytes].tobytes()
        edges = at[r.first_word]
        texts = [packed[edges[i] : max(edges[i], edges[i + 1] - 1)] for i in range(len(docs))]
        return {"n_words": pa.array(words, pa.int64()), "n_removed": pa.array(removed, pa.int64()), "text": pa.array(texts, pa.binary()).cast(pa.string())}


def dedup_windows(docs: DataFrame, size: int = 13, n_blocks: int | None = None) -> DataFrame:
    """doc_id, n_words, n_removed and the kept words joined by one space, one row for each document.

    A word goes if a window over it also starts in a document with a smaller id. Null and empty texts have no
    words. Repeats inside a document, or in rows that repeat its id, don't count. A null id counts as the largest.
    An empty table gives an empty result. Other columns aren't read.
    """
    return exchange_runs(docs, WindowKernel(size), n_blocks)


def window_digests(docs: DataFrame) -> DataFrame:
    return dedup_windows(docs).select("doc_id", "n_words", "n_removed", F.sha2(F.col("text").cast("binary"), 256).alias("kept_sha256"))
