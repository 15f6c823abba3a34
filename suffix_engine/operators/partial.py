"""Sorting one bucket of suffixes: blocks as long as the widest gap, three kernels, and renaming."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from suffix_engine.operators.bwt import local_ranks

KERNELS = ("radix", "merge", "refine")
REDUCTIONS = ("gap_rename", "span_direct", "none")
#: read(positions, offset, width): the codes + 1 at positions + offset .. + width, 0 past the end, as a matrix.
Reader = Callable[[np.ndarray, int, int], np.ndarray]
#: Symbols that the merge kernel copies of each block at first; ties are sorted again on longer copies.
SLICE = 64
#: Symbols that the refining kernel reads at once at most, if more than one key for each suffix.
READ = 1 << 20
#: Symbols that the merge kernel copies at once, if more than eight for each suffix of one group.
CELLS = 1 << 22


def array_reader(codes: np.ndarray, base: int = 0) -> Reader:
    """Over the symbols from position base on; rows are copied whole, so wide reads cost little for each symbol."""
    return padded_reader(padded_codes(codes), base)


def padded_codes(codes: np.ndarray) -> np.ndarray:
    """The codes + 1, and READ zeros."""
    padded = np.zeros(len(codes) + READ, np.uint16)
    padded[: len(codes)] = codes
    padded[: len(codes)] += 1
    return padded


def padded_reader(padded: np.ndarray, base: int = 0) -> Reader:
    """array_reader over padded codes, which tasks may share."""
    end, views = len(padded) - READ, {}

    def read(positions: np.ndarray, offset: int, width: int) -> np.ndarray:
        if width not in views:
            views[width] = np.lib.stride_tricks.sliding_window_view(padded, width)
        return views[width][np.minimum(positions + (offset - base), end)]

    return read


def max_gap(positions: np.ndarray, n: int) -> int:
    """The widest gap between neighbours of a bucket, the end of the text counted as one."""
    return int(np.diff(np.r_[np.sort(positions), n]).max()) if len(positions) else 0


def bucket_gaps(rows: DataFrame, n: int, bucket: str = "bucket") -> DataFrame:
    """(bucket, members, l_max), relationally."""
    own = Window.partitionBy(bucket).orderBy("pos")
    return rows.withColumn("_gap", F.lead("pos", 1, n).over(own) - F.col("pos")).groupBy(bucket).agg(F.count(F.lit(1)).alias("members"), F.max("_gap").alias("l_max"))


def radix_order(positions: np.ndarray, read: Reader, length: int, width: int = 16) -> np.ndarray:
    """Stable counting passes over the columns from the last ones to the first: the cost is members times length, always.

    width: bits of a symbol; a pass takes as many columns as 16 bits hold. Columns are read in the given order of the positions, so positions
    in text order are read from front to back.
    """
    order, at_once = np.arange(len(positions)), max(1, 16 // width)
    # several passes' columns are read together, within a bound
    together = max(1, min(64, CELLS // max(1, len(positions) * at_once)))
    for end in range(length, 0, -at_once * together):
        begin = max(0, end - at_once * together)
        block = read(positions, begin, end - begin)
        for z in range(end - begin, 0, -at_once):
            a = max(0, z - at_once)
            digits = block[:, a].astype(np.uint16)
            for column in range(a + 1, z):
                digits = (digits << np.uint16(width)) | block[:, column]
            order = order[np.argsort(digits[order], kind="stable")]
    return order


def merge_order(positions: np.ndarray, read: Reader, length: int) -> np.ndarray:
    """The library's adaptive merge sort over byte copies of the blocks, longer copies only for those that tie.

    What is copied at once is bounded: groups take turns, and a large group gets narrow copies.
    """
    order = np.arange(len(positions))
    turns = [(order.copy(), np.zeros(len(order), np.int64), 0, SLICE)]  # places, their groups in order, symbols seen, symbols to copy
    while turns:
        place, group, done, step = turns.pop()
        width = min(step, length - done)
        if len(place) < 2 or width <= 0:
            continue
        if len(place) * width > CELLS:
            border = np.flatnonzero(group[1:] != group[:-1]) + 1
            if len(border):
                half = border[np.argmin(np.abs(border - len(place) // 2))]
                turns += [(place[half:], group[half:], done, step), (place[:half], group[:half], done, step)]
                continue
            width = min(width, max(8, CELLS // len(place)))
        rows = order[place]
        keys = np.ascontiguousarray(read(positions[rows], done, width).astype(">u2")).view(f"S{2 * width}")[:, 0]
        again = np.argsort(keys, kind="stable")
        again = again[np.argsort(group[again], kind="stable")]
        order[place], keys = rows[again], keys[again]
        number = np.cumsum(np.r_[False, (group[1:] != group[:-1]) | (keys[1:] != keys[:-1])])
        tied = np.bincount(number)[number] > 1
        turns.append((place[tied], number[tied], done + width, min(2 * step, READ // 2) if width == step else step))
    return order


def refine_order(positions: np.ndarray, read: Reader, depth: int, group: np.ndarray, width: int, longest: int | None = None) -> np.ndarray:
    """Only suffixes that still tie are read on, as many symbols at a time as a key of 63 bits holds.

    group: what the first depth symbols say, as numbers in their order. Ends when no two suffixes tie (the terminator sees to that), or
    after exactly longest symbols; what still ties then stays in the order of the positions.
    """
    order = np.argsort(group, kind="stable")
    rank = np.unique(group, return_inverse=True)[1][order].astype(np.int64)
    first = np.flatnonzero(np.r_[True, rank[1:] != rank[:-1]]) if len(rank) else np.zeros(0, np.int64)
    rank = np.repeat(first, np.diff(np.r_[first, len(rank)]))  # place of the group's first member
    take = 63 // width
    active, words = np.flatnonzero(_tied(rank)), 1
    while len(active) and (longest is None or depth < longest):
        # long common prefixes are few: the fewer suffixes still tie, the more symbols are read at a time
        words = max(1, min(2 * words, READ // (len(active) * take)))
        symbols, g = read(positions[order[active]], depth, take * words), rank[active]
        if longest is not None and depth + take * words > longest:
            symbols = symbols.copy()
            symbols[:, longest - depth :] = 0
        depth += take * words
        # inside long repeats all members of a group go on alike, which one pass over the rows shows
        parted = g[1:][(g[1:] == g[:-1]) & (symbols[1:] != symbols[:-1]).any(axis=1)]
        own = np.flatnonzero(np.isin(g, parted))
        if not len(own):
            continue
        rows, symbols, g = active[own], symbols[own], g[own]
        keys = np.zeros((words, len(own)), np.int64)
        for j in range(take):
            keys = (keys << width) | symbols[:, j::take].T
        again = np.lexsort((*keys[::-1], g))
        order[rows] = order[rows][again]
        keys = keys[:, again]  # the groups stand in place order already
        new = np.r_[True, (g[1:] != g[:-1]) | (keys[:, 1:] != keys[:, :-1]).any(axis=0)]
        rank[rows] = rows[np.flatnonzero(new)][np.cumsum(new) - 1]
        active = active[_tied(rank[active])]
    return order


def refine_columns(columns: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """refine_order for symbols that came along as columns of keys: a column is read only for what the ones before leave tied. The order, and for
    each place in it that of the first one with the same keys."""
    order = np.argsort(columns[0])
    first = columns[0][order]
    place = _first_of(first[1:] != first[:-1]) if len(order) else np.zeros(0, np.int64)
    for column in columns[1:]:
        own = np.flatnonzero(_tied(place))
        if not len(own):
            break
        group, keys = place[own], column[order[own]]
        again = np.lexsort((keys, group))
        order[own], keys = order[own][again], keys[again]
        place[own] = own[_first_of((group[1:] != group[:-1]) | (keys[1:] != keys[:-1]))]
    return order, place


def _first_of(new: np.ndarray) -> np.ndarray:
    """For each place the one where its group began; new: whether a group begins at places 1, 2, ..."""
    first = np.r_[0, np.flatnonzero(new) + 1]
    return np.repeat(first, np.diff(np.r_[first, len(new) + 1]))


def _tied(rank: np.ndarray) -> np.ndarray:
    same = rank[1:] == rank[:-1]
    return np.r_[False, same] | np.r_[same, False] if len(rank) else np.zeros(0, bool)


def block_length(positions: np.ndarray, n: int, k: int) -> int:
    """Blocks must reach past the next member's own first k symbols: gap + k - 1. Blocks of the gap alone order some texts wrongly."""
    return max_gap(positions, n) + k - 1


def sort_bucket(positions: np.ndarray, keys: np.ndarray, read: Reader, n: int, k: int, width: int, kernel: str = "refine", reduction: str = "gap_rename", length: int | None = None) -> np.ndarray:
    """The positions of a bucket in suffix order; keys are their first k symbols. length overrides the blocks' (for tests).

    No symbol further from a position than its block is read, but by the refining kernel without renaming ("none"), which reads on while suffixes tie.
    """
    by_text = np.argsort(positions)
    positions, keys = positions[by_text], keys[by_text]
    if not len(positions):
        return positions
    if kernel == "refine" and reduction == "none":
        return positions[refine_order(positions, read, k, keys, width)]
    size = length or (block_length(positions, n, k) if reduction == "gap_rename" else n - int(positions[0]))
    if kernel == "refine":
        order = refine_order(positions, read, min(k, size), keys if size >= k else keys >> width * (k - size), width, size)
    else:
        order = radix_order(positions, read, size, width) if kernel == "radix" else merge_order(positions, read, size)
    if reduction == "span_direct":
        return positions[order]
    # equal blocks get equal names; the order of the names' own suffixes is that of the positions
    equal = np.r_[False, _equal(read, positions[order[:-1]], positions[order[1:]], size)]
    names = np.empty(len(order), np.int64)
    names[order] = np.cumsum(~equal)
    out = np.empty_like(positions)
    out[local_ranks(names)] = positions
    return out


def _equal(read: Reader, a: np.ndarray, b: np.ndarray, length: int) -> np.ndarray:
    """Which pairs of blocks are equal; only those that were so far are read on."""
    out, active, at, step = np.ones(len(a), bool), np.arange(len(a)), 0, 16
    while at < length and len(active):
        width = min(step, length - at)
        rows = max(1, READ // width)
        for i in range(0, len(active), rows):
            own = active[i : i + rows]
            out[own] = (read(a[own], at, width) == read(b[own], at, width)).all(axis=1)
        active = active[out[active]]
        at, step = at + width, min(step * 2, READ // 2)
    return out
