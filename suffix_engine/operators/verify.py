"""Checks of results at any size, without a second suffix array."""

from __future__ import annotations

import secrets
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from suffix_engine.model import Corpus
from suffix_engine.operators.anchors import Turns
from suffix_engine.operators.corpus import text
from suffix_engine.operators.suffix_array import neighbours
from suffix_engine.session import release

#: The prime of the digests of sequences.
PRIME = (1 << 61) - 1
_POWERS: dict[int, np.ndarray] = {}


def check_suffix_array(sa: DataFrame, corpus: Corpus) -> DataFrame:
    """(n, rows, positions, misplaced, violations): a right array has n rows, n positions, and 0 of both others.

    Neighbours are in order if their first symbols are, or if these are equal and the suffixes behind them are in order by rank.
    """
    n = corpus.n
    behind = sa.select((F.col("pos") - 1).alias("pos"), F.col("rank").alias("behind"))
    own = sa.join(text(corpus), "pos").join(behind, "pos", "left").select("rank", "pos", F.struct("code", F.coalesce("behind", F.lit(-1)).alias("behind")).alias("v"))
    bad = neighbours(own, "v")
    wrong = F.col("prior_v").isNotNull() & ~((F.col("prior_v.code") < F.col("v.code")) | ((F.col("prior_v.code") == F.col("v.code")) & (F.col("prior_v.behind") < F.col("v.behind"))))
    out_of = (F.col("pos") < 0) | (F.col("pos") >= n) | (F.col("rank") < 0) | (F.col("rank") >= n)
    unique = sa.groupBy("pos").agg(F.count(F.lit(1)).alias("c")).agg(F.count(F.lit(1)).alias("positions"))
    return bad.agg(F.count(F.lit(1)).alias("rows"), F.sum(F.when(out_of, 1).otherwise(0)).alias("misplaced"), F.sum(F.when(wrong, 1).otherwise(0)).alias("violations")).join(F.broadcast(unique)).select(F.lit(n).cast("long").alias("n"), "rows", "positions", "misplaced", "violations")


def times(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Products modulo PRIME."""
    low = np.uint64((1 << 31) - 1)
    ah, al, bh, bl = a >> np.uint64(31), a & low, b >> np.uint64(31), b & low
    mid, rest = ah * bl + al * bh, al * bl
    out = np.uint64(2) * ah * bh + (mid >> np.uint64(30)) + ((mid & np.uint64((1 << 30) - 1)) << np.uint64(31)) + (rest & np.uint64(PRIME)) + (rest >> np.uint64(61))
    out = (out & np.uint64(PRIME)) + (out >> np.uint64(61))
    return np.where(out >= PRIME, out - np.uint64(PRIME), out)


def powers(base: int, count: int) -> np.ndarray:
    """base ** 0, 1, ... modulo PRIME."""
    own = _POWERS.get(base, np.ones(1, np.uint64))
    while len(own) < count:
        own = np.r_[own, times(own, np.uint64(pow(base, len(own), PRIME)))]
    for other in [x for x in _POWERS if x != base][:-1]:
        del _POWERS[other]
    _POWERS[base] = own
    return own


def digests(code: np.ndarray, values: np.ndarray, bases: tuple[int, ...]) -> list[tuple[int, ...]]:
    """(code, length, digest for each base) of the values under each code, in their order: the sum of value i times base ** i modulo PRIME."""
    if not len(code):
        return []
    order = np.argsort(code, kind="stable")
    code, values = code[order], values[order].astype(np.uint64)
    first = np.flatnonzero(np.r_[True, code[1:] != code[:-1]])
    size = np.diff(np.r_[first, len(code)])
    at = np.arange(len(code)) - np.repeat(first, size)
    found = []
    for base in bases:
        terms = times(values, powers(base, int(size.max()))[at])
        high, low = (np.add.reduceat(x, first) for x in (terms >> np.uint64(32), terms & np.uint64((1 << 32) - 1)))
        found.append([((int(h) << 32) + int(x)) % PRIME for h, x in zip(high, low, strict=True)])
    return list(zip(code[first].tolist(), size.tolist(), *found, strict=True))


def check_turns(turns: Turns, corpus: Corpus) -> DataFrame | None:
    """check_suffix_array's row for suffixes that are sorted in turns, none of which is kept; None if anything is wrong.

    A list of n positions within the text is the suffix array if its first symbols are in order and, for each symbol, the positions that begin with
    it are, in the same order, those before the positions that it precedes. It has every position once, then: those but the last one are
    as often in it as the next ones. Both lists are compared by two digests of their length, values and order at random bases.
    """
    n, bases, spark = corpus.n, tuple(secrets.randbelow(PRIME - 2) + 2 for _ in range(2)), corpus.pieces.sparkSession

    def digest(bucket: int, pos: np.ndarray, first: np.ndarray, before: np.ndarray) -> pa.Table:
        good = bool(len(pos) and pos.min() >= 0 and pos.max() < n and (first[1:] >= first[:-1]).all())
        rows = [(2, int(first[0]), len(pos), int(first[-1]), int(good))]
        if good:
            head, tail = pos != n - 1, pos != 0
            rows += [(0, *x) for x in digests(first[head], pos[head], bases)] + [(1, *x) for x in digests(before[tail], pos[tail] - 1, bases)]
        columns = [np.array(x, np.int64) for x in zip(*rows, strict=True)]
        return pa.table({"bucket": np.full(len(rows), bucket, np.int64)} | dict(zip(("kind", "code", "number", "a", "b"), columns, strict=True)))

    rows, last, lists = 0, -1, (defaultdict(lambda: (0, 0, 0)), defaultdict(lambda: (0, 0, 0)))
    for turn in range(turns.count):
        found = sorted(tuple(x) for x in turns.each(turn, digest, "bucket long, kind long, code long, number long, a long, b long").collect())
        for _, kind, code, number, a, b in found:
            if kind == 2:
                if not b or code < last:
                    return None
                rows, last = rows + number, a
            else:
                length, x, y = lists[kind][code]
                lists[kind][code] = (length + number, (x + a * pow(bases[0], length, PRIME)) % PRIME, (y + b * pow(bases[1], length, PRIME)) % PRIME)
        release(spark, at_once=True)
    if rows != n or dict(lists[0]) != dict(lists[1]):
        return None
    return spark.createDataFrame([(n, rows, n, 0, 0)], "n long, rows long, positions long, misplaced long, violations long")


def same_symbols(bwt: DataFrame, corpus: Corpus) -> DataFrame:
    """(code, text, bwt) where the counts of a symbol differ: none in a right transform."""
    a = text(corpus).groupBy("code").agg(F.count(F.lit(1)).alias("text"))
    b = bwt.groupBy("code").agg(F.count(F.lit(1)).alias("bwt"))
    return a.join(b, "code", "full").where("text is distinct from bwt")


def bucket_property(buckets: DataFrame) -> DataFrame:
    """(bucket, members, least, greatest, apart): apart is whether all k-mers of the bucket come after those of the one before."""
    spans = buckets.groupBy("bucket").agg(F.count(F.lit(1)).alias("members"), F.min("kmer").alias("least"), F.max("kmer").alias("greatest"))
    ranked = spans.select(F.col("bucket").cast("long").alias("rank"), "members", "least", "greatest")
    return neighbours(ranked, "greatest").select(F.col("rank").alias("bucket"), "members", "least", "greatest", (F.col("prior_greatest").isNull() | (F.col("prior_greatest") < F.col("least"))).alias("apart"))
