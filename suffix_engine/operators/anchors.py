"""Suffix sort of a text that lies in chunks, without a table of all positions: anchors are ranked first, then the buckets take turns.

An anchor is the place of the least hash of a short gram within the window behind a suffix, so it depends on the symbols alone: suffixes that share
`seen` symbols have their next anchors equally far off, and the order of these anchors is theirs. Anchors, one in a dozen or two positions, are
named by their own first symbols; their names in text order are a shorter text, which is ranked in the same way until one task can hold it.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from suffix_engine.model import CODE, Corpus
from suffix_engine.operators import kmers, partial
from suffix_engine.operators.packing import fewest, packed, spread, unpacked
from suffix_engine.session import cut, release

#: Symbols of a chunk; with what it shows of its neighbours it has less than 2^20.
CHUNK_SYMBOLS = 1 << 19
#: Suffixes (or anchors) in a bucket on average, and turns that the buckets take.
BUCKET, TURNS = 1 << 18, 24
#: Names that one task may rank by itself.
ALONE = 1 << 23
#: Suffixes that a task holds before it hands them on.
HELD = 1 << 18
#: Sampled keys for each splitter.
SAMPLED = 64
_INDEX = np.uint64((1 << 20) - 1)


def keys_of(symbols: np.ndarray, count: int, k: int, width: int) -> np.ndarray:
    """Keys of the k symbols from each of the first count places on, by doubling."""
    out, have, power, reach = None, 0, symbols, 1
    while True:
        if k & reach:
            if out is None:
                out, have = power[: len(power)], reach
            else:
                n = min(len(power), len(out) - reach)
                out, have = (power[:n] << (width * have)) | out[reach : reach + n], have + reach
        if 2 * reach > k:
            return out[:count]
        power = (power[: len(power) - reach] << (width * reach)) | power[reach:]
        reach *= 2


@dataclass
class Shape:
    """How a text of n symbols (from 1 on, of so many bits) is read: words of take symbols, anchors by grams within a window."""

    n: int
    width: int
    words: int
    gram: int
    size: int

    @property
    def take(self) -> int:
        return 63 // self.width

    @property
    def base(self) -> int:
        """Symbols of the keys that are made for all places."""
        return 1 << max(0, (31 // self.width).bit_length() - 1)

    @property
    def seen(self) -> int:
        return self.words * self.take

    @property
    def window(self) -> int:
        return self.seen - self.gram

    @property
    def halo(self) -> int:
        return self.window + self.seen

    @property
    def chunks(self) -> int:
        return -(-self.n // self.size)


def shape(n: int, width: int, names: bool = False, size: int | None = None) -> Shape:
    take, size = 63 // width, size or CHUNK_SYMBOLS
    if names:
        return Shape(n, width, max(2, -(-8 // take)), 1, size)
    words = max(2, -(-40 // take))
    own = Shape(n, width, words, 1, size)
    own.gram = min(own.base, own.seen // 4)
    return own


class View:
    """A chunk's anchors, and the suffixes whose next anchor is one of them; places count from the chunk's start.

    A chunk has the anchors from the window's length on (the first chunk: from 0) up to the same place in the next chunk, so that every suffix
    belongs to one chunk, which shows all that is read of it, and the symbol before it. found: what find has stored.
    """

    def __init__(self, chunk: int, codes: np.ndarray, s: Shape, found: bytes | None = None):
        self.chunk, self.start, self.shape = chunk, chunk * s.size, s
        limit = min(s.n - self.start, s.size + s.window)
        self.symbols = np.zeros(limit + s.halo + s.take + s.seen, np.int32 if s.width < 32 else np.int64)
        self.symbols[: len(codes)] = codes[: len(self.symbols)]
        self.keys = keys_of(self.symbols, limit + s.halo + s.take, s.base, s.width)
        self.limit = limit
        if found is not None:
            own = unpacked(found)
            at, self.anchors = np.cumsum(own["at"].astype(np.int64)), np.cumsum(own["anchor"].astype(np.int64))[:-1]
            self.at, self.end = at[:-1], int(at[-1])
            self.first = int(at[0])

    def find(self) -> bytes:
        """The anchors, and the first suffix of each."""
        s, have = self.shape, self.limit + self.shape.window
        grams = (self.keys[:have] >> s.width * (s.base - s.gram)).astype(np.uint64)
        grams = (grams + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
        grams = (grams ^ (grams >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
        grams = (grams ^ (grams >> np.uint64(32))) & ~_INDEX
        grams[s.n - self.start :] = ~_INDEX  # nothing past the end is an anchor
        grams |= np.arange(have, dtype=np.uint64)
        reach = 1
        while reach < s.window:  # the least of each window, the leftmost one if several are
            step = min(reach, s.window - reach)
            grams, reach = np.minimum(grams[:-step], grams[step:]), reach + step
        nearest = (grams[: self.limit] & _INDEX).astype(np.int64)
        first, end = np.searchsorted(nearest, [s.window if self.chunk else 0, s.size + s.window])
        nearest = nearest[first:end]
        at = np.flatnonzero(np.r_[True, nearest[1:] != nearest[:-1]]) if len(nearest) else np.zeros(0, np.int64)
        anchors = nearest[at]
        return packed(at=np.diff(np.r_[at + first, end], prepend=0).astype(np.int32), anchor=np.diff(np.r_[anchors, anchors[-1:] if len(anchors) else 0], prepend=0).astype(np.int32))

    def word(self, places: np.ndarray, j: int) -> np.ndarray:
        s, out, done = self.shape, np.zeros(len(places), np.int64), 0
        while done < s.take:
            step = min(s.base, s.take - done)
            out = (out << s.width * step) | (self.keys[places + (j * s.take + done)] >> s.width * (s.base - step))
            done += step
        return out

    def columns(self, places: np.ndarray) -> dict[str, np.ndarray]:
        return {f"w{j}": self.word(places, j) for j in range(self.shape.words)}

    def number(self, places: np.ndarray) -> np.ndarray:
        """Of the anchor of each suffix, among the chunk's own."""
        return np.searchsorted(self.at, places, side="right") - 1


def views(batch: pa.RecordBatch, s: Shape) -> Iterator[View]:
    for chunk, raw, found in zip(batch["chunk"].to_pylist(), batch["codes"].to_pylist(), batch["found"].to_pylist(), strict=True):
        yield View(chunk, unpacked(raw)["c"], s, found)


def lay(pieces: DataFrame, s: Shape, dtype: np.dtype, partitions: int) -> DataFrame:
    """(chunk, codes, found): symbols + 1 of each chunk and its halo, compressed, and its anchors; pieces are (start, codes)."""
    size, halo, most = s.size, s.halo, 1 << s.width

    def split(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, starts, parts = [], [], []
            runs: list[tuple[int, list[bytes]]] = []
            end = -1
            for start, raw in sorted(zip(batch["start"].to_pylist(), batch["codes"].to_pylist(), strict=True)):
                if start != end:
                    runs.append((start, []))
                runs[-1][1].append(raw)
                end = start + len(raw) // dtype.itemsize
            for start, raws in runs:
                c = np.frombuffer(b"".join(raws), dtype).astype(np.int64) + 1
                for i in range(max(0, (start - halo - size + 1) // size), (start + len(c) - 1) // size + 1):
                    a, z = max(i * size, start), min((i + 1) * size + halo, start + len(c))
                    if a < z:
                        ids.append(i)
                        starts.append(a)
                        parts.append(packed(c=fewest(c[a - start : z - start], most)))
            yield pa.RecordBatch.from_arrays([pa.array(ids, pa.int64()), pa.array(starts, pa.int64()), pa.array(parts, pa.binary())], ["chunk", "start", "codes"])

    def join(table: pa.Table) -> pa.Table:
        order = np.argsort(table["start"].to_numpy())
        raw = table["codes"].to_pylist()
        whole = np.concatenate([unpacked(raw[i])["c"] for i in order])
        found = View(table["chunk"][0].as_py(), whole, s).find()
        return pa.table({"chunk": table["chunk"][:1], "codes": pa.array([packed(c=whole)], pa.binary()), "found": pa.array([found], pa.binary())})

    parts = pieces.select("start", "codes").mapInArrow(split, "chunk long, start long, codes binary")
    return cut(parts.repartition(partitions, "chunk").groupBy("chunk").applyInArrow(join, "chunk long, codes binary, found binary"))


def splitters(laid: DataFrame, s: Shape, anchors: bool, count: int) -> np.ndarray:
    """count - 1 first words between the buckets, from a sample; all rows are dealt by them."""
    each = max(1, -(-SAMPLED * count // s.chunks))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for v in views(batch, s):
                if len(v.anchors):
                    random = np.random.default_rng(v.chunk)
                    own = v.anchors[random.integers(0, len(v.anchors), each)] if anchors else random.integers(v.first, v.end, each)
                    yield pa.RecordBatch.from_arrays([pa.array(v.word(own, 0))], ["w"])

    got = np.sort(np.array([r[0] for r in laid.mapInArrow(run, "w long").collect()], np.int64))
    return np.unique(got[np.arange(1, count) * len(got) // count]) if count > 1 and len(got) else np.zeros(0, np.int64)


def _dealt(bucket: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """Each bucket with its rows, in their order."""
    if not len(bucket):
        return
    order = np.argsort(bucket, kind="stable")
    border = np.flatnonzero(np.r_[True, np.diff(bucket[order]) != 0])
    for a, z in zip(border, np.r_[border[1:], len(order)], strict=True):
        yield int(bucket[order[a]]), order[a:z]


def names(laid: DataFrame, s: Shape) -> tuple[DataFrame, int, int]:
    """(chunk, names) of the chunks' anchors, how many there are and how many tie; a name is twice the number of anchors with lesser words, and 1 more for ties."""
    spark = laid.sparkSession
    r = max(spark.sparkContext.defaultParallelism, -(-s.n // (s.window // 2 * BUCKET)))
    borders = splitters(laid, s, True, r)
    salts, words = spread(spark, r), s.words

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for v in views(batch, s):
                columns, rows = v.columns(v.anchors), []
                for b, own in _dealt(np.searchsorted(borders, columns["w0"], side="right")):
                    rows.append((b, salts[b], v.chunk, packed(i=own.astype(np.uint32), **{k: x[own] for k, x in columns.items()})))
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), (pa.int32(), pa.int32(), pa.int64(), pa.binary()), strict=True)], ["bucket", "salt", "chunk", "batch"])

    def sort(table: pa.Table) -> pa.Table:
        chunks, parts = table["chunk"].to_pylist(), [unpacked(x) for x in table["batch"].to_pylist()]
        order, place = partial.refine_columns([np.concatenate([p[f"w{j}"] for p in parts]) for j in range(words)])
        tied = partial._tied(place)
        name = np.empty(len(order), np.int64)
        name[order] = 2 * place + tied
        ends = np.cumsum([len(p["i"]) for p in parts])
        out = [packed(i=p["i"], name=name[z - len(p["i"]) : z]) for p, z in zip(parts, ends, strict=True)]
        n = len(chunks)
        return pa.table({"bucket": table["bucket"], "chunk": table["chunk"], "rows": pa.array([len(p["i"]) for p in parts], pa.int64()), "tied": pa.array([int(tied.sum())] + [0] * (n - 1), pa.int64()), "batch": pa.array(out, pa.binary())})

    local = cut(laid.mapInArrow(deal, "bucket int, salt int, chunk long, batch binary").repartition(r, "salt").groupBy("salt").applyInArrow(sort, "bucket int, chunk long, rows long, tied long, batch binary"))
    release(spark, at_once=True)
    counts = {x[0]: (x[1], x[2]) for x in local.groupBy("bucket").agg(F.sum("rows"), F.sum("tied")).collect()}
    before, total = {}, 0
    for b in sorted(counts):
        before[b] = total
        total += counts[b][0]

    def place(table: pa.Table) -> pa.Table:
        parts = [unpacked(x) for x in table["batch"].to_pylist()]
        out = np.empty(sum(len(p["i"]) for p in parts), np.int64)
        for b, p in zip(table["bucket"].to_pylist(), parts, strict=True):
            out[p["i"]] = p["name"] + 2 * before[b]
        return pa.table({"chunk": table["chunk"][:1], "rows": pa.array([len(out)], pa.int64()), "names": pa.array([packed(c=out)], pa.binary())})

    placed = cut(local.select("chunk", "bucket", "batch").groupBy("chunk").applyInArrow(place, "chunk long, rows long, names binary"))
    return placed, total, sum(x[1] for x in counts.values())


def _each(column: str, f: Callable[[np.ndarray], np.ndarray]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch["chunk"], pa.array([packed(c=f(unpacked(x)["c"])) for x in batch[column].to_pylist()], pa.binary())], ["chunk", "ranks"])

    return run


def ranks_of_names(names: np.ndarray) -> np.ndarray:
    """Ranks of the suffixes of a text of names on one machine, by doubling; only places that still tie take part."""
    rank, active, h = names >> 1, np.flatnonzero(names & 1), 1
    while len(active):
        second = np.full(len(active), -1, np.int64)
        inside = active + h < len(rank)
        second[inside] = rank[active[inside] + h]
        own = np.lexsort((second, rank[active]))
        active, second = active[own], second[own]
        group = rank[active]
        old = np.r_[True, group[1:] != group[:-1]]
        new = np.flatnonzero(old | np.r_[True, second[1:] != second[:-1]])
        first, size = np.flatnonzero(old), np.diff(np.r_[new, len(active)])
        base = first[np.searchsorted(first, new, side="right") - 1]
        rank[active] = np.repeat(group[new] + new - base, size)
        active = active[np.repeat(size > 1, size)]
        h *= 2
    return rank


def ranked(laid: DataFrame, s: Shape) -> tuple[DataFrame, int]:
    """(chunk, codes, found, ranks), and the number of anchors: the ranks of a chunk's anchors among all, as suffixes."""
    spark = laid.sparkSession
    named, m, tied = names(laid, s)
    release(spark, at_once=True)
    if not tied:
        ranks = named.mapInArrow(_each("names", lambda c: fewest(c >> 1, m)), "chunk long, ranks binary")
    elif m <= ALONE or 2 * m > s.n:  # long runs of one name don't get shorter

        def alone(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            rows = sorted((x, y) for batch in batches for x, y in zip(batch["chunk"].to_pylist(), batch["names"].to_pylist(), strict=True))
            if rows:
                parts = [unpacked(y)["c"] for _, y in rows]
                rank, at = fewest(ranks_of_names(np.concatenate(parts)), m), 0
                for (x, _), p in zip(rows, parts, strict=True):
                    yield pa.RecordBatch.from_arrays([pa.array([x], pa.int64()), pa.array([packed(c=rank[at : at + len(p)])], pa.binary())], ["chunk", "ranks"])
                    at += len(p)

        ranks = named.select("chunk", "names").repartition(1).mapInArrow(alone, "chunk long, ranks binary")
    else:
        ranks = _by_names(named, m)
    parts = _partitions(spark, s)
    return cut(laid.repartition(parts, "chunk").join(ranks.repartition(parts, "chunk"), "chunk")), m


def _partitions(spark: SparkSession, s: Shape) -> int:
    return max(1, min(s.chunks, max(4 * spark.sparkContext.defaultParallelism, s.chunks // 16)))


def _by_names(named: DataFrame, m: int) -> DataFrame:
    """(chunk, ranks) of named anchors that one task can't rank: the names are a text, whose own anchors are ranked, and only tied ones are sorted."""
    spark = named.sparkSession
    counts = sorted((x[0], x[1]) for x in named.select("chunk", "rows").collect())
    ids, starts = np.array([x[0] for x in counts], np.int64), np.r_[0, np.cumsum([x[1] for x in counts])].astype(np.int64)
    s = shape(m, int(2 * m + 1).bit_length(), names=True)

    def as_pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            at = starts[np.searchsorted(ids, batch["chunk"].to_numpy())]
            yield pa.RecordBatch.from_arrays([pa.array(at), pa.array([unpacked(x)["c"].astype("<i8").tobytes() for x in batch["names"].to_pylist()], pa.binary())], ["start", "codes"])

    laid = lay(named.select("chunk", "names").mapInArrow(as_pieces, "start long, codes binary"), s, np.dtype("<i8"), _partitions(spark, s))
    known, _ = ranked(laid, s)
    r = max(spark.sparkContext.defaultParallelism, -(-m // BUCKET))
    salts, words = spread(spark, r), s.words

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for v, ranks in zip(views(batch, s), batch["ranks"].to_pylist(), strict=True):
                places = v.first + np.flatnonzero((v.symbols[v.first : v.end] - 1) & 1)
                if not len(places):
                    continue
                columns = {"pos": v.start + places, "start": (v.symbols[places].astype(np.int64) - 1) >> 1, **v.columns(places), "rank": unpacked(ranks)["c"][v.number(places)]}
                rows = [(salts[b], packed(**{k: x[some] for k, x in columns.items()})) for b, some in _dealt(columns["start"] * r // m)]
                yield pa.RecordBatch.from_arrays([pa.array([x for x, _ in rows], pa.int32()), pa.array([x for _, x in rows], pa.binary())], ["salt", "batch"])

    def sort(table: pa.Table) -> pa.Table:
        parts = [unpacked(x) for x in table["batch"].to_pylist()]
        c = {k: np.concatenate([p[k] for p in parts]) for k in parts[0]}
        order, _ = partial.refine_columns([*(c[f"w{j}"] for j in range(words)), c["rank"]])
        start, pos = c["start"][order], c["pos"][order]
        first = np.flatnonzero(np.r_[True, start[1:] != start[:-1]])
        rank = start + np.arange(len(start)) - np.repeat(first, np.diff(np.r_[first, len(start)]))
        of = np.searchsorted(starts, pos, side="right") - 1
        rows = [(int(ids[k]), packed(i=pos[some] - starts[k], rank=rank[some])) for k, some in _dealt(of)]
        return pa.table({"chunk": pa.array([x for x, _ in rows], pa.int64()), "batch": pa.array([x for _, x in rows], pa.binary())})

    found = known.mapInArrow(deal, "salt int, batch binary").repartition(r, "salt").groupBy("salt").applyInArrow(sort, "chunk long, batch binary")

    def merge(left: pa.Table, right: pa.Table) -> pa.Table:
        out = unpacked(left["names"][0].as_py())["c"] >> 1
        for raw in right["batch"].to_pylist():
            p = unpacked(raw)
            out[p["i"]] = p["rank"]
        return pa.table({"chunk": left["chunk"], "ranks": pa.array([packed(c=fewest(out, m))], pa.binary())})

    return named.select("chunk", "names").groupBy("chunk").cogroup(found.groupBy("chunk")).applyInArrow(merge, "chunk long, ranks binary")


@dataclass
class Turns:
    """The buckets of all suffixes, a few at a time: `each` applies a function to (bucket, positions in suffix order, first symbols, symbols before)."""

    known: DataFrame
    shape: Shape
    borders: np.ndarray
    count: int
    end: int

    @property
    def buckets(self) -> int:
        return len(self.borders) + 1

    def each(self, turn: int, f: Callable[[int, np.ndarray, np.ndarray, np.ndarray], pa.Table], schema: str) -> DataFrame:
        s, borders, end = self.shape, self.borders, self.end
        low, high = self.buckets * turn // self.count, self.buckets * (turn + 1) // self.count
        salts, words, lead = spread(self.known.sparkSession, max(1, high - low)), s.words, s.width * (s.take - s.base)

        def flush(held: dict[int, list[dict]]) -> Iterator[pa.RecordBatch]:
            for b, parts in sorted(held.items()):
                c = {k: np.concatenate([p[k] for p in parts]) for k in parts[0]}
                c["pos"] = np.diff(c["pos"], prepend=0)  # close together, so that they compress
                yield pa.RecordBatch.from_arrays([pa.array([b], pa.int32()), pa.array([salts[b - low]], pa.int32()), pa.array([packed(**c)], pa.binary())], ["bucket", "salt", "batch"])
            held.clear()

        def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            held, rows = {}, 0
            for batch in batches:
                for v, ranks in zip(views(batch, s), batch["ranks"].to_pylist(), strict=True):
                    # by the leading symbols of the borders first, then by the borders
                    key, own = v.keys[v.first : v.end], None
                    if low:
                        own = key >= borders[low - 1] >> lead
                    if high <= len(borders):
                        under = key <= borders[high - 1] >> lead
                        own = under if own is None else own & under
                    places = v.first + (np.arange(len(key)) if own is None else np.flatnonzero(own))
                    bucket = np.searchsorted(borders, v.word(places, 0), side="right")
                    own = (bucket >= low) & (bucket < high)
                    places, bucket = places[own], bucket[own]
                    before = np.where(places + v.start > 0, v.symbols[np.maximum(places - 1, 0)] - 1, end)
                    columns = {"pos": v.start + places, "before": fewest(before, 1 << s.width), **v.columns(places), "rank": unpacked(ranks)["c"][v.number(places)]}
                    for b, some in _dealt(bucket):
                        held.setdefault(b, []).append({k: x[some] for k, x in columns.items()})
                    rows += len(places)
                    if rows >= HELD:
                        yield from flush(held)
                        rows = 0
            yield from flush(held)

        def sort(table: pa.Table) -> pa.Table:
            parts = [unpacked(x) for x in table["batch"].to_pylist()]
            pos = np.concatenate([np.cumsum(p.pop("pos")) for p in parts])
            order, _ = partial.refine_columns([np.concatenate([p[k] for p in parts]) for k in (*(f"w{j}" for j in range(words)), "rank")])
            first = np.concatenate([p["w0"] for p in parts])[order] >> (s.width * (s.take - 1))
            return f(table["bucket"][0].as_py(), pos[order], first - 1, np.concatenate([p["before"] for p in parts])[order].astype(np.int64))

        return self.known.mapInArrow(deal, "bucket int, salt int, batch binary").repartition(max(1, high - low), "salt").groupBy("salt").applyInArrow(sort, schema)


def turns(corpus: Corpus, count: int = TURNS, buckets: int | None = None, size: int | None = None, split: Callable[[int], np.ndarray] | None = None) -> Turns:
    """Anchors ranked, and the suffixes' buckets by sampled first words. split: gives the first words between so many buckets instead."""
    spark = corpus.pieces.sparkSession
    s = shape(corpus.n, kmers.bits(corpus), size=size)
    laid = lay(corpus.pieces, s, CODE, _partitions(spark, s))
    release(spark, at_once=True)
    known, _ = ranked(laid, s)
    del laid
    release(spark, at_once=True)
    buckets = buckets or count * max(1, -(-corpus.n // (count * BUCKET)))
    borders = split(buckets) if split else splitters(known.select("chunk", "codes", "found"), s, False, buckets)
    release(spark, at_once=True)
    return Turns(known, s, borders, min(count, len(borders) + 1), corpus.terminator)


def suffix_order(own: Turns) -> DataFrame:
    """(bucket, ord, pos, code) of all suffixes, in one turn."""

    def rows(bucket: int, pos: np.ndarray, first: np.ndarray, before: np.ndarray) -> pa.Table:
        return pa.table({"bucket": pa.array(np.full(len(pos), bucket, np.int32)), "ord": pa.array(np.arange(len(pos))), "pos": pa.array(pos), "code": pa.array(before.astype(np.int32))})

    return own.each(0, rows, "bucket int, ord long, pos long, code int")
