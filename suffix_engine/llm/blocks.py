"""Blocks and buckets: the exchange that several corpus operators share.

Documents are dealt into *blocks* by a hash of their id and text (one shuffle of the texts, reused by both
passes).  A block packs what it must ask about its content into compressed bundles for the
*buckets*; equal items inside a block are asked about once, so a passage that a third of all
documents hold costs a bucket one item for each block and not one for each document.  A bucket
answers every block in one bundle, and the block, computing its items again in the same order,
applies the answers to its documents.

A block sends at most FAN bundles.  Where there are more buckets than that, items go in two passes, as in
radix partitioning: a bundle holds a range of buckets, a *relay* takes the bundles of many blocks for one
range and deals them to its buckets, and the answers go back the same way.  So the rows of the exchange grow
with the blocks alone.  No task ever sees more than a block, a relay or a bucket, and nothing
goes through the driver.  A lost executor only makes Spark run some of these deterministic tasks again.
"""

from __future__ import annotations

import hashlib
import struct
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from typing import Any

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Bytes of text aimed at for a block, and bundles that it sends at most.
BLOCK_BYTES, FAN = 12 << 20, 8192
#: Stands for a null document id: it sorts after all others.
NO_ID = np.int64(2**63 - 1)

TILE = 1 << 16
_POS = np.uint64((1 << 18) - 1)
_TOP = np.uint64(0xFFFFFFFFFFFFFFFF)
_STEP = np.uint64(0x9FB21C651E98DF25)
#: The first n bytes of a word of eight.
_FIRST = np.array([(1 << 8 * n) - 1 for n in range(9)], np.uint64)
#: Bytes of a range that are hashed eight at a time; what lies behind them is digested whole.
_LONG = 256


def mix(h: np.ndarray) -> np.ndarray:
    """A permutation of the 64-bit numbers under which all bits of the result depend on all bits."""
    h = h ^ (h >> np.uint64(32))
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(32)
    h *= np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(32)
    return h


def words_at(b: np.ndarray) -> np.ndarray:
    """The eight bytes from each place on as one number, bytes 0 past the end."""
    padded = np.zeros(len(b) + 8, np.uint8)
    padded[: len(b)] = b
    return np.ndarray(len(b) + 1, "<u8", padded, strides=(1,))


def range_hashes(b: np.ndarray, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
    """64-bit hashes of the ranges [begin, end): each eight bytes are mixed into all that came before.

    No structure of a text carries through the mixing, as it does through sums of powers. Ranges of one length up to eight bytes have
    equal hashes only if they are equal. Equal hashes of longer ones are unlikely and no proof: where identity
    decides, bytes are compared or digested.
    """
    word, size = words_at(b), end - begin
    out = mix(size.astype(np.uint64) * _STEP + _STEP)
    left, done = np.flatnonzero(size > 0), 0
    while len(left) and done < _LONG:
        n = np.minimum(size[left] - done, 8)
        out[left] = mix((out[left] ^ (word[begin[left] + done] & _FIRST[n])) * _STEP)
        done += 8
        left = left[size[left] > done]
    for i in left.tolist():
        rest = hashlib.blake2b(b[begin[i] + done : end[i]], digest_size=8).digest()
        out[i] ^= np.uint64(int.from_bytes(rest, "little"))
    return out


def chained(h: np.ndarray, k: int) -> np.ndarray:
    """Hashes of all k neighbouring entries."""
    if len(h) < k:
        return np.zeros(0, np.uint64)
    out = np.zeros(len(h) - k + 1, np.uint64)
    for j in range(k):
        out = mix(out * _STEP + h[j : len(h) - k + 1 + j])
    return out


def digests(parts: Iterator[bytes]) -> np.ndarray:
    """Cryptographic digests of 128 bits, as rows of two numbers: what they tell apart is told apart for good."""
    out = b"".join(hashlib.blake2b(x, digest_size=16).digest() for x in parts)
    return np.frombuffer(out, np.uint64).reshape(-1, 2)


def numbered(raw: bytes, begin: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A number for each range, equal for equal bytes, in the order of first occurrence; and which ranges came first. Exact."""
    seen: dict[bytes, int] = {}
    number = np.fromiter((seen.setdefault(raw[a:z], len(seen)) for a, z in zip(begin.tolist(), end.tolist(), strict=True)), np.int64, len(begin))
    first = np.zeros(len(number), bool)
    if len(number):
        first[0] = True
        first[1:] = number[1:] > np.maximum.accumulate(number)[:-1]
    return number, np.flatnonzero(first)


class Docs:
    """The documents of a block, in the order of their ids: one buffer of bytes and its bounds."""

    def __init__(self, table: pa.Table):
        #: All columns, in the order of the documents.
        self.table = table = table.sort_by([("doc_id", "ascending"), ("text", "ascending")])
        self.raw_ids = table["doc_id"].combine_chunks()
        self.ids = pc.fill_null(self.raw_ids.cast(pa.int64()), int(NO_ID)).to_numpy(zero_copy_only=False)
        text = pc.fill_null(table["text"].cast(pa.large_string()), "").combine_chunks()
        if isinstance(text, pa.ChunkedArray):
            text = pa.concat_arrays(text.chunks) if text.num_chunks else pa.array([], pa.large_string())
        offsets = np.frombuffer(text.buffers()[1], np.int64)[text.offset : text.offset + len(text) + 1] if len(text) else np.zeros(1, np.int64)
        data = text.buffers()[2]
        whole = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
        self.bytes = whole[offsets[0] : offsets[-1]]
        self.bounds = offsets - offsets[0]

    def __len__(self) -> int:
        return len(self.ids)


def pack(arrays: list[np.ndarray]) -> bytes:
    """Numbers that ascend are stored as differences, and bytes of equal weight stand together."""
    parts = [struct.pack("<I", len(arrays))]
    for a in arrays:
        a = np.ascontiguousarray(a)
        rising = a.dtype.kind == "u" and a.itemsize > 1 and len(a) > 1 and bool((a[1:] >= a[:-1]).all())
        if rising:
            a = np.diff(a, prepend=a.dtype.type(0))
        parts += [struct.pack("<4s?Q", a.dtype.str.encode(), rising, a.nbytes), a.view(np.uint8).reshape(-1, a.itemsize).T.tobytes()]
    return zstandard.ZstdCompressor(level=5).compress(b"".join(parts))


def unpack(blob: bytes) -> list[np.ndarray]:
    raw = zstandard.ZstdDecompressor().decompress(blob)
    (n,), at, out = struct.unpack_from("<I", raw), 4, []
    for _ in range(n):
        kind, rising, size = struct.unpack_from("<4s?Q", raw, at)
        dtype = np.dtype(kind.rstrip(b"\0").decode())
        planes = np.frombuffer(raw, np.uint8, size, at + 13).reshape(dtype.itemsize, -1)
        a = np.ascontiguousarray(planes.T).reshape(-1).view(dtype)
        out.append(np.cumsum(a, dtype=dtype) if rising else a)
        at += 13 + size
    return out


def spread(starts: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """The positions of all ranges, one range after another."""
    ends = np.cumsum(lengths)
    return np.repeat(starts - (ends - lengths), lengths) + np.arange(int(ends[-1]) if len(ends) else 0)


def gathered(raw: bytes, begin: np.ndarray, end: np.ndarray) -> np.ndarray:
    """The bytes of all ranges, one range after another, without an index of every byte."""
    return np.frombuffer(b"".join([raw[a:z] for a, z in zip(begin.tolist(), end.tolist(), strict=True)]), np.uint8)


def portions(batch: pa.RecordBatch, column: str, most: int) -> Iterator[pa.RecordBatch]:
    """A batch by rows of about that many bytes in a column, one row at least."""
    size = pc.fill_null(pc.binary_length(batch[column].cast(pa.large_binary())), 0).to_numpy(zero_copy_only=False)
    part = np.cumsum(size) // most
    for i, j in runs_in(part):
        yield batch.slice(i, j - i)


@dataclass
class Items:
    """What is asked, an entry for each item: its bucket, columns of numbers, and bytes of any length."""

    bucket: np.ndarray
    columns: list[np.ndarray]
    size: np.ndarray
    data: np.ndarray

    def __len__(self) -> int:
        return len(self.bucket)

    def taken(self, at: np.ndarray) -> Items:
        begin = np.cumsum(self.size) - self.size
        data = gathered(self.data.tobytes(), begin[at], begin[at] + self.size[at]) if len(self.data) else self.data
        return Items(self.bucket[at], [c[at] for c in self.columns], self.size[at], data)

    def between(self, i: int, j: int) -> Items:
        edge = np.r_[0, np.cumsum(self.size)] if len(self.data) else np.zeros(len(self) + 1, np.int64)
        return Items(self.bucket[i:j], [c[i:j] for c in self.columns], self.size[i:j], self.data[edge[i] : edge[j]])

    def packed(self) -> bytes:
        return pack([self.bucket.astype(np.uint32), self.size.astype(np.uint32), self.data, *self.columns])

    @staticmethod
    def joined(blobs: list[bytes]) -> tuple[Items, np.ndarray]:
        """All items of some bundles, and where each bundle's begin (one more entry than bundles)."""
        parts = [unpack(b) for b in blobs]
        bucket, size, data, *columns = (np.concatenate(x) for x in zip(*parts, strict=True))
        return Items(bucket.astype(np.int64), columns, size.astype(np.int64), data), np.cumsum([0, *(len(p[0]) for p in parts)])


class Kernel:
    """What an operator does in blocks and buckets. items must give equal results for equal Docs."""

    #: Schema of what apply returns, as a DDL string.
    schema: str

    def items(self, docs: Docs, n_buckets: int) -> tuple[Items, Any]:
        """The distinct items of a block in the order of their buckets, and whatever apply needs to know of them."""
        raise NotImplementedError

    def answers(self, items: Items) -> np.ndarray:
        """How many answers each item gets."""
        return np.ones(len(items), np.int64)

    def resolve(self, items: Items) -> np.ndarray:
        """The answers (bytes) to all items of a bucket, one item after another. Blocks don't show, and an item may come from several."""
        raise NotImplementedError

    def apply(self, docs: Docs, items: Items, known: Any, answers: np.ndarray) -> dict[str, Any]:
        raise NotImplementedError


def _said(answers: np.ndarray) -> bytes | None:
    if not answers.any():
        return None
    flags = answers.max() == 1
    return pack([np.array([len(answers), flags], np.uint64), np.packbits(answers) if flags else answers])


def _heard(blob: bytes) -> np.ndarray:
    (n, flags), body = unpack(blob)
    return np.unpackbits(body, count=int(n)) if flags else body


def minimiser_runs(n: int, width: int, hashes: Callable[[int, int], np.ndarray], valid: Callable[[int, int], np.ndarray], avoid: np.ndarray) -> tuple[np.ndarray, ...]:
    """Runs of consecutive valid window starts that share a minimiser: first start, count, place and hash of it.

    hashes(i, j): of the grams that start in [i, j), fewer at the end; a window that starts at i has those of
    [i, i + width), and its minimiser is the leftmost of the least. Hashes to avoid (sorted) come after all others.  valid(i, j): which
    starts are whole windows.
    """
    found: list[tuple[np.ndarray, ...]] = []
    for low in range(0, n, TILE):
        high = min(n, low + TILE)
        starts = np.flatnonzero(valid(low, high))
        if not len(starts):
            continue
        h = hashes(low, min(n, high + width - 1))
        least = np.full(high - low + width - 1, _TOP)
        order = h >> np.uint64(1)
        if len(avoid):
            order[avoid[np.minimum(np.searchsorted(avoid, h), len(avoid) - 1)] == h] |= np.uint64(1 << 63)
        least[: len(h)] = (order & ~_POS) | np.arange(len(h), dtype=np.uint64)
        done = 1
        while 2 * done <= width:
            least = np.minimum(least[:-done], least[done:])
            done *= 2
        if done < width:
            least = np.minimum(least[: -(width - done)], least[width - done :])
        at = (least[starts] & _POS).astype(np.int64)
        first = np.flatnonzero(np.r_[True, (at[1:] != at[:-1]) | (np.diff(starts) != 1)])
        found.append((low + starts[first], np.diff(np.r_[first, len(starts)]), low + at[first], h[at[first]]))
    if not found:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint64)
    return tuple(np.concatenate(x) for x in zip(*found, strict=True))


def text_bytes(docs: DataFrame) -> int:
    """Bytes of all texts, counted. Docs should be a table or cheap to compute: this is a pass of its own over one column."""
    return docs.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]


def block_count(docs: DataFrame, size: int | None = None) -> int:
    """At least as many blocks as shuffle partitions, of BLOCK_BYTES of text or a little more."""
    size = text_bytes(docs) if size is None else size
    return max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), size // BLOCK_BYTES + 1)


def runs_in(keys: np.ndarray) -> Iterator[tuple[int, int]]:
    """Begin and end of the runs of equal sorted keys."""
    edges = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1], True]) if len(keys) else np.zeros(1, np.int64)
    return zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True)


def own_columns(docs: DataFrame, keep: tuple[str, ...] = ()) -> tuple[DataFrame, list[tuple[str, str, T.DataType]]]:
    """doc_id and text, and the columns to keep under names that clash with nothing."""
    kept = [(f"_keep_{i}", c, docs.schema[c].dataType) for i, c in enumerate(keep)]
    own: list[Column] = [F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")]
    return docs.select(*own, *(F.col(c).alias(k) for k, c, _ in kept)), kept


def exchange(docs: DataFrame, kernel: Kernel, n_blocks: int | None = None, buckets_per_block: int = 1, keep: tuple[str, ...] = (), fan: int = FAN) -> DataFrame:
    """Runs a kernel over documents (doc_id, text). Of the other columns only those to keep are read; they follow the kernel's."""
    docs, kept = own_columns(docs, keep)
    n = n_blocks or block_count(docs)
    n_buckets = n * buckets_per_block
    n_ranges = min(n_buckets, fan)
    dealt = docs.withColumn("block", F.pmod(F.xxhash64("doc_id", "text"), F.lit(n)).cast("long")).repartition(n, "block")
    names = [x.split()[0] for x in kernel.schema.split(", ")]
    bundle = "source long, target long, payload binary"

    def bundles(source: int, rows: list[tuple[int, bytes]]) -> pa.Table:
        return pa.table({"source": pa.array([source] * len(rows), pa.int64()), "target": pa.array([k for k, _ in rows], pa.int64()), "payload": pa.array([x for _, x in rows], pa.binary())})

    def range_of(bucket: np.ndarray) -> np.ndarray:
        return bucket * n_ranges // n_buckets

    def ask(table: pa.Table) -> pa.Table:
        items, _ = kernel.items(Docs(table), n_buckets)
        to = range_of(items.bucket)
        return bundles(table["block"][0].as_py(), [(int(to[i]), items.between(i, j).packed()) for i, j in runs_in(to)])

    def forward(table: pa.Table) -> pa.Table:
        table = table.sort_by("source")
        items, _ = Items.joined(table["payload"].to_pylist())
        items = items.taken(np.argsort(items.bucket, kind="stable"))
        return bundles(table["relay"][0].as_py(), [(int(items.bucket[i]), items.between(i, j).packed()) for i, j in runs_in(items.bucket)])

    def split(target: int, sources: list[int], answers: np.ndarray, edges: np.ndarray) -> pa.Table:
        parts = [(s, _said(answers[a:z])) for s, a, z in zip(sources, edges[:-1], edges[1:], strict=True)]
        out = [(s, x) for s, x in parts if x is not None]
        return pa.table({"source": pa.array([s for s, _ in out], pa.int64()), "target": pa.array([target] * len(out), pa.int64()), "payload": pa.array([x for _, x in out], pa.binary())})

    def answer(table: pa.Table) -> pa.Table:
        table = table.sort_by("source")
        items, edges = Items.joined(table["payload"].to_pylist())
        at = np.r_[0, np.cumsum(kernel.answers(items))]
        return split(table["target"][0].as_py(), table["source"].to_pylist(), kernel.resolve(items), at[edges])

    def back(left: pa.Table, right: pa.Table) -> pa.Table:
        left = left.sort_by("source")
        items, edges = Items.joined(left["payload"].to_pylist())
        order, n_own = np.argsort(items.bucket, kind="stable"), kernel.answers(items)
        place = np.cumsum(n_own) - n_own
        got = np.zeros(int(n_own.sum()), np.uint8)
        said = {k.as_py(): x.as_py() for k, x in zip(right["target"], right["payload"], strict=True)}
        for i, j in runs_in(items.bucket[order]):
            if (x := said.get(int(items.bucket[order[i]]))) is not None:
                own = order[i:j]
                got[spread(place[own], n_own[own])] = _heard(x)
        return split(left["target"][0].as_py(), left["source"].to_pylist(), got, np.r_[place, len(got)][edges])

    def finish(left: pa.Table, right: pa.Table) -> pa.Table:
        own = Docs(left)
        items, known = kernel.items(own, n_buckets)
        n_own = kernel.answers(items)
        at, to = np.r_[0, np.cumsum(n_own)], range_of(items.bucket)
        got = np.zeros(int(at[-1]), np.uint8)
        said = {k.as_py(): x.as_py() for k, x in zip(right["target"], right["payload"], strict=True)}
        for i, j in runs_in(to):
            if (x := said.get(int(to[i]))) is not None:
                got[at[i] : at[j]] = _heard(x)
        return pa.table({"doc_id": own.raw_ids} | kernel.apply(own, items, known, got) | {k: own.table[k] for k, _, _ in kept}).select([*names, *(k for k, _, _ in kept)])

    asked = dealt.groupBy("block").applyInArrow(ask, bundle)
    if n_ranges < n_buckets:
        groups = -(-n // fan)
        relayed = asked.withColumn("relay", F.col("target") * groups + F.floor(F.col("source") / fan))
        told = relayed.groupBy("relay").applyInArrow(forward, bundle).groupBy("target").applyInArrow(answer, bundle)
        told = relayed.groupBy("relay").cogroup(told.groupBy("source")).applyInArrow(back, bundle)
    else:
        told = asked.groupBy("target").applyInArrow(answer, bundle)
    schema = T.StructType.fromDDL(kernel.schema)
    for k, _, kind in kept:
        schema = schema.add(k, kind)
    return dealt.groupBy("block").cogroup(told.groupBy("source")).applyInArrow(finish, schema).withColumnsRenamed({k: c for k, c, _ in kept})
