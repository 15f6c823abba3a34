"""Benchmark decontamination with one automaton over the normalised items."""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Bytes that are not in words become spaces, A-Z becomes a-z; bytes from 0x80 on are parts of words.
_CLEAN = bytes(c + 32 if 65 <= c <= 90 else c if 48 <= c <= 57 or 97 <= c <= 122 or c >= 128 else 32 for c in range(256))
_WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
#: Bytes of benchmark text that one automaton takes, checked before anything is read to the driver; what lies beyond gets one of its own.
AUTOMATON_BYTES = 64 << 20


def words_of(text: str | None) -> list[str]:
    return (text or "").encode().translate(_CLEAN).decode().split(" ")


def normalised(text: str | None) -> list[str]:
    return [w for w in words_of(text) if w]


class Items:
    """One automaton over benchmark items, of a size in proportion to their text.

    Of a window's size words, any window holds a whole block of (size + 1) // 2 words that starts at a multiple of that in its item.
    The automaton has these blocks, each with the different contexts it stands in (up to as many words on either side as a window can
    reach) and the items that have them. Where a block occurs, a context that agrees far enough makes up windows, and
    no window occurs without its block. Items of fewer words than a window are one block without a context.
    """

    def __init__(self, items: list[tuple[str, str]], size: int):
        self.size, anchor = size, (size + 1) // 2
        reach = size - anchor
        blocks: dict[str, dict[tuple[tuple[str, ...], tuple[str, ...]], set[str]]] = {}
        for key, text in items:
            w = text.split(" ") if text else []
            n = anchor if len(w) >= size else max(len(w), 1)
            for i in range(0, len(w) - n + 1, n):
                context = (tuple(w[max(0, i - reach) : i][::-1]), tuple(w[i + n : i + n + reach])) if len(w) >= size else ((), ())
                blocks.setdefault(f" {' '.join(w[i : i + n])} ", {}).setdefault(context, set()).add(key)
        self.find = ahocorasick.Automaton()
        for block, contexts in blocks.items():
            self.find.add_word(block, (block.count(" ") - 1, [(*c, tuple(keys)) for c, keys in contexts.items()]))
        self.empty = not blocks
        if blocks:
            self.find.make_automaton()

    def occurrences(self, line: str) -> tuple[list[tuple[int, int]], set[str]]:
        """The ranges of words that lie in windows, and the items of these; line: words with a space around each."""
        spans: list[tuple[int, int]] = []
        own: set[str] = set()
        found = [] if self.empty else list(self.find.iter(line))
        if not found:
            return spans, own
        spaces = np.flatnonzero(np.frombuffer(line.encode("utf-32-le"), np.uint32) == 32)
        words = line[1:-1].split(" ")
        for end, (n, contexts) in found:
            last = int(np.searchsorted(spaces, end))
            first = last - n
            for before, after, keys in contexts:
                a, z = first, last
                for w in before:
                    if not a or words[a - 1] != w:
                        break
                    a -= 1
                for w in after:
                    if z == len(words) or words[z] != w:
                        break
                    z += 1
                # a block of a longer item counts as part of a window only; that of a short item is one
                if z - a >= self.size or not (before or after):
                    spans.append((a, z))
                    own.update(keys)
        return _union(spans), own


def portions(rows: Iterator[tuple[object, str | None]], most: int) -> Iterator[list[tuple[str, str]]]:
    """Normalised items, by as many as one automaton takes."""
    own: list[tuple[str, str]] = []
    chars = 0
    for key, text in rows:
        if chars > most:
            yield own
            own, chars = [], 0
        own.append(("" if key is None else str(key), " ".join(normalised(text))))
        chars += len(text or "")
    if own:
        yield own


_BUILT: dict[bytes, Items] = {}


def scan(docs: DataFrame, benchmark: DataFrame, size: int = 13, keep: tuple[str, ...] = (), rename: bool = True) -> DataFrame:
    """doc_id, n_words, the words hit (begin, end in word numbers), their spans in the original text (in characters) and the item ids.

    The benchmark's bytes are counted first. Up to AUTOMATON_BYTES of them are one broadcast, one automaton and one scan; a larger benchmark is
    read through an iterator in portions of that size, each with a scan of its own, and the results are united. Null and empty texts have no words; an item
    without words never occurs; items with one id count as one, a null id as the empty string. All rows stay, repeated ones too.
    Empty tables are fine on both sides. Of the other columns only those to keep are read.
    """
    sc = docs.sparkSession.sparkContext
    hit = "array<struct<begin:bigint,end:bigint>>"
    kept = [(f"_keep_{i}", c, docs.schema[c].dataType) for i, c in enumerate(keep)]
    schema = T.StructType.fromDDL(f"doc_id long, text string, n_words long, words {hit}, items array<string>")
    for k, _, kind_ in kept:
        schema = schema.add(k, kind_)
    out = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"), F.lit(0).cast("long").alias("n_words"), F.lit(None).cast(hit).alias("words"), F.lit(None).cast("array<string>").alias("items"), *(F.col(c).alias(k) for k, c, _ in kept))
    given = benchmark.select(F.col("item_id"), F.col("text").cast("string").alias("text"))
    small = given.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0] <= AUTOMATON_BYTES
    rows = given.collect() if small else given.toLocalIterator()
    kind = pa.list_(pa.struct([("begin", pa.int64()), ("end", pa.int64())]))

    def pass_over(shared):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            digest, own_items = shared.value
            if digest not in _BUILT:
                _BUILT.clear()
                _BUILT[digest] = Items(own_items, size)
            index = _BUILT[digest]
            for batch in batches:
                n_words, ranges, items = [], [], []
                for text, old, names in zip(batch["text"], batch["words"], batch["items"], strict=True):
                    w = text.as_py().encode().translate(_CLEAN).split()
                    spans, own = index.occurrences(f" {b' '.join(w).decode()} ")
                    n_words.append(len(w))
                    if old.is_valid:
                        spans = _union([*spans, *((x["begin"], x["end"]) for x in old.as_py())])
                        own = own.union(names.as_py())
                    ranges.append([{"begin": a, "end": b} for a, b in spans])
                    items.append(sorted(own))
                yield pa.RecordBatch.from_arrays([batch["doc_id"], batch["text"], pa.array(n_words, pa.int64()), pa.array(ranges, kind), pa.array(items, pa.list_(pa.string())), *(batch[k] for k, _, _ in kept)], ["doc_id", "text", "n_words", "words", "items", *(k for k, _, _ in kept)])

        return run

    for own in [*portions(((r[0], r[1]) for r in rows), AUTOMATON_BYTES)] or [[]]:
        digest = hashlib.blake2b(repr((size, own)).encode(), digest_size=16).digest()
        out = out.mapInArrow(pass_over(sc.broadcast((digest, own))), schema)
    return out.withColumnsRenamed({k: c for k, c, _ in kept}) if rename else out


def _union(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1] = (out[-1][0], max(b, out[-1][1]))
        else:
            out.append((a, b))
    return out


def original_spans(text: str, words: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Ranges of words as ranges of characters of the original text."""
    at = [m.span() for m in _WORD.finditer(text)]
    return [(at[a][0], at[b - 1][1]) for a, b in words]


def _hits():
    return F.aggregate("words", F.lit(0).cast("long"), lambda s, x: s + x["end"] - x["begin"])


def clean(docs: DataFrame, benchmark: DataFrame, size: int = 13) -> DataFrame:
    """The documents that are not contaminated, with all their columns; a null text becomes an empty one."""
    rest = tuple(c for c in docs.columns if c not in ("doc_id", "text"))
    hits = _hits()
    kept = scan(docs, benchmark, size, rest, rename=False).where((hits == 0) | (20 * hits < F.col("n_words")))
    return kept.select("doc_id", "text", *(F.col(f"_keep_{i}").alias(c) for i, c in enumerate(rest))).select(docs.columns)


def contamination(docs: DataFrame, benchmark: DataFrame, size: int = 13) -> DataFrame:
    """n_hit words of n_words are in windows of n_items items; contaminated if they are a twentieth of all words."""
    out = scan(docs, benchmark, size).select("doc_id", "n_words", _hits().alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"))
    return out.withColumn("contaminated", (F.col("n_hit") > 0) & (20 * F.col("n_hit") >= F.col("n_words")))


def with_spans(docs: DataFrame, benchmark: DataFrame, size: int = 13) -> DataFrame:
    """The scan's rows with the hit passages as character offsets of the original text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("begin", pa.int64()), ("end", pa.int64())]))
        for batch in batches:
            spans = [[{"begin": a, "end": b} for a, b in original_spans(t.as_py(), [(x["begin"], x["end"]) for x in w.as_py()])] for t, w in zip(batch["text"], batch["words"], strict=True)]
            yield pa.RecordBatch.from_arrays([batch["doc_id"], pa.array(spans, kind), batch["items"]], ["doc_id", "spans", "items"])

    return scan(docs, benchmark, size).mapInArrow(run, "doc_id long, spans array<struct<begin:bigint,end:bigint>>, items array<string>")
