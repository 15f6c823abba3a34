"""Token counts with the whole-token shortcut."""

from __future__ import annotations

import json
import os
from collections.abc import Iterator

import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: How byte-level vocabularies split a text before merging, and the code points over which
#: the local regular expressions are compared with the library's own splitting.
SPLIT = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
PROVEN = 0x10000
#: Entries of a worker's memo of merged pre-tokens; it starts anew beyond that.
MEMO = 400_000


def library(source: str):
    os.environ["TOKENIZERS_PARALLELISM"] = "false"
    from tokenizers import Tokenizer

    t = Tokenizer.from_str(source)
    t.no_padding()
    t.no_truncation()
    return t


def prove_whole_tokens(source: str) -> tuple[list[str], str, list[str]]:
    """Offline part: which vocabulary strings are one pre-token that encodes alone as one token; which characters
    below PROVEN the local splitting treats differently from the library's; the special strings."""
    t, split = library(source), regex.compile(SPLIT)
    strings = [s for s in t.decode_batch([[i] for i in range(t.get_vocab_size())], skip_special_tokens=False) if s and "�" not in s]
    special = sorted((x["content"] for x in json.loads(source)["added_tokens"]), key=len, reverse=True)
    alone = [s for s in dict.fromkeys(strings) if s not in special and split.findall(s) == [s]]
    whole = [s for s, e in zip(alone, t.encode_batch(alone, add_special_tokens=False), strict=True) if len(e.ids) == 1]
    odd, left = [], [[chr(i) for i in range(low, low + 512) if not 0xD800 <= i < 0xE000] for low in range(0, PROVEN, 512)]
    while left:  # many characters in one probe, which is halved where it shows a difference
        own = left.pop()
        probe = "".join(f"a{c}b1{c} {c}{c}.{c}\n" for c in own)
        if [x for _, x in t.pre_tokenizer.pre_tokenize_str(probe)] == [m.span() for m in split.finditer(probe)]:
            continue
        if len(own) == 1:
            odd += own
        else:
            left += [own[: len(own) // 2], own[len(own) // 2 :]]
    return whole, "".join(sorted(odd)), special


class Counter:
    """Counts the tokens of texts as the library does; one for each worker."""

    def __init__(self, source: str, proof: tuple[list[str], str, list[str]]):
        whole, odd, special = proof
        self.library, self.split = library(source), regex.compile(SPLIT).findall
        self.whole = dict.fromkeys(whole, 1)
        self.memo = dict(self.whole)
        self.unproven = regex.compile(f"[^\\x00-{chr(PROVEN - 1)}]" + (f"|[{regex.escape(odd)}]" if odd else "")).search
        self.special = regex.compile("|".join(map(regex.escape, special))) if special else None

    def _merge(self, pieces: set[str]) -> None:
        for s, e in zip(pieces, self.library.encode_batch_fast(list(pieces), add_special_tokens=False), strict=True):
            self.memo[s] = len(e)

    def count(self, text: str) -> int:
        if not text:
            return 0
        if not text.isascii() and self.unproven(text):
            return len(self.library.encode(text, add_special_tokens=False))
        total, parts = 0, [text]
        if self.special and self.special.search(text):
            parts = self.special.split(text)
            total = len(parts) - 1
        for part in parts:
            pieces = self.split(part)
            try:
                total += sum(map(self.memo.__getitem__, pieces))
            except KeyError:
                if len(self.memo) > MEMO:
                    self.memo = dict(self.whole)
                self._merge({x for x in set(pieces) if x not in self.memo})
                total += sum(map(self.memo.__getitem__, pieces))
        return total


_COUNTERS: dict[int, Counter] = {}


def count_tokens(docs: DataFrame, path: str, text: str = "text") -> DataFrame:
    """Adds n_tokens to documents (doc_id, text): null and empty texts have none; all rows stay, repeated ones too.

    Only byte-level vocabularies of the tokenizers library. Texts with characters beyond the proven range go through the library as a
    whole, so the counts are its own in any case. What is broadcast is the vocabulary: its size does not grow with the corpus.
    """
    with open(path, encoding="utf-8") as f:
        source = f.read()
    shared = docs.sparkSession.sparkContext.broadcast((source, prove_whole_tokens(source)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key = hash(shared.value[0])
        counter = _COUNTERS.get(key) or _COUNTERS.setdefault(key, Counter(*shared.value))
        for batch in batches:
            counts = [counter.count(x.as_py() or "") for x in batch["text"]]
            yield pa.RecordBatch.from_arrays([batch["doc_id"], batch["n_bytes"], pa.array(counts, pa.int64())], ["doc_id", "n_bytes", "n_tokens"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("text")).withColumn("n_bytes", F.octet_length("text").cast("long")).mapInArrow(run, "doc_id long, n_bytes long, n_tokens long")


def token_report(docs: DataFrame, path: str, limit: int = 1024) -> DataFrame:
    return count_tokens(docs, path).withColumn("over_limit", F.col("n_tokens") > limit)
