"""k-mers of a text, packed in 63 bits."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from suffix_engine.model import CODE, KMER, Corpus
from suffix_engine.operators.corpus import chunks
from suffix_engine.session import cut

CHUNK_SYMBOLS = 1 << 17
#: Words whose keys may be broadcast, and rows of a batch that is handed on.
MOST_WORDS, ROWS = 1 << 18, 1 << 16


def bits(corpus: Corpus) -> int:
    """For a code from 1 on; 0 stands for what lies past the end."""
    return max(1, int(corpus.sigma).bit_length())


def widest(corpus: Corpus) -> int:
    return 63 // bits(corpus)


def pack(codes: np.ndarray, count: int, k: int, width: int) -> np.ndarray:
    """Keys of the k symbols from each of the first count positions on."""
    c = np.zeros(count + k, np.int64)
    have = min(len(codes), count + k)
    c[:have] = codes[:have].astype(np.int64) + 1
    out = np.zeros(count, np.int64)
    for j in range(k):
        out = (out << width) | c[j : j + count]
    return out


def extract(corpus: Corpus, k: int) -> DataFrame:
    """(kmer, pos) of every suffix. The order of keys is that of the first k symbols; no shuffle but that of the chunks."""
    width = bits(corpus)
    if not 1 <= k <= 63 // width:
        raise ValueError(f"k is from 1 to {63 // width} for {corpus.sigma} symbols")
    size, n = CHUNK_SYMBOLS, corpus.n

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start, raw in zip(batch["start"].to_pylist(), batch["codes"].to_pylist(), strict=True):
                own = min(size, n - start)
                yield pa.RecordBatch.from_arrays([pa.array(pack(np.frombuffer(raw, CODE), own, k, width)), pa.array(start + np.arange(own))], ["kmer", "pos"])

    return chunks(corpus, size, k).mapInArrow(run, KMER)


def decode(corpus: Corpus, kmer: int, k: int) -> str:
    """The symbols of a key; past the end is shown as the terminator."""
    width = bits(corpus)
    own = [(kmer >> width * (k - 1 - j)) & ((1 << width) - 1) for j in range(k)]
    return "".join(corpus.symbols[c - 1] if c else corpus.symbols[corpus.terminator] for c in own)


def readable(df: DataFrame, corpus: Corpus, k: int, column: str = "kmer", out: str = "word") -> DataFrame:
    """Adds the symbols of packed keys, by DataFrame functions."""
    width = bits(corpus)
    symbols = F.array(F.lit(corpus.symbols[corpus.terminator]), *(F.lit(s) for s in corpus.symbols))
    one = lambda j: F.get(symbols, F.shiftright(F.col(column), width * (k - 1 - j)).bitwiseAND(F.lit((1 << width) - 1)).cast("int"))
    return df.withColumn(out, F.concat(*(one(j) for j in range(k))))


def histogram(corpus: Corpus, k: int) -> DataFrame:
    return extract(corpus, k).groupBy("kmer").agg(F.count(F.lit(1)).alias("cnt"))


def suggest_k(corpus: Corpus, partitions: int) -> int:
    """The least k for which no k-mer has more than an even share of the suffixes, or the widest that can be packed."""
    for k in range(1, widest(corpus) + 1):
        if histogram(corpus, k).agg(F.max("cnt")).first()[0] <= max(1, corpus.n // partitions):
            return k
    return widest(corpus)


def hash_index(corpus: Corpus, k: int) -> DataFrame:
    """(kmer, positions): the table index that full-text indexes are weighed against; positions of frequent k-mers are in several
    rows of bounded length, so no row grows with the text."""
    span = 1 << 20
    return extract(corpus, k).groupBy("kmer", F.floor(F.col("pos") / span).alias("part")).agg(F.array_sort(F.collect_list("pos")).alias("positions"))


def lookup(corpus: Corpus, k: int, words: DataFrame) -> DataFrame:
    """(word, pos) of the words (each of k symbols) by equi-join on the packed key."""
    keyed = _keyed(corpus, words.where(F.char_length("word") == k))
    return keyed.join(hash_index(corpus, k), "kmer").select("word", F.explode("positions").alias("pos"))


def _keyed(corpus: Corpus, words: DataFrame) -> DataFrame:
    """(word, kmer): each word's symbols as one key; words with other symbols than the text's have none."""
    width, code = bits(corpus), {s: c + 1 for c, s in enumerate(corpus.symbols) if c != corpus.terminator}
    table = F.create_map(*(x for s, c in code.items() for x in (F.lit(s), F.lit(c).cast("long"))))
    symbols = F.filter(F.split("word", ""), lambda s: s != "")
    key = F.aggregate(symbols, F.lit(0).cast("long"), lambda a, s: F.when(a.isNull(), a).otherwise(F.shiftleft(a, width) + F.try_element_at(table, s)))
    return words.select("word").withColumn("kmer", key).where("kmer is not null")


def occurrences(corpus: Corpus, words: DataFrame, most: int = MOST_WORDS) -> DataFrame:
    """(word, pos) of distinct words of 1 to widest symbols, each where it starts in the text.

    Up to most words the table of their keys goes to the text: the text is read once for all lengths, and no k-mer that isn't asked for is
    moved or kept. With more, the index of all k-mers is joined, for each length. The rows are the same.
    """
    keyed = cut(_keyed(corpus, words.where(F.char_length("word").between(1, widest(corpus)))).withColumn("length", F.char_length("word")))
    lengths = sorted(r[0] for r in keyed.select("length").distinct().collect())
    if keyed.count() > most:
        out = keyed.select("word", F.lit(0).cast("long").alias("pos")).limit(0)
        for length in lengths:
            out = out.unionByName(lookup(corpus, length, keyed))
        return out
    width, n, size, longest = bits(corpus), corpus.n, CHUNK_SYMBOLS, max(lengths, default=1)
    table: dict[int, tuple[list[int], list[str]]] = {k: ([], []) for k in lengths}
    for r in keyed.orderBy("length", "kmer").select("length", "kmer", "word").toLocalIterator():
        table[r[0]][0].append(r[1])
        table[r[0]][1].append(r[2])
    shared = corpus.pieces.sparkSession.sparkContext.broadcast({k: (np.array(keys, np.int64), pa.array(names, pa.string())) for k, (keys, names) in table.items()})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start, raw in zip(batch["start"].to_pylist(), batch["codes"].to_pylist(), strict=True):
                keyed_at = pack(np.frombuffer(raw, CODE), min(size, n - start), longest, width)
                for k, (keys, names) in shared.value.items():
                    kmer = keyed_at >> width * (longest - k)
                    at = np.minimum(np.searchsorted(keys, kmer), len(keys) - 1)
                    hit = np.flatnonzero(keys[at] == kmer)
                    for i in range(0, len(hit), ROWS):
                        some = hit[i : i + ROWS]
                        yield pa.RecordBatch.from_arrays([names.take(pa.array(at[some])), pa.array(start + some)], ["word", "pos"])

    return chunks(corpus, size, longest).mapInArrow(run, "word string, pos long")


def lookup_any(corpus: Corpus, words: DataFrame, most: int = MOST_WORDS) -> DataFrame:
    """(word, pos) of words of any length from 1 on; longer ones than a key are looked up in pieces that must follow each other."""
    k, words = widest(corpus), cut(words.select("word").where("char_length(word) > 0").distinct())
    long = words.where(F.char_length("word") > k)
    # a piece at every k-th symbol, and one that ends with the word
    offsets = F.array_distinct(F.array_append(F.sequence(F.lit(0), F.char_length("word") - k, F.lit(k)), F.char_length("word") - k))
    pieces = cut(long.select("word", F.size(offsets).alias("n"), F.explode(offsets).alias("offset")).withColumn("piece", F.substring("word", F.col("offset") + 1, F.lit(k))))
    out = occurrences(corpus, words, most)
    if not pieces.limit(1).count():
        return out
    found = occurrences(corpus, pieces.select(F.col("piece").alias("word")).distinct(), most).withColumnRenamed("word", "piece")
    return out.unionByName(pieces.join(found, "piece").groupBy("word", "n", (F.col("pos") - F.col("offset")).alias("pos")).agg(F.count(F.lit(1)).alias("met")).where("met = n").select("word", "pos"))
