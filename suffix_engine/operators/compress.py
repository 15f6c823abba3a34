"""What a transform is good for in compression: runs, move-to-front codes, order-0 entropy."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from suffix_engine.operators import prefix
from suffix_engine.operators.suffix_array import neighbours
from suffix_engine.session import cut


def rle(bwt: DataFrame, n: int) -> DataFrame:
    """(run, code, start, len) from (rank, code)."""
    first = neighbours(bwt, "code").where("prior_code is null or prior_code <> code").select("code", F.col("rank").alias("start"))
    numbered = cut(prefix.exclusive(first, None, "start", out="run"))
    after = numbered.select((F.col("run") - 1).alias("run"), F.col("start").alias("after"))
    return numbered.join(after, "run", "left").select("run", "code", "start", (F.coalesce("after", F.lit(n)) - F.col("start")).alias("len"))


def unrle(runs: DataFrame) -> DataFrame:
    return runs.select(F.explode(F.sequence(F.col("start"), F.col("start") + F.col("len") - 1)).alias("rank"), "code")


def _blocks(df: DataFrame, column: str, block: int, most: int) -> DataFrame:
    """(block, v): the values of each block of ranks in order; values are less than most. They are sent as arrays, not as rows."""
    at, value = (np.dtype("<u1" if x <= 1 << 8 else "<u2" if x <= 1 << 16 else "<u4") for x in (block, most))

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            rank, values = batch["rank"].to_numpy(), batch[column].to_numpy()
            if (rank[1:] < rank[:-1]).any():
                order = np.argsort(rank, kind="stable")
                rank, values = rank[order], values[order]
            own, offset = np.divmod(rank, block)
            first = np.flatnonzero(np.r_[True, own[1:] != own[:-1]])
            offset, values = np.diff(offset, prepend=0), values.astype(value)  # steps of ranks that follow each other are all 1
            offset[first] = rank[first] % block
            offset = offset.astype(at)
            bounds = list(zip(first, np.r_[first[1:], len(rank)], strict=True))
            yield pa.RecordBatch.from_arrays([pa.array(own[first]), pa.array([offset[i:j].tobytes() for i, j in bounds], pa.binary()), pa.array([values[i:j].tobytes() for i, j in bounds], pa.binary())], ["block", "at", "v"])

    def gather(table: pa.Table) -> pa.Table:
        places = np.concatenate([np.cumsum(np.frombuffer(x, at).astype(np.int64)) for x in table["at"].to_pylist()])
        out = np.empty(len(places), "<i4")
        out[places] = np.frombuffer(b"".join(table["v"].to_pylist()), value)
        return pa.table({"block": table["block"].slice(0, 1), "v": pa.array([out.tobytes()], pa.binary())})

    sent = df.select("rank", column).mapInArrow(pieces, "block long, at binary, v binary")
    return sent.groupBy("block").applyInArrow(gather, "block long, v binary")


def mtf(bwt: DataFrame, sigma: int, block: int = 1 << 16, inverse: bool = False) -> DataFrame:
    """(rank, code) as (rank, mtf), each block of ranks with a fresh list of symbols, or back."""
    source, target = ("mtf", "code") if inverse else ("code", "mtf")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for b, raw in zip(batch["block"].to_pylist(), batch["v"].to_pylist(), strict=True):
                values, own, moved = np.frombuffer(raw, "<i4"), list(range(sigma)), []
                # within a run the list stays as it is
                heads = np.flatnonzero(np.r_[True, values[1:] != 0] if inverse else np.r_[True, values[1:] != values[:-1]])
                for x in values[heads].tolist():
                    i = x if inverse else own.index(x)
                    symbol = own.pop(i)
                    own.insert(0, symbol)
                    moved.append(symbol if inverse else i)
                out = np.zeros(len(values), np.int32)
                out[heads] = moved
                if inverse:
                    out = np.repeat(out[heads], np.diff(np.r_[heads, len(values)]))
                yield pa.RecordBatch.from_arrays([pa.array(b * block + np.arange(len(out))), pa.array(out, pa.int32())], ["rank", target])

    return _blocks(bwt, source, block, sigma).mapInArrow(run, f"rank long, {target} int")


def entropy(df: DataFrame, column: str) -> DataFrame:
    """(n, bits): order-0 entropy of a column, in bits for each row."""
    counts = df.groupBy(column).agg(F.count(F.lit(1)).cast("double").alias("c"))
    return counts.agg(F.sum("c").alias("n"), F.sum(F.col("c") * F.log2("c")).alias("s")).select(F.col("n").cast("long").alias("n"), (F.log2("n") - F.col("s") / F.col("n")).alias("bits"))


def run_report(bwt: DataFrame, n: int) -> DataFrame:
    """(n, runs, ratio): how much run-length coding gains."""
    return neighbours(bwt, "code").agg(F.sum(F.when(F.col("prior_code").isNull() | (F.col("prior_code") != F.col("code")), 1).otherwise(0)).alias("runs")).select(F.lit(n).cast("long").alias("n"), "runs", (F.lit(n) / F.col("runs")).alias("ratio"))
