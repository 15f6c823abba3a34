"""The methods as SQL functions."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from suffix_engine.operators import bwt


@F.pandas_udf(T.StructType([T.StructField("bwt", T.StringType()), T.StructField("primary", T.LongType())]))
def bwt_encode(text: pd.Series) -> pd.DataFrame:
    return pd.DataFrame([(None, None) if t is None else bwt.encode(t) for t in text], columns=["bwt", "primary"])


@F.pandas_udf(T.StringType())
def bwt_decode(transform: pd.Series, primary: pd.Series) -> pd.Series:
    return pd.Series([None if t is None or pd.isna(i) else bwt.decode(t, int(i)) for t, i in zip(transform, primary, strict=True)], dtype=object)


@F.pandas_udf(T.LongType())
def bwt_runs(text: pd.Series) -> pd.Series:
    """Runs of the transform."""
    return pd.Series([None if t is None else (lambda b: 1 + sum(x != y for x, y in zip(b, b[1:])))(bwt.encode(t)[0]) for t in text], dtype="Int64")


@F.pandas_udf(T.DoubleType())
def run_ratio(text: pd.Series) -> float:
    """Of a group: symbols for each run of the transforms, terminators included."""
    own = [bwt.encode(t)[0] for t in text if t is not None]
    return sum(map(len, own)) / max(1, sum(1 + sum(x != y for x, y in zip(b, b[1:])) for b in own))


@F.udtf(returnType=T.StructType([T.StructField("pos", T.LongType()), T.StructField("kmer", T.StringType())]))
class Suffixes:
    """suffixes(text, k): each suffix's first k symbols, padded with the terminator."""

    def eval(self, text: str, k: int):
        if text is not None:
            padded = text + bwt.TERMINATOR * (k + 1)
            for i in range(len(text) + 1):
                yield i, padded[i : i + k]


def register(spark: SparkSession) -> None:
    for name, f in (("bwt_encode", bwt_encode), ("bwt_decode", bwt_decode), ("bwt_runs", bwt_runs), ("bwt_run_ratio", run_ratio)):
        spark.udf.register(name, f)
    spark.udtf.register("suffixes", Suffixes)
