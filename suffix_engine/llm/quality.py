"""Quality classifier from trusted positives and unlabelled text (non-negative unbiased risk)."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from suffix_engine.llm.blocks import Docs
from suffix_engine.llm.features import shape_features

#: Bounds of the sample that the model is fitted on: trusted positives and unlabelled texts.
MOST_POSITIVE, MOST_UNLABELLED = 3000, 6000
_ROWS = 512


@dataclass
class Model:
    mean: np.ndarray
    scale: np.ndarray
    weights: np.ndarray
    bias: float
    prior: float

    def score(self, x: np.ndarray) -> np.ndarray:
        z = np.clip((x - self.mean) / self.scale, -5, 5) @ self.weights + self.bias
        return 1 / (1 + np.exp(-np.clip(z.astype(np.float64), -500, 500)))


def held_out(doc_id: Column) -> Column:
    """Rows that labels are never learned from; a null id is none of them."""
    return F.coalesce(F.crc32(doc_id.cast("string")) % 3 == 1, F.lit(False))


def _sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -60, 60)))


def spread(x: np.ndarray, columns: int = 64) -> tuple[np.ndarray, np.ndarray]:
    """Mean and deviation of each column, for some columns at a time: no copy of the whole is made."""
    mean, deviation = np.zeros(x.shape[1], np.float32), np.zeros(x.shape[1], np.float32)
    for i in range(0, x.shape[1], columns):
        part = x[:, i : i + columns].astype(np.float32)
        mean[i : i + columns], deviation[i : i + columns] = part.mean(0), part.std(0)
    return mean, deviation


def standard(x: np.ndarray, mean: np.ndarray, scale: np.ndarray) -> np.ndarray:
    """A copy with each column moved and scaled, within 5 of 0: one array, and no others on the way."""
    out = x.astype(np.float32)
    out -= mean
    out /= scale
    return np.clip(out, -5, 5, out=out)


def fit_nnpu(positive: np.ndarray, unlabelled: np.ndarray, prior: float, steps: int = 250, rate: float = 0.01, decay: float = 1e-3) -> Model:
    """Minimises prior * E_p[l(f)] + max(0, E_u[l(-f)] - prior * E_p[l(-f)]) with l the sigmoid loss, f linear.

    Where the part for negatives is below 0, only that part is climbed back, as the non-negative correction asks.
    """
    if not len(positive) or not len(unlabelled):
        zero = np.zeros(unlabelled.shape[1] if unlabelled.ndim == 2 else positive.shape[1], np.float32)
        return Model(zero, zero + 1, zero, float(np.log(prior / (1 - prior))), prior)
    mean, deviation = spread(unlabelled)
    scale = deviation + np.float32(0.02)
    used = np.flatnonzero((deviation > 0) | (spread(positive)[1] > 0))
    p, u = (standard(x[:, used], mean[used], scale[used]) for x in (positive, unlabelled))
    w = np.zeros(len(used) + 1, np.float32)
    first, second = np.zeros_like(w), np.zeros_like(w)
    for t in range(1, steps + 1):
        fp, fu = _sigmoid(p @ w[:-1] + w[-1]), _sigmoid(u @ w[:-1] + w[-1])
        slope_p, slope_u = fp * (1 - fp) / len(p), fu * (1 - fu) / len(u)
        if fu.mean() - prior * fp.mean() >= 0:
            on_p, on_u = -2 * prior * slope_p, slope_u
        else:
            on_p, on_u = prior * slope_p, -slope_u
        g = np.append(on_p @ p + on_u @ u + decay * w[:-1], on_p.sum() + on_u.sum()).astype(np.float32)
        first, second = 0.9 * first + 0.1 * g, 0.999 * second + 0.001 * g * g
        w -= rate * (first / (1 - 0.9**t)) / (np.sqrt(second / (1 - 0.999**t)) + 1e-8)
    weights = np.zeros(len(mean), np.float32)
    weights[used] = w[:-1]
    return Model(mean.astype(np.float32), scale.astype(np.float32), weights, float(w[-1]), prior)


def estimated_prior(positive: np.ndarray, unlabelled: np.ndarray, steps: int = 150, least: float = 0.3) -> float:
    """The share of positives among unlabelled texts, from these two samples alone.

    Positives against unlabelled texts is a task without negatives; where its scores are high there are hardly any, so the
    share of unlabelled texts there over that of positives comes down to the prior. The least such ratio is taken, over regions that hold
    at least that share of the positives. Each half of the texts is scored by what the other half taught.
    """
    if len(positive) < 2 or len(unlabelled) < 2:
        return 0.5
    mean, deviation = spread(unlabelled)
    used = np.flatnonzero((deviation > 0) | (spread(positive)[1] > 0))
    p, u = (standard(x[:, used], mean[used], deviation[used] + np.float32(0.02)) for x in (positive, unlabelled))
    scores: list[list[np.ndarray]] = [[], []]
    for half in (0, 1):
        a = np.vstack([p[half::2], u[half::2]])
        y = np.r_[np.ones(len(p[half::2])), np.zeros(len(u[half::2]))].astype(np.float32)
        weight = np.where(y > 0, 0.5 / max(y.sum(), 1), 0.5 / max((1 - y).sum(), 1)).astype(np.float32)
        w, first, second = np.zeros(a.shape[1] + 1, np.float32), 0.0, 0.0
        for t in range(1, steps + 1):
            d = weight * (_sigmoid(a @ w[:-1] + w[-1]) - y)
            g = np.append(a.T @ d + 1e-3 * w[:-1], d.sum())
            first, second = 0.9 * first + 0.1 * g, 0.999 * second + 0.001 * g * g
            w -= (0.01 * (first / (1 - 0.9**t)) / (np.sqrt(second / (1 - 0.999**t)) + 1e-8)).astype(np.float32)
        for out, x in zip(scores, (p[1 - half :: 2], u[1 - half :: 2]), strict=True):
            out.append(x @ w[:-1] + w[-1])
    sp, su = np.sort(np.concatenate(scores[0])), np.sort(np.concatenate(scores[1]))
    at = sp[: max(1, int((1 - least) * len(sp)))]
    above = lambda s, t: 1 - np.searchsorted(s, t) / len(s)
    return float(np.clip((above(su, at) / above(sp, at)).min(), 0.01, 0.99))


def _buffer(batch: pa.RecordBatch, text: str) -> Docs:
    """The texts of a batch in their own order."""
    n = batch.num_rows
    return Docs(pa.table({"doc_id": pa.array(np.arange(n)), "text": batch[text]}))


def _features(batch: pa.RecordBatch, text: str) -> Iterator[np.ndarray]:
    docs = _buffer(batch, text)
    for i in range(0, len(docs), _ROWS):
        yield shape_features(docs.bytes, docs.bounds[i : i + _ROWS + 1])


def sampled_features(docs: DataFrame, ids: DataFrame, n_ids: int) -> tuple[list, np.ndarray]:
    """Rows of ids (doc_id and others) and the features of their documents as half floats, of rows that repeat an id one; n_ids bounds what
    comes to the driver."""
    assert n_ids <= 100_000
    names = ids.columns
    joined = docs.select("doc_id", F.col("text").cast("string").alias("text")).join(F.broadcast(ids.hint("broadcast")), "doc_id")

    def run(batches):
        for batch in batches:
            rows = [x.astype(np.float16).tobytes() for part in _features(batch, "text") for x in part]
            yield pa.RecordBatch.from_arrays([batch[c] for c in names] + [pa.array(rows, pa.binary())], [*names, "x"])

    schema = T.StructType([*ids.schema.fields, T.StructField("x", T.BinaryType())])
    one = joined.mapInArrow(run, schema).groupBy(*names).agg(F.min("x").alias("x"))
    got = sorted(((tuple(r)[:-1], bytes(r["x"])) for r in one.collect()), key=lambda r: (r[0][names.index("doc_id")], r[1]))
    x = np.frombuffer(b"".join(r[1] for r in got), np.float16)
    return [dict(zip(names, r[0], strict=True)) for r in got], x.reshape(len(got), -1) if len(got) else x


def fit(docs: DataFrame, labels: DataFrame, most_positive: int = MOST_POSITIVE, most_unlabelled: int = MOST_UNLABELLED) -> Model:
    """Trusted positives: rows of the fold with label 1; no label 0 is read. Unlabelled: any documents of the fold. The prior is estimated from
    these two. Both samples are the ids with the least hashes, so they don't depend on the order of rows."""
    fold = labels.where(~held_out(F.col("doc_id")) & F.col("doc_id").isNotNull())
    order = F.xxhash64("doc_id", F.lit(17))
    p = fold.where("quality = 1").select("doc_id").distinct().orderBy(order).limit(most_positive).withColumn("positive", F.lit(True))
    u = docs.where(F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id"))).select("doc_id").distinct().orderBy(order).limit(most_unlabelled).withColumn("positive", F.lit(False))
    rows, x = sampled_features(docs, p.unionByName(u), most_positive + most_unlabelled)
    kind = np.array([r["positive"] for r in rows], bool)
    if not len(rows):
        x = np.zeros((0, shape_features(np.zeros(0, np.uint8), np.zeros(2, np.int64)).shape[1]), np.float16)
    positive, unlabelled = x[kind], x[~kind]
    del rows, x
    return fit_nnpu(positive, unlabelled, estimated_prior(positive, unlabelled))


def with_score(docs: DataFrame, model: Model, text: str = "text", score: str = "score", keep_text: bool = True) -> DataFrame:
    """All rows and columns of docs (the text only if it is to be kept) and the score of its text: the estimated probability of label 1. Null and empty texts
    score as texts without any feature. Only the text is an input of the score. A column with the score's name is replaced."""
    docs = docs.select([c for c in docs.columns if c != score])
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for batch in batches:
            s = np.concatenate([np.zeros(0)] + [shared.value.score(x) for x in _features(batch, text)])
            yield pa.RecordBatch.from_arrays([*(batch[c] for c in names), pa.array(s, pa.float64())], [*names, score])

    names = [c for c in docs.columns if keep_text or c != text]
    return docs.mapInArrow(run, T.StructType([*(docs.schema[c] for c in names), T.StructField(score, T.DoubleType())]))


def quality_scores(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score and predicted of each row, repeated ones too; other columns aren't read. An empty table gives an empty
    result; without any positive or unlabelled text in the fold, all scores are one half."""
    out = with_score(docs.select("doc_id", F.col("text").cast("string").alias("text")), fit(docs, labels), keep_text=False)
    return out.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
