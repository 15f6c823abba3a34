"""Mixing by soft membership: posteriors of domains, and document rates whose expected token totals meet target shares."""

from __future__ import annotations

import warnings
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from suffix_engine.llm.features import CLASSES, class_shares, word_slots
from suffix_engine.llm.quality import _buffer, spread
from suffix_engine.session import written

#: The labelled table's domains, and the share of all tokens that the production mix takes of each at most. Domains within their bound keep
#: their proportions, so that nothing is weighed up for being scarce.
DOMAINS = ("good", "poor", "toxic")
AT_MOST = (1.0, 0.05, 0.05)
#: Hashed words; bound of the labelled sample; least test value of a word that the classifier uses, and how many it uses at most (those
#: with the greatest values); rounds of the
#: descent, and the part of its own target by which a domain may miss it; what a target of 0 may be missed by.
SLOTS, MOST_LABELLED, TELLING, MOST_TELLING = 1 << 14, 9000, 4.5, 2048
ROUNDS, PRECISION, NOTHING = 40, 1e-3, 1e-6
#: Added to the posteriors' second moments: the descent approaches domains of which there is hardly any in small steps, so that its
#: first ones don't overshoot on noise in their posteriors. What it is slow at is left to settle.
RIDGE = 0.02
_ROWS = 512


@dataclass
class DomainModel:
    slots: np.ndarray
    mean: np.ndarray
    scale: np.ndarray
    weights: np.ndarray

    def posteriors(self, b: np.ndarray, bounds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Of each text, and its number of words."""
        doc, slot, counts = word_slots(b, bounds, SLOTS)
        at = np.searchsorted(self.slots, slot)
        known = at < len(self.slots)
        known[known] = self.slots[at[known]] == slot[known]
        x = np.zeros((len(counts), len(self.slots) + CLASSES), np.float32)
        x[doc[known], at[known]] = 1
        x[:, len(self.slots) :] = class_shares(b, bounds)
        z = np.clip((x - self.mean) / self.scale, -5, 5) @ self.weights[:-1] + self.weights[-1]
        p = np.exp(z - z.max(axis=1, keepdims=True)).astype(np.float64)
        return p / p.sum(axis=1, keepdims=True), counts


def domain(quality, toxic):
    return F.when(toxic == 1, 2).when(quality == 0, 1).when(quality == 1, 0)


def fit(docs: DataFrame, labels: DataFrame, most: int = MOST_LABELLED, steps: int = 200, rate: float = 0.03, decay: float = 1e-3) -> DomainModel:
    """A linear classifier over telling words and byte classes, fitted on the labelled documents with the least hashes of their ids
    (most of them at most, which bounds what comes to the driver; of rows that repeat an id, one). Labels with a null count for nothing."""
    marked = labels.select("doc_id", domain(F.col("quality"), F.col("toxic")).alias("y")).where("y is not null and doc_id is not null")
    own = marked.groupBy("doc_id").agg(F.max("y").alias("y")).orderBy(F.xxhash64("doc_id", F.lit(29)), "doc_id").limit(most)
    joined = docs.select("doc_id", F.col("text").cast("string").alias("text")).join(F.broadcast(own), "doc_id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            d = _buffer(batch, "text")
            doc, slot, _ = word_slots(d.bytes, d.bounds, SLOTS)
            edge = np.searchsorted(doc, np.arange(len(d) + 1))
            shares = class_shares(d.bytes, d.bounds).astype(np.float16)
            yield pa.RecordBatch.from_arrays([batch["doc_id"], batch["y"], pa.array([slot[i:j].astype(np.uint16).tobytes() for i, j in zip(edge[:-1], edge[1:], strict=True)], pa.binary()), pa.array([x.tobytes() for x in shares], pa.binary())], ["doc_id", "y", "slots", "shares"])

    one = joined.mapInArrow(run, "doc_id long, y int, slots binary, shares binary").groupBy("doc_id").agg(F.min(F.struct("y", "slots", "shares")).alias("x"))
    got = [r["x"] for r in sorted(one.collect(), key=lambda r: r["doc_id"])]
    n, k = len(got), len(DOMAINS)
    y = np.array([r["y"] for r in got], np.int64)
    words = [np.frombuffer(r["slots"], np.uint16).astype(np.int64) for r in got]
    slots = _telling(words, y)
    a = np.zeros((n, len(slots) + CLASSES + 1), np.float32)
    for i, r in enumerate(got):
        a[i, np.flatnonzero(np.isin(slots, words[i]))] = 1
        a[i, len(slots) : -1] = np.frombuffer(r["shares"], np.float16)
    if not n:
        return DomainModel(slots, np.zeros(CLASSES, np.float32), np.ones(CLASSES, np.float32), np.zeros((CLASSES + 1, k), np.float32))
    del got, words
    # in place: with all slots in use this is the driver's largest array
    mean, scale = spread(a[:, :-1])
    scale += np.float32(0.02)
    a[:, :-1] -= mean
    a[:, :-1] /= scale
    np.clip(a, -5, 5, out=a)
    a[:, -1] = 1
    truth, w = np.eye(k, dtype=np.float32)[y], np.zeros((a.shape[1], k), np.float32)
    first, second = np.zeros_like(w), np.zeros_like(w)
    for t in range(1, steps + 1):
        z = a @ w
        p = np.exp(z - z.max(axis=1, keepdims=True))
        p /= p.sum(axis=1, keepdims=True)
        g = a.T @ ((p - truth) / n) + decay * w
        first, second = 0.9 * first + 0.1 * g, 0.999 * second + 0.001 * g * g
        w -= rate * (first / (1 - 0.9**t)) / (np.sqrt(second / (1 - 0.999**t)) + 1e-8)
    return DomainModel(slots, mean, scale, w)


def _telling(words: list[np.ndarray], y: np.ndarray) -> np.ndarray:
    """Slots whose share of documents differs between a domain and the rest."""
    value = np.zeros(SLOTS)
    held = lambda which: np.bincount(np.concatenate([np.zeros(0, np.int64), *(words[i] for i in np.flatnonzero(which))]), minlength=SLOTS)
    for k in range(len(DOMAINS)):
        inside = y == k
        if not inside.any() or inside.all():
            continue
        a, b, na, nb = held(inside), held(~inside), inside.sum(), (~inside).sum()
        p = (a + b) / (na + nb)
        z = (a / na - b / nb) / np.sqrt(p * (1 - p) * (1 / na + 1 / nb) + 1e-9)
        value = np.maximum(value, np.where(a + b >= 5, np.abs(z), 0))
    best = np.argsort(-value, kind="stable")[:MOST_TELLING]
    return np.sort(best[value[best] > TELLING])


def with_posteriors(docs: DataFrame, model: DomainModel, text: str = "text", keep_text: bool = True) -> DataFrame:
    """All rows and columns of docs (the text only if it is to be kept), with n_tokens (words) and posteriors; an empty text has no tokens."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            d, parts = _buffer(batch, text), [(np.zeros((0, len(DOMAINS))), np.zeros(0, np.int64))]
            for i in range(0, len(d), _ROWS):
                bounds = d.bounds[i : i + _ROWS + 1]
                parts.append(shared.value.posteriors(d.bytes[bounds[0] : bounds[-1]], bounds - bounds[0]))
            p, n = (np.concatenate(x) for x in zip(*parts, strict=True))
            yield pa.RecordBatch.from_arrays([*(batch[c] for c in names), pa.array(n, pa.int64()), pa.array(list(p), pa.list_(pa.float64()))], [*names, "n_tokens", "posteriors"])

    names = [c for c in docs.columns if keep_text or c != text]
    return docs.mapInArrow(run, T.StructType([*(docs.schema[c] for c in names), T.StructField("n_tokens", T.LongType()), T.StructField("posteriors", T.ArrayType(T.DoubleType()))]))


def _rates(p: np.ndarray, steps: np.ndarray) -> np.ndarray:
    """The rates after the given descent steps from 1: each is projected onto what is not negative."""
    r = np.ones(len(p))
    for s in steps:
        r = np.maximum(0, r - p @ s)
    return r


def _totals(scored: DataFrame, steps: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
    """Expected domain tokens, token-weighted second moments of the posteriors where the rate is over 0, and squared rates; a row for
    each batch goes to the sum."""
    k = len(DOMAINS)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, square, norm = np.zeros(k), np.zeros((k, k)), 0.0
        for batch in batches:
            p = batch["posteriors"].values.to_numpy().reshape(-1, k) if batch.num_rows else np.zeros((0, k))
            n = batch["n_tokens"].to_numpy().astype(float)
            rates = _rates(p, steps)
            total += (rates * n) @ p
            square += (p * (n * (rates > 0))[:, None]).T @ p
            norm += float(n @ rates**2)
        yield pa.RecordBatch.from_arrays([pa.array([*total, *square.ravel(), norm]).cast(pa.float64()), pa.array(range(k + k * k + 1), pa.int32())], ["x", "i"])

    sums = scored.select("n_tokens", "posteriors").mapInArrow(run, "x double, i int").groupBy("i").agg(F.sum("x")).collect()
    got = np.zeros(k + k * k + 1)
    for i, x in sums:
        got[i] = x
    return got[:k], got[k:-1].reshape(k, k), float(got[-1])


class _Sums:
    """The totals of a table under any steps, each computed once. Domains may be taken together: merged has a row for each domain and
    a column with a 1 for each group of them, and steps, totals and moments are those of groups."""

    def __init__(self, scored: DataFrame, merged: np.ndarray | None = None):
        self.scored, self.known = scored, {}
        self.merged = np.eye(len(DOMAINS)) if merged is None else merged
        self.k = self.merged.shape[1]

    def __call__(self, steps: np.ndarray) -> tuple[np.ndarray, np.ndarray, float]:
        own = steps @ self.merged.T
        key = own.tobytes()
        if key not in self.known:
            self.known[key] = _totals(self.scored, own)
        totals, moment, norm = self.known[key]
        return totals @ self.merged, self.merged.T @ moment @ self.merged, norm

    def grouped(self, merged: np.ndarray) -> _Sums:
        out = _Sums(self.scored, merged)
        out.known = self.known
        return out


def over_bounds(totals: np.ndarray, at_most=AT_MOST) -> np.ndarray:
    """Which domains must come down to their bounds, also after the others have taken what is left in the proportions that they have."""
    shares, bounds = totals / totals.sum(), np.asarray(at_most, float)
    over = np.zeros(len(shares), bool)
    while not over.all():
        targets = shares * (1 - bounds[over].sum()) / max(shares[~over].sum(), 1e-300)
        more = ~over & (targets > bounds)
        if not more.any():
            break
        over |= more
    return over if not over.all() else np.zeros(len(shares), bool)


def _miss(residual: np.ndarray, targets: np.ndarray, precision: float) -> float:
    """The worst residual, each as a part of what its domain's target allows: met up to 1."""
    return float((np.abs(residual) / np.where(targets > 0, precision * targets, NOTHING)).max())


def descend(scored: DataFrame | _Sums, targets, rounds: int = ROUNDS, precision: float = PRECISION, pace: float | None = None) -> np.ndarray:
    """Steps of projected gradient descent on the weighted squares of (expected totals - target totals) / tokens.

    Weighting by the inverse second moment of the posteriors makes the step 1 safe and the pace even in all domains. A document's
    rate follows from its posteriors and these few vectors, so a round ships one row of sums per task and no rates. It ends when
    every domain is within precision of its own target, after the rounds, or when a round leaves more than pace of the worst miss.
    """
    sums = scored if isinstance(scored, _Sums) else _Sums(scored)
    k = sums.k
    steps = np.zeros((0, k))
    totals, moment, _ = sums(steps)
    tokens = totals.sum()
    if tokens <= 0:
        return steps
    targets = np.asarray(targets, float)
    weight, before = np.linalg.inv(moment / tokens + RIDGE * np.eye(k)), np.inf
    for _ in range(rounds):
        residual = totals / tokens - targets
        miss = _miss(residual, targets, precision)
        if miss <= 1 or (pace is not None and miss > pace * before):
            break
        steps, before = np.vstack([steps, weight @ residual]), miss
        totals, _, _ = sums(steps)
    return steps


def settle(sums: _Sums, steps: np.ndarray, targets, rounds: int = ROUNDS, precision: float = PRECISION) -> tuple[np.ndarray, np.ndarray]:
    """Steps that meet the targets, and the shares of tokens they reach. Given ones that meet them are returned as they are.

    Otherwise one step is looked for under which the rates are, of all that meet the targets, those nearest to 1. It is the least
    point of a convex function of as many variables as there are domains, found by Newton's method with shortened steps whatever the
    domains' sizes. Targets that no rates from 0 on meet have no such step; then the one that misses least is returned.
    """
    k = sums.k
    targets = np.asarray(targets, float)
    tokens = sums(np.zeros((0, k)))[0].sum()

    def at(x: np.ndarray) -> tuple:
        totals, moment, norm = sums(x)
        return totals / tokens, moment / tokens, norm / tokens / 2 + float(x.sum(axis=0) @ targets)

    shares, moment, _ = at(steps)
    best = (_miss(shares - targets, targets, precision), steps, shares)
    if best[0] <= 1:
        return best[1:]
    here = steps.sum(axis=0, keepdims=True)
    shares, moment, value = at(here)
    least = 1e-9 * np.trace(moment) + 1e-12
    left = rounds
    while True:
        residual = shares - targets
        best = min(best, (_miss(residual, targets, precision), here, shares), key=lambda b: b[0])
        if best[0] <= 1:
            break
        step, part, found = np.linalg.solve(moment + least * np.eye(k), residual), 1.0, None
        while found is None and left > 0:
            there, left = here + part * step, left - 1
            tried = at(there)
            if tried[2] <= value - 1e-4 * part * float(residual @ step) + 1e-15:
                found = tried
            part /= 4
        if found is None:
            break
        here, (shares, moment, value) = there, found
    return best[1:]


def with_rates(scored: DataFrame, steps: np.ndarray) -> DataFrame:
    """Adds rate, by DataFrame functions only."""
    rate = F.lit(1.0)
    array = F.array(*(F.array(*(F.lit(float(x)) for x in s)) for s in steps)) if len(steps) else F.array().cast("array<array<double>>")
    dot = lambda s: F.aggregate(F.zip_with("posteriors", s, lambda a, b: a * b), F.lit(0.0), lambda x, y: x + y)
    return scored.withColumn("rate", F.aggregate(array, rate, lambda r, s: F.greatest(F.lit(0.0), r - dot(s))))


@dataclass
class Plan:
    """Steps that give each document its rate, the target shares of tokens by group of domains, those reached, and whether each is met
    within PRECISION of itself."""

    steps: np.ndarray
    targets: dict[str, float]
    reached: dict[str, float]
    met: bool


def plan(scored: DataFrame, targets=None, at_most=AT_MOST) -> Plan:
    """The descent while it is quick, then what it left; the whole descent, and a warning, where the targets can't be met.

    Without targets, each domain over its bound has the bound as its target, and the others are one group with the rest: what
    is scarce anyway gets no target of its own, which little but the noise in the posteriors could meet.
    """
    sums, none = _Sums(scored), np.zeros((0, len(DOMAINS)))
    totals = sums(none)[0]
    if totals.sum() <= 0:
        return Plan(none, {}, {}, True)
    names = list(DOMAINS)
    if targets is None:
        over = over_bounds(totals, at_most)
        columns = [~over, *(np.arange(len(over)) == i for i in np.flatnonzero(over))]
        sums = sums.grouped(np.column_stack(columns).astype(float))
        names = ["+".join(d for d, x in zip(DOMAINS, c, strict=True) if x) for c in columns]
        bounds = np.asarray(at_most, float)[over]
        targets = np.r_[1 - bounds.sum(), bounds]
    targets = np.asarray(targets, float)
    steps, shares = settle(sums, descend(sums, targets, pace=0.5), targets)
    met = _miss(shares - targets, targets, PRECISION) <= 1
    if not met:
        steps = descend(sums, targets)
        shares = sums(steps)[0] / totals.sum()
        unmet = ", ".join(f"{d} {x:.3g} of {t:.3g}" for d, x, t in zip(names, shares, targets, strict=True))
        warnings.warn(f"targets not met, shares of tokens reached: {unmet}", stacklevel=2)
    given = lambda x: dict(zip(names, map(float, x), strict=True))
    return Plan(steps @ sums.merged.T, given(targets), given(shares), met)


def mix(docs: DataFrame, labels: DataFrame, targets=None) -> DataFrame:
    """All columns of docs, n_tokens, posteriors of DOMAINS, rate (how often each document is to be taken, on average) and targets_met.

    Targets are shares of all tokens of docs (None: the domains over AT_MOST come down to it), each met within PRECISION of itself. Targets that the
    documents can't meet with rates from 0 on are met as nearly as least squares allow; targets_met is then false in all rows, and a warning tells by
    how much. Every text is scored once. Null and empty texts have no tokens and get a rate, too. Rows that repeat an id are documents of
    their own. Columns of docs with the names of the new ones are replaced. An empty table gives an empty result.
    """
    rest = [c for c in docs.columns if c not in ("n_tokens", "posteriors", "rate", "targets_met")]
    scored = written(with_posteriors(docs.select(rest), fit(docs, labels)), "posteriors")
    found = plan(scored.select("n_tokens", "posteriors"), targets)
    return with_rates(scored, found.steps).withColumn("targets_met", F.lit(found.met))


def mixing_rates(docs: DataFrame, labels: DataFrame, targets=None) -> DataFrame:
    """doc_id, n_tokens, the posteriors, rate and targets_met of each row of docs; other columns aren't read. Cases as in mix."""
    scored = written(with_posteriors(docs.select("doc_id", F.col("text").cast("string").alias("text")), fit(docs, labels), keep_text=False), "posteriors")
    found = plan(scored.select("n_tokens", "posteriors"), targets)
    out = with_rates(scored, found.steps).withColumn("targets_met", F.lit(found.met))
    return out.select("doc_id", "n_tokens", *(F.get("posteriors", F.lit(i)).alias(f"p_{d}") for i, d in enumerate(DOMAINS)), "rate", "targets_met")
