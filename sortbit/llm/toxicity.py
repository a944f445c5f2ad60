"""Toxicity from confirmed toxic examples and unlabelled text: a numpy classifier
trained by the non-negative positive-unlabelled risk.

Features are the presence of hashed byte n-grams of the lower-cased text (whatever is
not a letter counts as a space, so an n-gram may begin or end a word). `fit` keeps the
n-grams whose document frequency differs most between the positives and the unlabelled
texts, then minimises

    prior * E_P[loss(f, 1)] + max(0, E_U[loss(f, 0)] - prior * E_P[loss(f, 0)])

with the logistic loss; where the bracket falls below zero, the step goes against it.
The sample sizes are parameters (`max_positive`, `max_unlabelled`) and bound what the
one training task holds; scoring covers whole texts of all rows.

Nulls and empty texts have no n-gram: their score is the model's bias alone. Without any
positive, the model is the constant prior 0.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import bounded_sample, fold_is_held_out, ship, text_chunks
from .bytewords import LOWER, distinct, text_bytes

BUCKETS = 1 << 22


def folded(data: np.ndarray) -> np.ndarray:
    """Lower case for A-Z and for the two-byte Latin letters; ASCII that is no letter becomes a space."""
    out = LOWER[data]
    out[(out < 0x80) & ((out < 97) | (out > 122))] = 0x20
    if len(out) > 1:
        after = out[1:]
        after[(out[:-1] == 0xC3) & (after >= 0x80) & (after <= 0x9E) & (after != 0x97)] += 0x20
    return out


def ngram_buckets(data: np.ndarray, width: int) -> np.ndarray:
    """The bucket of the n-gram that begins at each byte; the text's ends count as spaces."""
    n = len(data)
    h = np.full(n, width * 0x9E37, np.uint32)
    padded = np.concatenate([data, np.full(width, 0x20, np.uint8)]).astype(np.uint32)
    for i in range(width):
        h *= np.uint32(0x01000193)
        h ^= padded[i : i + n]
    h ^= h >> np.uint32(15)
    h *= np.uint32(0x85EBCA6B)
    h ^= h >> np.uint32(13)
    return h & np.uint32(BUCKETS - 1)


def buckets_by_text(column: pa.Array, widths: tuple[int, ...]):
    """For each width, buckets and text numbers of all its n-grams; a space is set around every text."""
    data, offsets = text_bytes(column)
    n = len(offsets) - 1
    spaced = np.full(len(data) + n, 0x20, np.uint8)
    text = np.repeat(np.arange(n), np.diff(offsets))
    spaced[np.arange(len(data)) + text + 1] = folded(data)
    owner = np.repeat(np.arange(n), np.diff(offsets) + 1)
    starts = offsets[:-1] + np.arange(n)
    for width in widths:
        yield ngram_buckets(spaced, width), owner, starts


@dataclass
class ToxicityModel:
    widths: tuple[int, ...] = (5, 7)
    features: np.ndarray = field(default_factory=lambda: np.zeros(0, np.int64))
    weights: np.ndarray = field(default_factory=lambda: np.zeros(0, np.float32))
    bias: float = -30.0

    def table(self) -> np.ndarray:
        """Bucket to 1 + feature number, 0 for the others."""
        out = np.zeros(BUCKETS, np.uint16)
        out[self.features] = np.arange(1, len(self.features) + 1)
        return out

    def presence(self, column: pa.Array, table: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Distinct (text, feature) pairs."""
        pairs = []
        for buckets, owner, _ in buckets_by_text(column, self.widths):
            found = table[buckets]
            at = np.flatnonzero(found)
            pairs.append(owner[at] * np.int64(1 << 17) + found[at] - 1)
        pairs = distinct(np.concatenate(pairs)) if pairs else np.zeros(0, np.int64)
        return pairs >> 17, pairs & ((1 << 17) - 1)

    def score(self, column: pa.Array, table: np.ndarray) -> np.ndarray:
        text, feature = self.presence(column, table)
        z = np.bincount(text, weights=self.weights[feature].astype(np.float64), minlength=len(column)) + self.bias
        return 1 / (1 + np.exp(-np.clip(z, -60, 60)))


def _chunks(texts: pa.Array | list[str]):
    texts = texts if isinstance(texts, pa.Array) else pa.array(texts, pa.large_string())
    return text_chunks(iter([pa.record_batch({"text": texts})]), limit=1 << 18)


def _document_frequency(texts: pa.Array | list[str], widths: tuple[int, ...]) -> np.ndarray:
    df = np.zeros(BUCKETS, np.int32)
    for batch in _chunks(texts):
        seen = [distinct(owner * np.int64(BUCKETS) + b) for b, owner, _ in buckets_by_text(batch.column(0), widths)]
        np.add.at(df, distinct(np.concatenate(seen)) & (BUCKETS - 1), 1)
    return df


def train(positive: pa.Array | list[str], unlabelled: pa.Array | list[str], prior: float, widths=(5, 7), n_features: int = 1024, least_z: float = 5.0, steps: int = 500, rate: float = 0.05, decay: float = 1e-3) -> ToxicityModel:
    """The model for two samples of texts. A prior beyond [0.001, 0.9] is moved there."""
    if not len(positive) or not len(unlabelled):
        return ToxicityModel(widths)
    prior = float(np.clip(prior, 1e-3, 0.9))
    dp, du = _document_frequency(positive, widths), _document_frequency(unlabelled, widths)
    seen = np.flatnonzero(dp + du >= 3)
    p, u = (dp[seen] + 0.5) / (len(positive) + 1), (du[seen] + 0.5) / (len(unlabelled) + 1)
    del dp, du
    # the root of the likelihood ratio holds for rare n-grams and few positives, where a normal z is too small
    z = np.sqrt(2 * len(positive) * np.maximum(p * np.log(p / u) + (1 - p) * np.log((1 - p) / (1 - u)), 0))
    weight = np.where(z >= least_z, z * np.abs(np.log(p / u)), 0)
    best = np.argsort(-weight, kind="stable")[:n_features]
    model = ToxicityModel(tuple(widths), np.sort(seen[best[weight[best] > 0]]).astype(np.int64))
    if not len(model.features):
        return ToxicityModel(widths)

    table = model.table()

    def matrix(texts: pa.Array | list[str]) -> np.ndarray:
        x, at = np.zeros((len(texts), len(model.features)), np.uint8), 0
        for batch in _chunks(texts):
            text, feature = model.presence(batch.column(0), table)
            x[at + text, feature] = 1
            at += batch.num_rows
        return x

    xp, xu = matrix(positive), matrix(unlabelled)
    w, b = np.zeros(xp.shape[1], np.float32), np.float32(np.log(prior / (1 - prior)))
    m, v = np.zeros(len(w) + 1, np.float32), np.zeros(len(w) + 1, np.float32)
    rng = np.random.default_rng(7)
    for step in range(1, steps + 1):
        bp = xp[rng.integers(0, len(xp), min(len(xp), 256))].astype(np.float32)
        bu = xu[rng.integers(0, len(xu), min(len(xu), 512))].astype(np.float32)
        zp, zu = bp @ w + b, bu @ w + b
        sp, su = 1 / (1 + np.exp(-np.clip(zp, -60, 60))), 1 / (1 + np.exp(-np.clip(zu, -60, 60)))
        rest = np.logaddexp(0, zu).mean() - prior * np.logaddexp(0, zp).mean()
        of_rest = np.append(bu.T @ su / len(su) - prior * (bp.T @ sp) / len(sp), su.mean() - prior * sp.mean())
        of_positive = prior * np.append(bp.T @ (sp - 1) / len(sp), (sp - 1).mean())
        grad = (of_positive + of_rest if rest >= 0 else -of_rest).astype(np.float32)
        grad[:-1] += decay * w
        m, v = 0.9 * m + 0.1 * grad, 0.999 * v + 0.001 * grad * grad
        move = rate * (1 - step / (steps + 1)) * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.999**step)) + 1e-8)
        w, b = w - move[:-1], b - move[-1]
    model.weights, model.bias = w, float(b)
    return model


def fit(docs: DataFrame, labels: DataFrame, max_positive: int = 3000, max_unlabelled: int = 6000, **how) -> ToxicityModel:
    """Learns from rows outside the held-out fold: confirmed toxic documents, and a sample of all as unlabelled text.

    docs: doc_id, text; labels: doc_id, toxic. The class prior is the share of toxic rows among the labels.
    """
    learn = labels.where(~fold_is_held_out(F.col("doc_id")) & F.col("toxic").isNotNull()).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    n, toxic = learn.agg(F.count("*"), F.sum("toxic")).first()
    if not toxic:
        return ToxicityModel()
    ship(docs.sparkSession)
    positive = bounded_sample(learn.where("toxic = 1").select("doc_id"), "doc_id", max_positive)
    texts = docs.select("doc_id", "text").where(~fold_is_held_out(F.col("doc_id")))
    pos = texts.join(F.broadcast(positive), "doc_id", "left_semi").withColumn("positive", F.lit(True))
    rest = bounded_sample(texts, "doc_id", max_unlabelled, seed=1).withColumn("positive", F.lit(False))
    prior = toxic / n

    def run(batches):
        rows = [x for x in batches if x.num_rows]
        if not rows:
            return
        table = pa.Table.from_batches(rows).sort_by("doc_id")
        texts = table.column("text").cast(pa.large_string()).combine_chunks()
        del rows
        model = train(texts.filter(table.column("positive").combine_chunks()), texts.filter(pc.invert(table.column("positive").combine_chunks())), prior, **how)
        yield pa.record_batch({"features": pa.array([model.features.tobytes()], pa.binary()), "weights": pa.array([model.weights.tobytes()], pa.binary()), "bias": pa.array([model.bias]), "widths": pa.array([list(model.widths)], pa.list_(pa.int32()))})

    # the sample is bounded, so one task holds it; the driver only gets the model
    made = pos.unionByName(rest).repartition(1).mapInArrow(run, "features binary, weights binary, bias double, widths array<int>").collect()
    if not made:
        return ToxicityModel()
    return ToxicityModel(tuple(made[0].widths), np.frombuffer(made[0].features, np.int64), np.frombuffer(made[0].weights, np.float32), made[0].bias)


def score(docs: DataFrame, model: ToxicityModel, id_col: str = "doc_id") -> DataFrame:
    """(id, score) for every row of docs."""
    ship(docs.sparkSession)
    kind = docs.schema[id_col].dataType

    def run(batches):
        table = model.table()
        for batch in text_chunks(batches, limit=1 << 19):
            yield pa.record_batch({id_col: batch.column(id_col), "score": pa.array(model.score(batch.column("text"), table))})

    return docs.select(id_col, "text").mapInArrow(run, f"{id_col} {kind.simpleString()}, score double")
