"""Toxicity by non-negative positive-unlabelled learning.

Only documents confirmed as toxic are positives; all other documents of the learning fold, labelled or not, are
unlabelled text, a mixture of toxic and clean. With a class prior ``pi`` the risk of a classifier g is estimated as

    pi * R_p(+)  +  max(0, R_u(-) - pi * R_p(-))

where R_p(+) and R_p(-) are mean losses of positives taken as positive and as negative, and R_u(-) that of unlabelled
text taken as negative. The second term estimates the risk on clean text; it cannot be negative, so where a batch makes it
so, the step goes uphill on it instead, which keeps the classifier from memorising the positives.

The classifier is linear over the presence of hashed words and word beginnings, trained with numpy on a bounded sample of the
learning fold: ``max_positive`` and ``max_unlabelled`` documents by hash order (all, where there are fewer). Whole texts
are used. Because insults are few among many words, a document's evidence is the sum of its weights, not a
mean over its length. The loss is logistic, so evidence plus bias is
the log odds of being toxic.

The class prior is estimated from the labels of the fold (share of toxic among labelled documents), or given.

Defined cases: null text scores as empty text; documents without known words get the score of no evidence; rows that
repeat are scored alike; labels that are null or belong to no document are ignored; with no positives every score is 0; an
empty table gives an empty result; ``filter_toxic`` passes columns of any name through.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from taskmesh.llm.words import CACHE_ENTRIES, in_fold, lean, numbered, release, text_bytes, words
from taskmesh.sources import load, relieve

BITS = 20
STRIP = b".,;:!?\"'()[]{}<>*_-"


def features(word: bytes) -> tuple[int, ...]:
    """Buckets of a word without the punctuation around it, and of its first three to six characters, which stand for its stem."""
    bare = word.strip(STRIP).decode("utf-8", "replace")
    parts = [f"={bare}", *[f"^{bare[:n]}" for n in range(3, 7) if len(bare) > n]] if bare else []
    return tuple((zlib.crc32(p.encode()) * 2654435761 >> 11) & ((1 << BITS) - 1) for p in parts)


class Buckets(dict):
    """Cache of words' buckets, bounded."""

    def __missing__(self, word: bytes) -> tuple[int, ...]:
        if len(self) >= CACHE_ENTRIES:
            self.clear()
        self[word] = found = features(word)
        return found


@dataclass(frozen=True)
class ToxicityModel:
    """weight: of each bucket, 0 where training saw too few documents; slope and bias map evidence to log odds."""

    weight: np.ndarray
    slope: float
    bias: float
    prior: float

    def probability(self, evidence: np.ndarray) -> np.ndarray:
        return 1.0 / (1.0 + np.exp(-np.clip(self.slope * evidence + self.bias, -40, 40)))


def _csr(docs: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    starts = np.zeros(len(docs) + 1, np.int64)
    np.cumsum(np.array([len(d) for d in docs], np.int64), out=starts[1:])
    return (np.concatenate(docs) if docs else np.zeros(0, np.int64)), starts


def _sums(values: np.ndarray, starts: np.ndarray) -> np.ndarray:
    total = np.concatenate([[0.0], np.cumsum(values)])
    return total[starts[1:]] - total[starts[:-1]]


def train_nnpu(
    positive: list[np.ndarray],
    unlabelled: list[np.ndarray],
    prior: float,
    epochs: int = 120,
    rate: float = 0.8,
    l2: float = 1e-5,
    least_surprise: float = 24.0,
    purity: float = 0.7,
    seed: int = 7,
) -> ToxicityModel:
    """Documents as arrays of distinct buckets. Logistic loss, mini-batches of both sets, adaptive steps, a light pull to 0."""
    size = 1 << BITS
    weight = np.zeros(size)
    if not positive or not unlabelled:
        return ToxicityModel(weight, 1.0, -40.0, prior)
    seen_p, seen_u = np.zeros(size, np.int32), np.zeros(size, np.int32)
    for seen, own in ((seen_p, positive), (seen_u, unlabelled)):
        for d in own:
            seen[d] += 1  # a document's buckets are distinct
    # The share of toxic documents among those with a feature is prior * p_rate / u_rate. A feature is weighed if that is
    # at least ``purity`` and positives hold it more often than chance allows; others stay at 0.
    p_rate, u_rate = (seen_p + 1e-9) / len(positive), (seen_u + 0.5) / (len(unlabelled) + 1)
    expected = u_rate * len(positive)
    surprise = 2 * (seen_p * np.log((seen_p + 1e-9) / expected) - (seen_p - expected))
    sure = (seen_p > expected) & (surprise >= least_surprise) & (prior * p_rate >= purity * u_rate)
    chosen = np.flatnonzero(sure)
    place = np.full(size, -1, np.int32)
    place[chosen] = np.arange(len(chosen))
    positive, unlabelled = ([p[p >= 0] for p in (place[d] for d in docs)] for docs in (positive, unlabelled))
    everything, size = weight, max(1, len(chosen))
    weight = np.zeros(size)
    rng = np.random.default_rng(seed)
    bias, square, square_b = -2.0, np.full(size, 1e-6), 1e-6
    batches = max(1, min(len(positive) // 64, 64))
    sigmoid = lambda z: 1.0 / (1.0 + np.exp(-np.clip(z, -40, 40)))
    for _ in range(epochs):
        order_p, order_u = rng.permutation(len(positive)), rng.permutation(len(unlabelled))
        for k in range(batches):
            fp, sp = _csr([positive[i] for i in order_p[k::batches]])
            fu, su = _csr([unlabelled[i] for i in order_u[k::batches]])
            np_, nu = len(sp) - 1, len(su) - 1
            if not np_ or not nu:
                continue
            zp, zu = _sums(weight[fp], sp) + bias, _sums(weight[fu], su) + bias
            clean = np.logaddexp(0, zu).mean() - prior * np.logaddexp(0, zp).mean()
            if clean >= 0:
                gp, gu = (-prior * (1 - sigmoid(zp)) - prior * sigmoid(zp)) / np_, sigmoid(zu) / nu
            else:  # climb on the term that went below zero
                gp, gu = prior * sigmoid(zp) / np_, -sigmoid(zu) / nu
            grad = np.bincount(fp, np.repeat(gp, np.diff(sp)), size) + np.bincount(fu, np.repeat(gu, np.diff(su)), size)
            grad = grad + l2 * weight  # without features in a batch, the counts above are integers
            square += grad * grad
            weight = weight - rate / np.sqrt(square) * grad
            grad_b = gp.sum() + gu.sum()
            square_b += grad_b * grad_b
            bias -= rate / np.sqrt(square_b) * grad_b
    everything[chosen] = weight[: len(chosen)]
    return ToxicityModel(everything, 1.0, float(bias), prior)


def _features(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    known = Buckets()
    for b in batches:
        rows = []
        for text in text_bytes(b):
            found = set().union(*map(known.__getitem__, set(words(text))))
            rows.append(np.fromiter(found, np.int32, len(found)).tobytes())
        yield pa.RecordBatch.from_arrays([b.column("positive"), pa.array(rows, pa.binary())], ["positive", "features"])


def fit(docs: DataFrame, labels: DataFrame, max_positive: int = 4000, max_unlabelled: int = 16000, prior: float | None = None, seed: int = 7) -> ToxicityModel:
    """Fits on the learning fold (crc32 of doc_id mod 4 is not 2). docs: doc_id, text; labels: doc_id, toxic."""
    spark = docs.sparkSession
    learn = labels.where(~in_fold(F.col("doc_id"), 4, 2) & F.col("doc_id").isNotNull() & F.col("toxic").isNotNull())
    learn = learn.groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    n, toxic = learn.agg(F.count("*"), F.coalesce(F.sum("toxic"), F.lit(0))).first()
    prior = prior if prior is not None else min(0.9, max(1e-4, toxic / n if n else 1e-4))
    order = F.xxhash64(F.lit(seed), F.col("doc_id"))
    positive_ids = learn.where("toxic = 1").select("doc_id").orderBy(order, "doc_id").limit(max_positive)
    unlabelled_ids = (
        docs.select("doc_id").where(~in_fold(F.col("doc_id"), 4, 2) & F.col("doc_id").isNotNull()).orderBy(F.xxhash64(F.lit(seed + 1), F.col("doc_id")), "doc_id").limit(max_unlabelled)
    )
    picked = [(r.doc_id, True) for r in positive_ids.collect()] + [(r.doc_id, False) for r in unlabelled_ids.collect()]
    chosen = spark.createDataFrame(picked, "_id long, positive boolean")
    sample = docs.select("doc_id", "text").join(F.broadcast(chosen), F.col("doc_id") == F.col("_id")).select("positive", "text")
    rows = sample.mapInArrow(lean(_features), "positive boolean, features binary")
    sets: dict[bool, list[bytes]] = {True: [], False: []}
    for r in rows.toLocalIterator():  # a partition at a time, and as bytes: the sample is the driver's largest load
        if len(r.features):
            sets[r.positive].append(bytes(r.features))
    for docs_of in sets.values():
        docs_of.sort()
    # The lists are handed over, not kept here, so that training can drop them once it has chosen its features.
    model = train_nnpu([np.frombuffer(d, np.int32) for d in sets.pop(True)], [np.frombuffer(d, np.int32) for d in sets.pop(False)], prior, seed=seed)
    release()  # else the sample's memory stays with the driver through all that comes after
    relieve(spark)
    return model


def score(docs: DataFrame, model: ToxicityModel, column: str = "score") -> DataFrame:
    """All columns of ``docs`` and the score of each whole text."""
    plain, names = numbered(docs)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    text_at = names.index("text")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        strong = {int(i): float(own.weight[i]) for i in np.flatnonzero(own.weight)}
        weights: dict[bytes, tuple[tuple[int, float], ...]] = {}
        for b in batches:
            evidence = []
            for text in text_bytes(b, text_at):
                found: dict[int, float] = {}
                for word in set(words(text)):
                    known = weights.get(word)
                    if known is None:
                        if len(weights) >= CACHE_ENTRIES:
                            weights.clear()
                        known = weights[word] = tuple((k, strong[k]) for k in features(word) if k in strong)
                    if known:
                        found.update(known)
                evidence.append(sum(found[k] for k in sorted(found)))
            scores = own.probability(np.array(evidence, float)) if own.weight.any() else np.zeros(len(evidence))
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(scores, pa.float64())], [*b.schema.names, "score"])

    schema = T.StructType([*plain.schema.fields, T.StructField("score", T.DoubleType())])
    return plain.mapInArrow(lean(run), schema).toDF(*names, column)


def filter_toxic(docs: DataFrame, labels: DataFrame, threshold: float = 0.3) -> DataFrame:
    """The rows whose score is below the threshold, with the columns they came with."""
    own = docs.columns
    model = fit(docs.select("doc_id", "text"), labels)
    scored = score(docs, model).toDF(*[f"c{i}" for i in range(len(own))], "score")
    return scored.where(F.col("score") < threshold).drop("score").toDF(*own)


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents", ["doc_id", "text"])
    model = fit(docs, load(spark, sf_dir, "labels", ["doc_id", "toxic"]))
    scored = score(docs, model)
    held = in_fold(F.col("doc_id"), 4, 2)
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))
