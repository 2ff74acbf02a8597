"""Toxicity by multiple-instance learning.

Only documents are labelled; sentences are the instances.  A sentence's probability is a logistic
function of its words and word beginnings, a document is toxic if any sentence is (noisy-or), and
the weights are fitted to the document labels through that combination.  The fitted weights then
tell the offending sentences.

Fitting uses at most ``SAMPLE`` labelled documents of each class (the smallest hashes of doc_id) and
``FEATURES`` features chosen by their log-likelihood ratio; every document is scored, on its whole text.

Defined results: a null, empty or wordless text scores as a text of no sentence, 0; labels of other
values than 0 and 1 and rows without a text teach nothing; without any label all scores are 0;
repeated rows are scored alike; an empty table gives no rows.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from narrative_engine.llm.bytewords import hashed, sentence_of, spans, sums
from narrative_engine.llm.common import staged, table
from narrative_engine.llm.shingles import text_bytes
from narrative_engine.shipping import ship

SAMPLE = 4_000
FEATURES = 4_096
LEAST_DOCS = 4
BEGINNINGS = (4, 5, 6, 7, 8)  # bytes
THRESHOLD = 0.3
HELD_OUT, FOLDS = 2, 4
STEPS, RATE, DECAY = 400, 0.1, 2e-4


def fold(doc_id="doc_id"):
    return F.pmod(F.crc32(F.col(doc_id).cast("string").cast("binary")), F.lit(FOLDS))


def features(data: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Feature hashes (families x words), sentence of each word, first and last byte of each word."""
    first, last = spans(data)
    if not len(first):
        return np.empty((0, 0), dtype=np.uint64), first, first, last
    total = sums(data)
    rows = [hashed(total, first, last)]
    for n in BEGINNINGS:
        h = hashed(total, first, np.minimum(first + n, last), n)
        rows.append(np.where(last - first > n, h, np.uint64(0)))  # a shorter word has no such beginning
    return np.stack(rows), sentence_of(data, first), first, last


@dataclass(frozen=True)
class Model:
    keys: np.ndarray  # sorted feature hashes
    weights: np.ndarray
    bias: float
    gate: np.ndarray  # 2^16 flags of the keys' low bits, to pass over most words quickly

    def sentences(self, data: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Probability, first byte and past-the-last byte of each sentence."""
        h, sentence, first, last = features(data)
        if not len(first):
            return np.empty(0), first, last
        n = int(sentence[-1]) + 1
        z = np.full(n, self.bias)
        _, word = hit = np.nonzero(self.gate[(h & np.uint64(0xFFFF)).astype(np.int64)])
        if len(word):
            found = h[hit]
            at = np.minimum(np.searchsorted(self.keys, found), len(self.keys) - 1)
            ok = self.keys[at] == found
            # a feature counts once in a sentence
            once = np.unique(sentence[word[ok]].astype(np.int64) * len(self.keys) + at[ok])
            z += np.bincount(once // len(self.keys), weights=self.weights[once % len(self.keys)], minlength=n)
        starts = np.flatnonzero(np.concatenate(([True], np.diff(sentence) > 0)))
        return 1 / (1 + np.exp(-z)), first[starts], last[np.concatenate((starts[1:] - 1, [len(last) - 1]))]


EMPTY = Model(np.zeros(1, dtype=np.uint64), np.zeros(1), -40.0, np.zeros(1 << 16, dtype=bool))


def fit(bags: list[tuple[int, int, np.ndarray, np.ndarray]], keys: np.ndarray, base: float) -> Model:
    """Weights from (label, sentences, sentence of, feature of) of each document; ``base``: share of toxic ones."""
    y = np.array([b[0] for b in bags], dtype=float)
    size = np.array([max(1, b[1]) for b in bags])
    at = np.concatenate(([0], np.cumsum(size)))
    sentence = np.concatenate([b[2] + o for b, o in zip(bags, at)]).astype(np.int64)
    feature = np.concatenate([b[3] for b in bags]).astype(np.int64)
    doc = np.repeat(np.arange(len(bags)), size)
    # classes were drawn apart, so their rows are weighed back to the share they have
    share = np.where(y == 1, base / max(1e-9, y.mean()), (1 - base) / max(1e-9, 1 - y.mean())) / len(y)
    w, b = np.zeros(len(keys)), -6.0
    m, v, t = np.zeros(len(keys) + 1), np.zeros(len(keys) + 1), 0
    for _ in range(STEPS):
        z = np.clip(b + np.bincount(sentence, weights=w[feature], minlength=at[-1]), -30, 30)
        p = 1 / (1 + np.exp(-z))
        none = np.exp(np.minimum(np.bincount(doc, weights=np.log1p(-np.minimum(p, 1 - 1e-12)), minlength=len(y)), -1e-12))
        # d loss / d z of a sentence: p for a clean document, p - p / P for a toxic one
        g = p * np.where(y == 1, -none / (1 - none), 1.0)[doc] * share[doc]
        grad = np.append(np.bincount(feature, weights=g[sentence], minlength=len(keys)) + DECAY * np.sign(w), g.sum())
        t += 1
        m, v = 0.9 * m + 0.1 * grad, 0.999 * v + 0.001 * grad**2
        step = RATE * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.999**t)) + 1e-9)
        w, b = w - step[:-1], b - step[-1]
    gate = np.zeros(1 << 16, dtype=bool)
    gate[(keys & np.uint64(0xFFFF)).astype(np.int64)] = True
    return Model(keys, w, float(b), gate)


def train(docs: DataFrame, labels: DataFrame) -> Model:
    """A model from the labelled documents outside the held-out fold."""
    ship(docs.sparkSession)
    known = labels.where("toxic IN (0, 1) AND doc_id IS NOT NULL").where(fold() != HELD_OUT).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    known = staged(known)
    n = {int(r["toxic"]): r["count"] for r in known.groupBy("toxic").count().collect()}
    if not n.get(1) or not n.get(0):
        return EMPTY
    order = F.xxhash64("doc_id")
    drawn = [known.where(F.col("toxic") == t).orderBy(order, "doc_id").limit(SAMPLE) for t in (0, 1)]
    drawn = drawn[0].unionByName(drawn[1]).select(F.col("doc_id").alias("_id"), F.col("toxic").cast("int").alias("toxic"))
    sample = staged(docs.join(F.broadcast(drawn), F.col("doc_id") == F.col("_id")).where("text IS NOT NULL").select("toxic", "text"))

    def seen(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            raw, ends = text_bytes(b.column(1))
            found = [np.unique(features(raw[i:j])[0]) for i, j in zip(ends[:-1], ends[1:])]
            flags = np.repeat(b.column(0).to_numpy(), [len(f) for f in found])
            key, where = np.unique(np.concatenate(found), return_inverse=True)
            total, hit = np.bincount(where, minlength=len(key)), np.bincount(where, weights=flags, minlength=len(key))
            yield pa.RecordBatch.from_arrays([pa.array(key.view(np.int64)), pa.array(hit.astype(np.int64)), pa.array((total - hit).astype(np.int64))], names=["key", "t", "c"])

    counts = sample.mapInArrow(seen, "key long, t long, c long").groupBy("key").agg(F.sum("t").alias("t"), F.sum("c").alias("c")).where("key <> 0")
    n1, n0 = sample.where("toxic = 1").count(), sample.where("toxic = 0").count()
    if not n1 or not n0:
        return EMPTY
    t, c = F.col("t") + 0.5, F.col("c") + 0.5
    # log-likelihood ratio of a feature that speaks for the label
    gain = t * F.log(t / (n1 + 1)) + c * F.log(c / (n0 + 1)) - (t + c) * F.log((t + c) / (n1 + n0 + 2))
    best = counts.where(F.col("t") >= LEAST_DOCS).where(t / (n1 + 1) > c / (n0 + 1)).orderBy(gain.desc(), "key").limit(FEATURES)
    keys = np.sort(best.select("key").toArrow().column(0).to_numpy().view(np.uint64))
    if not len(keys):
        return EMPTY
    sent = docs.sparkSession.sparkContext.broadcast(keys)

    def bags(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys = sent.value
        for b in batches:
            raw, ends = text_bytes(b.column(1))
            out = []
            for y, i, j in zip(b.column(0).to_pylist(), ends[:-1], ends[1:]):
                h, sentence, first, _ = features(raw[i:j])
                if not len(first):
                    out.append((y, 0, [], []))
                    continue
                at = np.minimum(np.searchsorted(keys, h), len(keys) - 1)
                _, word = hit = np.nonzero(keys[at] == h)
                once = np.unique(sentence[word].astype(np.int64) * len(keys) + at[hit])
                out.append((y, int(sentence[-1]) + 1, once // len(keys), once % len(keys)))
            kinds = [pa.int32(), pa.int64(), pa.list_(pa.int64()), pa.list_(pa.int64())]
            yield pa.RecordBatch.from_arrays([pa.array(list(x), k) for x, k in zip(zip(*out), kinds)], names=["y", "n", "s", "f"])

    rows = sample.mapInArrow(bags, "y int, n long, s array<long>, f array<long>").collect()  # at most 2 x SAMPLE documents, chosen features only
    rows.sort(key=lambda r: (r["y"], r["n"], r["s"], r["f"]))  # the same fit whatever order the tasks end in
    return fit([(r["y"], r["n"], np.array(r["s"], dtype=np.int64), np.array(r["f"], dtype=np.int64)) for r in rows], keys, n[1] / (n[0] + n[1]))


def scored(docs: DataFrame, model: Model, threshold: float = THRESHOLD) -> DataFrame:
    """Score, verdict and offending sentences (place in bytes, probability) of each document."""
    ship(docs.sparkSession)
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.struct([("first", pa.int64()), ("last", pa.int64()), ("p", pa.float64())])
        for b in batches:
            raw, ends = text_bytes(b.column(1))
            scores, found = [], []
            for i, j in zip(ends[:-1], ends[1:]):
                p, first, last = sent.value.sentences(raw[i:j])
                scores.append(float(-np.expm1(np.log1p(-np.minimum(p, 1 - 1e-12)).sum())) if len(p) else 0.0)
                found.append([{"first": int(first[k]), "last": int(last[k]), "p": float(p[k])} for k in np.flatnonzero(p >= threshold)])
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(scores), pa.array(found, pa.list_(kind))], names=["doc_id", "score", "offending"])

    rows = docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(score, "doc_id long, score double, offending array<struct<first:long,last:long,p:double>>")
    return rows.select("doc_id", (fold() == HELD_OUT).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"), "offending")


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return scored(docs, train(docs, table(spark, sf_dir, "labels")))


ORACLE = None
