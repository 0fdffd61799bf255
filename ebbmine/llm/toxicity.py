"""Toxicity by multiple-instance learning: sentence scores combined by noisy-or.

A document is a bag of sentences; sentence s has probability p_s = sigmoid(bias + sum of the weights of its
distinct words), the document 1 - prod(1 - p_s). Weights are learnt from document labels alone, by
AdaGrad on the bag's log loss, and calibrated on a fifth of the sample; the sentence scores then locate the offending sentences. A word's
weight is the sum of hashed features: the word and its beginnings of four and five letters, so
that inflected forms share evidence.

The classifier is fitted on a bounded sample (at most `per_class` labelled documents of each
label, the lowest by hash of doc_id, and `most_bytes` of text in all); scoring is a map over every document and every sentence.

Null or empty text: no sentence, score 0. Rows with null or repeated doc_id are scored one by one;
repeated labels of a document count as toxic if one is. No usable label: all weights stay 0.
Extra columns are ignored. Very long texts are scored whole.
"""

from __future__ import annotations

import math
import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import only, tidy, written

SENTENCE = re.compile(r"[^.!?\n]+[.!?]*")
WORD = re.compile(r"[^\W\d_]+")
#: A document is rejected from this score on.
THRESHOLD = 0.7


@dataclass
class NoisyOr:
    weights: np.ndarray
    bias: float
    shift: float = 0.0  # added to a document's log odds, see calibrated()

    def scorer(self):
        """A function text -> (score, [(start, end, p)] of sentences with p >= 0.5)."""
        weights, bias, shift = self.weights, self.bias, self.shift

        class Known(dict):
            def __missing__(self, word):
                if len(self) > 150_000:  # bounded memory
                    self.clear()
                self[word] = value = float(weights[features(word, len(weights))].sum())
                return value

        known = Known()
        get = known.__getitem__

        def score(text: str | None):
            if not text:
                return 0.0, []
            log_clean, worst = 0.0, []
            for m in SENTENCE.finditer(text):
                words = {*WORD.findall(m[0].lower())}
                if not words:
                    continue
                z = bias + sum(map(get, words))
                # log(1 - sigmoid(z))
                log_clean -= math.log1p(math.exp(-abs(z))) + max(z, 0.0)
                if z >= 0:
                    worst.append((m.start(), m.end(), 1 / (1 + math.exp(-z)) if z < 700 else 1.0))
            if log_clean < -30:
                return 1.0, worst
            p = -math.expm1(log_clean)
            return (1 / (1 + math.exp(-(math.log(p) - log_clean) - shift)) if p > 1e-300 else 0.0), worst

        return score


def features(word: str, size: int) -> list[int]:
    marks = (f"w{word}", f"4{word[:4]}", f"5{word[:5]}")
    return [xxhash.xxh32_intdigest(x) % size for x in marks]


def fit(texts: list[str], toxic: list[int], size: int = 1 << 20, epochs: int = 12, rate: float = 0.3, shrink: float = 2e-7, noise: float = 0.01, seed: int = 5) -> NoisyOr:
    """Learns the word weights from whole documents and their labels, of which a share of `noise` may be wrong."""
    ids: dict[str, list[int]] = {}
    bags = []
    for text in texts:
        flat, starts = [], []
        for m in SENTENCE.finditer(text or ""):
            words = {*WORD.findall(m[0].lower())}
            if words:
                starts.append(len(flat))
                for w in sorted(words):
                    known = ids.get(w)
                    if known is None:
                        known = ids[w] = features(w, size)
                    flat += known
        bags.append((np.array(flat, np.int64), np.array(starts, np.int64)))
    weights, power = np.zeros(size), np.full(size, 1e-3)
    bias, bias_power = -8.0, 1e-3
    if len(set(toxic)) == 2:  # start: log odds of a document with the feature, smoothed by one document in the labels' proportion
        of = np.bincount(toxic, minlength=2)
        seen = np.repeat((of / of.sum())[:, None], size, axis=1)
        for (flat, _), y in zip(bags, toxic):
            seen[y][np.unique(flat)] += 1
        weights = np.maximum(np.log(seen[1] / of[1]) - np.log(seen[0] / of[0]) - 1.5, 0)
    rng = np.random.default_rng(seed)
    for _ in range(epochs if bags and len(set(toxic)) == 2 else 0):
        for k in rng.permutation(len(bags)):
            flat, starts = bags[k]
            if not len(starts):
                continue
            z = bias + np.add.reduceat(weights[flat], starts)
            p = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
            clean = (1 - 2 * noise) * math.exp(max(-60.0, float(np.log1p(-np.minimum(p, 1 - 1e-12)).sum())))
            slope = -p * (clean / (1 - noise - clean)) if toxic[k] else p * (clean / (clean + noise))
            each = np.repeat(slope, np.diff(np.append(starts, len(flat))))
            at, inverse = np.unique(flat, return_inverse=True)
            push = np.bincount(inverse, weights=each)
            power[at] += push * push
            weights[at] -= rate * push / np.sqrt(power[at])
            weights[at] = np.maximum(weights[at] - shrink * len(bags) * rate / np.sqrt(power[at]), 0)
            total = float(slope.sum())
            bias_power += total * total
            bias -= rate * total / math.sqrt(bias_power)
    return NoisyOr(weights.astype(np.float32), float(bias))


def calibrated(texts: list[str], toxic: list[int]) -> NoisyOr:
    """Fits on four fifths and shifts the log odds so that THRESHOLD falls where the other fifth is parted best,
    by at most 2 (a small sample says little about the tails)."""
    model = fit([x for k, x in enumerate(texts) if k % 5], [y for k, y in enumerate(toxic) if k % 5])
    judge = model.scorer()
    seen = sorted((min(max(judge(x)[0], 1e-9), 1 - 1e-9), y) for x, y in zip(texts[::5], toxic[::5]))
    right = sum(y for _, y in seen)  # all predicted 1
    best = (right, 0, len(seen) and -1)
    for k, (_, y) in enumerate(seen):
        right += 1 - 2 * y
        best = max(best, (right, -k, k))
    k = best[2]
    if len({y for _, y in seen}) == 2 and 0 <= k < len(seen) - 1:
        odds = [math.log(p / (1 - p)) for p, _ in (seen[k], seen[k + 1])]
        model.shift = min(2.0, max(-2.0, math.log(THRESHOLD / (1 - THRESHOLD)) - sum(odds) / 2))
    return model


def in_training(doc_id) -> F.Column:
    return F.pmod(F.crc32(F.encode(doc_id.cast("string"), "UTF-8")), F.lit(3)) != 1


def train(docs: DataFrame, labels: DataFrame, per_class: int = 3000, most_bytes: int = 64 << 20) -> NoisyOr:
    """Fits on at most per_class documents of each label and most_bytes of text, held-out rows never among them.
    The sample is bounded before it leaves Spark: of rows that share a doc_id one is taken, whole
    documents are taken by the hash of doc_id until the bytes are used up (a document that does not fit is passed over)."""
    known = only(labels, doc_id="bigint", toxic="int").where(F.col("toxic").isin(0, 1) & in_training(F.col("doc_id")))
    known = known.groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    picked = [known.where(F.col("toxic") == y).orderBy(F.xxhash64("doc_id"), "doc_id").limit(per_class) for y in (0, 1)]
    sample = F.broadcast(picked[0].unionAll(picked[1]))  # at most 2 * per_class rows of two numbers
    found = only(docs, doc_id="bigint", text="string").where(F.octet_length("text") <= most_bytes).join(sample, "doc_id")
    once = written(found.groupBy("doc_id", "toxic").agg(F.min_by("text", F.xxhash64("text")).alias("text")), "toxicity-sample")
    sizes = once.select("doc_id", F.octet_length("text").alias("bytes"), F.xxhash64("doc_id").alias("h")).orderBy("h", "doc_id").collect()  # two numbers a sampled document
    fits, left = [], most_bytes
    for r in sizes:
        if r["bytes"] <= left:
            left -= r["bytes"]
            fits.append(r["doc_id"])
    spark = docs.sparkSession
    chosen = F.broadcast(spark.createDataFrame([(x,) for x in fits], "doc_id bigint"))
    rows = once.join(chosen, "doc_id").toPandas().sort_values("doc_id", kind="stable")
    return calibrated(rows["text"].tolist(), rows["toxic"].tolist())


def score(docs: DataFrame, model: NoisyOr) -> DataFrame:
    """docs(doc_id, text) -> doc_id, score, offending: the sentences with p >= 0.5 (code points, end exclusive)."""
    sent = docs.sparkSession.sparkContext.broadcast(model)  # a fixed number of weights

    def run(batches):
        judge = sent.value.scorer()
        for batch in batches:
            got = [judge(x.as_py()) for x in batch.column("text")]
            spans = pa.array([[{"start": a, "end": b, "p": p} for a, b, p in x[1]] for x in got], pa.list_(pa.struct([("start", pa.int32()), ("end", pa.int32()), ("p", pa.float64())])))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array([min(1.0, max(0.0, x[0])) for x in got], pa.float64()), spans], ["doc_id", "score", "offending"])

    return only(docs, doc_id="bigint", text="string").mapInArrow(tidy(run), "doc_id bigint, score double, offending array<struct<start:int,end:int,p:double>>")


def without_toxic(docs: DataFrame, model: NoisyOr) -> DataFrame:
    """The rows of docs, with all their columns, whose text scores below THRESHOLD."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        judge = sent.value.scorer()
        for batch in batches:
            yield batch.filter(pa.array([judge(x.as_py())[0] < THRESHOLD for x in batch.column("text")], pa.bool_()))

    return docs.mapInArrow(tidy(run), docs.schema)
