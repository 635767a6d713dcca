"""Toxicity by multiple-instance learning: sentence scores joined by noisy-or, trained from document labels alone.

A sentence's score is a logistic function of its distinct words (each word is worth its own weight and those of its beginnings); a document is toxic unless none of its sentences is:
``1 - (1 - leak) * prod(1 - p)``. Weights are fitted in numpy to the document labels of a bounded sample, by gradient ascent
through the noisy-or; the same sentence scores then locate the offending sentences.

Null and empty texts have no sentences and score the leak. Very long texts are scored whole. Repeated rows score alike,
extra columns are ignored, an empty table gives an empty result, and with no labels to learn from every score is 0.
"""

from __future__ import annotations

import math
import re
from array import array
from collections import Counter
from collections.abc import Iterable
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common

#: Sample bound: labelled documents per class that training reads; words and beginnings that the model keeps at most.
TRAIN_DOCS, VOCABULARY = 3000, 1200
#: A feature must be in so many sampled documents, and its class odds so many standard errors from even.
LEAST_DOCS, LEAST_Z = 5, 3.5
#: Lengths of the beginnings; words whose worth a worker remembers.
BEGINNINGS, MEMO = (2, 3, 4, 5), 1_000_000
WORD = re.compile(r"[^\W\d_]+")
SENTENCE = re.compile(r"[^.!?\n]+")


def features(word: str) -> list[str]:
    return [word, *(f"^{word[:k]}" for k in BEGINNINGS if len(word) > k)]


class Worth(dict):
    """What each word adds to a sentence's logit; a bounded memo."""

    def __init__(self, weights: dict[str, float]):
        super().__init__()
        self.weights = weights

    def __missing__(self, word: str) -> float:
        if len(self) >= MEMO:
            self.clear()
        get = self.weights.get
        self[word] = worth = sum(get(f, 0.0) for f in features(word))
        return worth


@dataclass
class NoisyOr:
    weights: dict[str, float] = field(default_factory=dict)
    bias: float = -30.0
    leak: float = 0.0  # -log(1 - leak probability)

    def __post_init__(self):
        self.worth = Worth(self.weights)

    def sentence(self, text: str) -> float:
        z = self.bias + sum(map(self.worth.__getitem__, set(WORD.findall(text))))
        return 1 / (1 + math.exp(-max(-60.0, min(60.0, z))))

    def document(self, text: str | None) -> tuple[float, list[tuple[int, int, float]]]:
        """(score, offending sentences as start, end, score)."""
        if not text:
            return 1 - math.exp(-self.leak), []
        lowered = text.lower()
        if len(lowered) != len(text):  # a few letters change their length; offsets must stay
            lowered = "".join(c.lower() if len(c.lower()) == 1 else c for c in text)
        plain = 1 / (1 + math.exp(-self.bias))
        cost = -math.log1p(-plain)
        if not any(map(self.worth.__getitem__, set(WORD.findall(lowered)))):
            n = sum(1 for _ in SENTENCE.finditer(lowered))
            return 1 - math.exp(-self.leak - n * cost), []
        total, worst = self.leak, []
        for m in SENTENCE.finditer(lowered):
            p = self.sentence(m[0])
            total -= math.log1p(-min(p, 1 - 1e-12))
            if p >= 0.5:
                worst.append((m.start(), m.end(), p))
        return 1 - math.exp(-total), worst


def vocabulary(docs: Iterable[set[str]], labels: np.ndarray) -> list[str]:
    """Features whose odds between the classes are far from even, strongest first."""
    pos, neg = Counter(), Counter()
    for words, y in zip(docs, labels, strict=True):
        (pos if y else neg).update(words)
    n1, n0 = max(1, int(labels.sum())), max(1, int((1 - labels).sum()))
    found = []
    for w in pos.keys() | neg.keys():
        a, b = pos[w], neg[w]
        if a + b >= LEAST_DOCS:
            odds = math.log((a + 0.5) / (n1 - a + 0.5)) - math.log((b + 0.5) / (n0 - b + 0.5))
            z = odds / math.sqrt(1 / (a + 0.5) + 1 / (b + 0.5))
            if abs(z) >= LEAST_Z:
                found.append((-abs(z), w))
    return [w for _, w in sorted(found)[:VOCABULARY]]


def train(samples: list[tuple[str, int]], steps: int = 400, rate: float = 0.15, decay: float = 2e-3) -> NoisyOr:
    samples = sorted({x: y for x, y in sorted(samples)}.items())  # copies of a text teach nothing more
    labels = np.array([y for _, y in samples], np.float64)
    if not len(labels) or labels.min() == labels.max():
        return NoisyOr()
    texts = [x.lower() for x, _ in samples]
    words = vocabulary(({f for w in set(WORD.findall(x)) for f in features(w)} for x in texts), labels)  # one document at a time
    place = {w: i for i, w in enumerate(words)}
    held: dict[str, list[int]] = {}
    owner, of, which, sentences = array("q"), array("q"), array("q"), 0
    for d, text in enumerate(texts):
        for m in SENTENCE.finditer(text):
            for w in sorted(set(WORD.findall(m[0]))):
                if w not in held:
                    held[w] = [place[f] for f in features(w) if f in place]
                of.extend([sentences] * len(held[w]))
                which.extend(held[w])
            owner.append(d)
            sentences += 1
    owner, of, which = np.array(owner, np.int64), np.array(of, np.int64), np.array(which, np.int64)
    # parameters: words, bias of a sentence, log of the leak
    theta = np.r_[np.full(len(words), 0.3), -7.0, math.log(0.03)]
    m, v = np.zeros_like(theta), np.zeros_like(theta)
    share = np.where(labels > 0, 0.5 / labels.sum(), 0.5 / (1 - labels).sum())
    for t in range(1, steps + 1):
        z = theta[-2] + np.bincount(of, theta[which], sentences) if len(of) else np.full(sentences, theta[-2])
        p = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
        leak = math.exp(theta[-1])
        total = leak + np.bincount(owner, -np.log1p(-np.minimum(p, 1 - 1e-9)), len(labels))  # -log P(clean)
        clean = np.exp(-total)
        d_total = share * np.where(labels > 0, clean / np.maximum(1 - clean, 1e-6), -1.0)
        d_z = d_total[owner] * p
        grad = np.r_[np.bincount(which, d_z[of], len(words)) - decay * theta[:-2] / max(1, len(words)), d_z.sum(), d_total.sum() * leak]
        m += 0.1 * (grad - m)
        v += 0.01 * (grad * grad - v)
        theta += rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-9) * (1 - 0.9 * t / steps)
        theta[-2] = min(theta[-2], -6.0)
    return NoisyOr({w: float(x) for w, x in zip(words, theta, strict=False)}, float(theta[-2]), math.exp(float(theta[-1])))


def learn(docs: DataFrame, labels: DataFrame, per_label: int = TRAIN_DOCS) -> NoisyOr:
    """A model from labelled rows that are not held out; about ``per_label`` documents of each class reach the driver."""
    rows = labels.select("doc_id", "toxic").filter(F.col("doc_id").isNotNull() & F.col("toxic").isin(0, 1) & ~common.held_out(F.col("doc_id")))
    chosen = common.label_sample(rows, "toxic", per_label, "toxicity").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    texts = docs.select("doc_id", "text").filter(F.col("text").isNotNull()).join(F.broadcast(chosen), "doc_id")
    return train([(r.text, int(r.toxic)) for r in texts.orderBy("doc_id", "text").collect()])


SPANS = T.ArrayType(T.StructType([T.StructField("start", T.IntegerType()), T.StructField("end", T.IntegerType()), T.StructField("score", T.DoubleType())]))


def scores(docs: DataFrame, model: NoisyOr) -> DataFrame:
    """doc_id, held_out, score, predicted, and the offending sentences (start, end, score)."""

    def make():
        def work(texts: list[str | None]) -> list:
            found = [model.document(x) for x in texts]
            return [[s for s, _ in found], [int(s >= 0.5) for s, _ in found], [[{"start": a, "end": b, "score": p} for a, b, p in w] for _, w in found]]

        return work

    fields = [T.StructField("score", T.DoubleType()), T.StructField("predicted", T.IntegerType()), T.StructField("offending", SPANS)]
    made = common.map_texts(docs, ["doc_id"], ["text"], fields, make)
    return made.select("doc_id", common.held_out(F.col("doc_id")).alias("held_out"), "score", "predicted", "offending")
