"""Language identification by a bidirectional gated recurrent network over bytes.

The network is small and trained here, in numpy, by backpropagation through time on windows of a bounded sample of
labelled rows. It labels every byte position of every text; a document's probabilities are the mean over its positions.

Nulls and texts without a letter: ``und`` with score 0. Long texts run as windows of ``WINDOW`` bytes, all of them.
Repeated rows are scored alike, extra columns are ignored, an empty table gives an empty result, and with no labelled
row to learn from every text is ``und``.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import common

WINDOW = 96
#: Sample bound: documents per language that training reads.
TRAIN_DOCS = 250
#: Windows per training step, steps, windows of one document at most.
TRAIN_BATCH, TRAIN_STEPS, TRAIN_PER_DOC = 384, 260, 24
HIDDEN = 12
UNKNOWN = "und"
LETTER = re.compile(r"[^\W\d_]")


def sigmoid(x: np.ndarray, out: np.ndarray | None = None) -> np.ndarray:
    out = np.multiply(x, 0.5, out=out)
    np.tanh(out, out=out)
    out += 1
    out *= 0.5
    return out


@dataclass
class ByteGru:
    """Weights of both directions, stacked on axis 0 (forward, backward); gates in the order update, reset, candidate."""

    labels: list[str]
    table: np.ndarray  # 2 x 256 x 3H: input weights of each byte with the biases
    recur: np.ndarray  # 2 x H x 3H
    head: np.ndarray  # 2H x labels
    bias: np.ndarray  # labels

    @staticmethod
    def fresh(labels: list[str], hidden: int = HIDDEN, seed: int = 7) -> ByteGru:
        rng = np.random.default_rng(seed)
        f = np.float32
        return ByteGru(labels, rng.normal(0, 0.3, (2, 256, 3 * hidden)).astype(f), rng.normal(0, 0.3, (2, hidden, 3 * hidden)).astype(f), rng.normal(0, 0.3, (2 * hidden, len(labels))).astype(f), np.zeros(len(labels), f))

    def states(self, windows: np.ndarray, trace: list | None = None) -> np.ndarray:
        """windows: T x B bytes. Hidden states 2 x T x B x H, the backward ones in reading order."""
        n, width = windows.shape
        h = self.recur.shape[1]
        both = np.stack([windows, windows[::-1]])
        state = np.zeros((2, width, h), np.float32)
        out = np.empty((2, n, width, h), np.float32)
        for t in range(n):
            x = np.stack([self.table[0][both[0, t]], self.table[1][both[1, t]]])
            gates = x[:, :, : 2 * h]
            gates += state @ self.recur[:, :, : 2 * h]
            gates = sigmoid(gates)
            z, r = gates[:, :, :h], gates[:, :, h:]
            gated = r * state
            cand = x[:, :, 2 * h :] + gated @ self.recur[:, :, 2 * h :]
            np.tanh(cand, out=cand)
            new = cand - state
            new *= z
            new += state
            if trace is not None:
                trace.append((state, z, r, gated, cand))
            state = new
            out[0, t], out[1, n - 1 - t] = new[0], new[1]
        return out

    def position_probabilities(self, states: np.ndarray) -> np.ndarray:
        """T x B x labels: what every byte position says."""
        logits = states[0] @ self.head[: states.shape[-1]] + states[1] @ self.head[states.shape[-1] :] + self.bias
        logits -= logits.max(-1, keepdims=True)
        np.exp(logits, out=logits)
        logits /= logits.sum(-1, keepdims=True)
        return logits

    def train_step(self, windows: np.ndarray, target: np.ndarray, adam: dict, rate: float) -> float:
        """One step of Adam on the mean cross-entropy of all positions; gradients by backpropagation through time."""
        trace: list = []
        h = self.recur.shape[1]
        states = self.states(windows, trace)
        n, width = windows.shape
        probs = self.position_probabilities(states)
        loss = float(-np.log(probs[:, np.arange(width), target] + 1e-9).mean())
        d_logits = probs
        d_logits[:, np.arange(width), target] -= 1
        d_logits /= n * width
        flat = d_logits.reshape(-1, d_logits.shape[-1])
        grad = {"head": np.concatenate([states[d].reshape(-1, h).T @ flat for d in (0, 1)]), "bias": flat.sum(0)}
        d_states = np.stack([d_logits @ self.head[:h].T, (d_logits @ self.head[h:].T)[::-1]])
        d_table, d_recur = np.zeros_like(self.table), np.zeros_like(self.recur)
        both = np.stack([windows, windows[::-1]])
        later = np.zeros((2, width, h), np.float32)
        for t in range(n - 1, -1, -1):
            state, z, r, gated, cand = trace[t]
            d_new = d_states[:, t] + later
            d_cand = d_new * z * (1 - cand * cand)
            d_gated = d_cand @ self.recur[:, :, 2 * h :].transpose(0, 2, 1)
            d_z = d_new * (cand - state) * z * (1 - z)
            d_r = d_gated * state * r * (1 - r)
            d_gates = np.concatenate([d_z, d_r], -1)
            later = d_new * (1 - z) + d_gated * r + d_gates @ self.recur[:, :, : 2 * h].transpose(0, 2, 1)
            d_recur[:, :, : 2 * h] += state.transpose(0, 2, 1) @ d_gates
            d_recur[:, :, 2 * h :] += gated.transpose(0, 2, 1) @ d_cand
            d_input = np.concatenate([d_gates, d_cand], -1)
            for d in (0, 1):
                order = np.argsort(both[d, t], kind="stable")
                seen, starts = np.unique(both[d, t][order], return_index=True)
                d_table[d][seen] += np.add.reduceat(d_input[d][order], starts, axis=0)
        grad |= {"table": d_table, "recur": d_recur}
        adam["t"] = adam.get("t", 0) + 1
        for name, g in grad.items():
            m, v = adam.setdefault(name, (np.zeros_like(g), np.zeros_like(g)))
            m += 0.1 * (g - m)
            v += 0.01 * (g * g - v)
            step = rate * (m / (1 - 0.9 ** adam["t"])) / (np.sqrt(v / (1 - 0.99 ** adam["t"])) + 1e-8)
            setattr(self, name, (getattr(self, name) - step).astype(np.float32))
        return loss

    def documents(self, texts: list[bytes], width: int = 2048) -> np.ndarray:
        """Mean probabilities of each text (zeros for an empty one)."""
        size = np.array([len(x) for x in texts], np.int64)
        joined = np.frombuffer(b"".join(texts), np.uint8)
        starts = np.cumsum(size) - size
        pieces = -(-size // WINDOW)
        owner = np.repeat(np.arange(len(texts)), pieces)
        nth = np.arange(len(owner)) - np.repeat(np.cumsum(pieces) - pieces, pieces)
        begin = starts[owner] + nth * WINDOW
        length = np.minimum(WINDOW, size[owner] - nth * WINDOW)
        total = np.zeros((len(texts), len(self.labels)))
        order = np.argsort(-length, kind="stable")
        for at in range(0, len(order), width):
            some = order[at : at + width]
            longest = int(length[some[0]])
            steps = np.arange(longest)[:, None]
            inside = steps < length[some]
            windows = joined[np.minimum(begin[some] + steps, len(joined) - 1)]
            if not inside.all():
                windows = np.where(inside, windows, 32)  # padding reads as blanks and is not pooled
            probs = self.position_probabilities(self.states(windows))
            if not inside.all():
                probs *= inside[:, :, None]
            np.add.at(total, owner[some], probs.sum(0))
        return total / np.maximum(size, 1)[:, None]


def cut_windows(text: bytes, most: int, rng: np.random.Generator) -> list[bytes]:
    found = [text[i : i + WINDOW] for i in range(0, len(text), WINDOW)]
    if len(found) > most:
        found = [found[i] for i in rng.choice(len(found), most, replace=False)]
    return [x.ljust(WINDOW, b" ") for x in found]


def train(samples: list[tuple[str, str]], steps: int = TRAIN_STEPS, seed: int = 7) -> ByteGru:
    """samples: (text, language). Windows are drawn evenly over the languages."""
    labels = sorted({y for _, y in samples})
    rng = np.random.default_rng(seed)
    of = [np.frombuffer(b"".join(w for x, y in samples if y == lab for w in cut_windows(x.encode("utf-8", "replace"), TRAIN_PER_DOC, rng)), np.uint8).reshape(-1, WINDOW) for lab in labels]
    model, adam = ByteGru.fresh(labels, seed=seed), {}
    each = max(1, TRAIN_BATCH // len(labels))
    for step in range(steps):
        some = np.concatenate([w[rng.integers(0, len(w), each)] for w in of])
        model.train_step(some.T, np.repeat(np.arange(len(labels)), each), adam, 0.03 * (1 - 0.9 * step / steps))
    return model


def learn(docs: DataFrame, per_label: int = TRAIN_DOCS) -> ByteGru | None:
    """A model from the rows that are not held out; the driver gets about ``per_label`` texts of each language."""
    rows = docs.select("doc_id", "text", "lang").filter(F.col("lang").isNotNull() & F.col("text").isNotNull() & ~common.held_out(F.col("doc_id")))
    rows = common.label_sample(rows, "lang", per_label, "lang-id")
    samples = [(r.text, r.lang) for r in rows.orderBy("doc_id", "text", "lang").collect() if LETTER.search(r.text)]
    return train(samples) if samples else None


def predict(docs: DataFrame, model: ByteGru | None) -> DataFrame:
    """doc_id, held_out, lang_pred, score, and the mean probability of every language as ``probabilities``."""

    def make():
        def work(texts: list[str | None]) -> list:
            if model is None:
                return [[UNKNOWN] * len(texts), [0.0] * len(texts), [[] for _ in texts]]
            live = [bool(x) and LETTER.search(x) is not None for x in texts]
            pooled = model.documents([x.encode("utf-8", "replace") if ok else b"" for x, ok in zip(texts, live, strict=True)])
            best = pooled.argmax(1)
            return [[model.labels[k] if ok else UNKNOWN for k, ok in zip(best, live, strict=True)], np.where(live, np.clip(pooled.max(1), 0, 1), 0.0), pooled.tolist()]

        return work

    fields = [T.StructField("lang_pred", T.StringType()), T.StructField("score", T.DoubleType()), T.StructField("probabilities", T.ArrayType(T.DoubleType()))]
    made = common.map_texts(docs, ["doc_id"], ["text"], fields, make)
    return made.select("doc_id", common.held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score", "probabilities")
