"""Hashed n-gram features of whole texts, and softmax regression on them, in numpy over flat bytes.

A text's features are the relative frequencies of its hashed words, pairs of neighbouring words, and byte
3- and 4-grams; each of the four blocks sums to SCALE. Scoring needs no sparse matrix: a class's logit is the
mean of the weights met at each position, block by block.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .flat import BYTE_CODE, LOWER, Texts, mix, prefix_hash, span_hash, texts_of

BITS = 17
SCALE = 40.0
_U = np.uint64


def features(t: Texts) -> list[tuple[np.ndarray, np.ndarray]]:
    """Blocks of (feature of each position, n + 1 offsets of the texts' positions)."""
    low = LOWER[t.data]
    codes = BYTE_CODE[low]
    s, e, at = t.words(low)
    word = span_hash(prefix_hash(codes), s, e)
    out = [((word >> _U(64 - BITS)).astype(np.int64), at)]
    pair = mix(word[:-1] * _U(3) + word[1:]) if len(word) > 1 else word[:0]
    keep = np.ones(len(pair), bool)
    inner = at[1:-1]
    keep[inner[(inner > 0) & (inner <= len(pair))] - 1] = False  # pairs across two texts
    cum = np.concatenate([[0], np.cumsum(keep)])
    out.append(((pair[keep] >> _U(64 - BITS)).astype(np.int64), cum[np.minimum(at, len(pair))]))
    for k in (3, 4):
        n = max(0, len(low) - k + 1)
        g = codes[:n].copy()
        for i in range(1, k):
            g = g * _U(0x100000001B3) + codes[i : i + n]
        keep = np.ones(n, bool)
        for c in np.unique(t.cuts[1:-1]):
            keep[max(0, c - k + 1) : c] = False
        cum = np.concatenate([[0], np.cumsum(keep)])
        out.append(((mix(g[keep]) >> _U(64 - BITS)).astype(np.int64), cum[np.minimum(t.cuts, n)]))
    return out


class Softmax:
    """Multinomial logistic regression over the hashed features."""

    def __init__(self, classes: list):
        self.classes = classes
        self.w = np.zeros((4, 1 << BITS, len(classes)), np.float32)
        self.b = np.zeros(len(classes))
        self.heat = np.ones(1)

    def logits(self, t: Texts) -> np.ndarray:
        out = np.tile(self.b, (len(t), 1))
        for block, (f, at) in enumerate(features(t)):
            n = np.maximum(np.diff(at), 1)
            full = np.flatnonzero(n * (at[1:] > at[:-1]))
            if len(full):
                out[full] += SCALE * np.add.reduceat(self.w[block][f], at[full], axis=0, dtype=np.float64) / n[full, None]
        return out

    def predict(self, t: Texts) -> np.ndarray:
        z = self.logits(t) * self.heat
        p = np.exp(z - z.max(1, keepdims=True))
        return p / p.sum(1, keepdims=True)

    def fit(self, texts: list[str], y: np.ndarray, steps: int = 60, rate: float = 0.05, decay: float = 1e-4, seed: int = 3) -> Softmax:
        """Full-batch adaptive gradient steps on four fifths of the texts; the rest sets the temperature."""
        if not len(texts):
            return self
        rows = np.random.default_rng(seed).permutation(len(texts))
        fit_on, held = (rows[len(rows) // 5 :], rows[: len(rows) // 5]) if len(rows) >= 20 else (rows, rows)
        blocks: list[list] = [[] for _ in range(4)]
        base = 0
        for t in texts_of(pa.array([texts[i] for i in fit_on], pa.large_string())):
            for block, (f, at) in enumerate(features(t)):
                row = np.repeat(np.arange(len(t)), np.diff(at))
                key, n = np.unique((row.astype(np.int64) << BITS) | f, return_counts=True)
                row = key >> BITS
                blocks[block].append((row + base, key & ((1 << BITS) - 1), SCALE * n / np.maximum(np.diff(at), 1)[row]))
            base += len(t)
        row, col, val = (np.concatenate([np.concatenate([x[i] for x in b]) + (k << BITS if i == 1 else 0) for k, b in enumerate(blocks)]) for i in range(3))
        target = np.eye(len(self.classes))[y[fit_on]]
        weight = (1 / np.maximum(target.sum(0), 1))[y[fit_on]]  # each class counts alike
        weight = weight / weight.sum()
        w = np.zeros((len(self.classes), 4 << BITS))
        m, v = np.zeros_like(w), np.zeros_like(w)
        for step in range(1, steps + 1):
            z = np.stack([np.bincount(row, val * w[k][col], len(fit_on)) for k in range(len(self.classes))], 1) + self.b
            p = np.exp(z - z.max(1, keepdims=True))
            p /= p.sum(1, keepdims=True)
            d = (p - target) * weight[:, None]
            for k in range(len(self.classes)):
                g = np.bincount(col, val * d[row, k], w.shape[1]) + decay * w[k]
                m[k] += 0.1 * (g - m[k])
                v[k] += 0.01 * (g * g - v[k])
                w[k] -= rate * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.99**step)) + 1e-5)
            self.b -= rate * d.sum(0)
        self.w = w.reshape(len(self.classes), 4, 1 << BITS).transpose(1, 2, 0).astype(np.float32).copy()
        z = np.concatenate([self.logits(t) for t in texts_of(pa.array([texts[i] for i in held], pa.large_string()))])
        heats = np.geomspace(0.1, 5, 40)
        loss = [np.mean(np.log(np.exp(h * (z - z.max(1, keepdims=True))).sum(1)) - h * (z[np.arange(len(z)), y[held]] - z.max(1))) for h in heats]
        self.heat = heats[[int(np.argmin(loss))]]  # calibrates the probabilities on rows the weights never saw
        return self


def labelled_sample(docs: DataFrame, labels: DataFrame, column: str, per_value: int, values: tuple = (0, 1)) -> tuple[list, list[str], np.ndarray]:
    """Ids, texts and labels of at most ``per_value`` labelled documents of each value, those first in the order of a hash."""
    one = labels.filter(F.col("doc_id").isNotNull() & F.col(column).isNotNull()).groupBy(F.col("doc_id").alias("_d")).agg(F.max(column).alias("_y"))
    some = None
    for v in values:
        part = one.filter(F.col("_y") == F.lit(v)).orderBy(F.xxhash64("_d"), "_d").limit(per_value)
        some = part if some is None else some.unionByName(part)
    rows = docs.select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    got = rows.join(F.broadcast(some), F.col("doc_id") == F.col("_d")).select("doc_id", "text", "_y").toPandas().sort_values(["doc_id", "text"])
    at = {v: i for i, v in enumerate(values)}
    return got["doc_id"].tolist(), got["text"].tolist(), got["_y"].map(at).to_numpy(np.int64) if len(got) else np.zeros(0, np.int64)
