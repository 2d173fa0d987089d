"""Toxicity: a linear-chain conditional random field over tokens, aggregated to document scores.

Tokens are runs of ASCII letters and digits and of bytes of longer characters; a chain is a sentence of at most
CHAIN tokens. Labels mark documents, so tokens are labelled from them first: in toxic documents a token
counts as toxic if its word or a prefix of it occurs in enough toxic and hardly any clean documents of the sample, beside
enough different neighbours.
The field then learns which hashed words, prefixes, suffixes and neighbours, and which transitions, go with
those labels. Forward and backward passes run position by position over all chains of a slice at once; with
two states each needs one number a token. A small logistic regression turns the marginals of a document (their
sum, largest value and share) into its score, learnt on a quarter of the sample that the field has not seen; runs of tokens
with marginals of one half or more are its spans.

Results by case: null and empty texts and texts without tokens have marginals of none and get that score; without
labelled rows of both values all scores are 0; repeated rows and null ids give one row each. Only the text
enters a score.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .flat import BYTE_CODE, LOWER, Texts, per_text, prefix_hash, span_hash, texts_of
from .hashed import labelled_sample
from .tables import remainder, widened

#: Labelled documents of each value that the field learns from, at most.
PER_VALUE = 800
FOLDS, CHAIN, BITS = 5, 256, 18
#: A token's feature marks it toxic if so many toxic documents have it (or this share), at this odds.
LEAST_DOCS, LEAST_SHARE, PRECISION = 4, 0.015, 0.97
#: Each APART-th row of the sample sets the document score only, if those hold LEAST_APART rows of either value; the share counts in SHARES.
APART, LEAST_APART, SHARES = 4, 10, 1000
_U = np.uint64
_IN = np.zeros(256, bool)
_IN[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True
_STOP = np.isin(np.arange(256), np.frombuffer(b".!?\n", np.uint8))


class Tokens:
    """Tokens of a slice: spans, n + 1 text offsets, own features (word and affixes) and chains."""

    def __init__(self, t: Texts):
        low = LOWER[t.data]
        self.start, self.stop, self.at = t.words(low, _IN)
        s, e = self.start, self.stop
        prefix = prefix_hash(BYTE_CODE[low])
        word = span_hash(prefix, s, e)
        self.own = [word] + [span_hash(prefix, s, np.minimum(e, s + k)) ^ _U(k * 0x51ED270B) for k in (4, 5, 6)]
        tail = span_hash(prefix, np.maximum(s, e - 4), e) ^ _U(0x7F4A7C15)
        text = np.repeat(np.arange(len(t)), np.diff(self.at))
        stops = np.concatenate([[0], np.cumsum(_STOP[low])])
        n = len(s)
        new = np.ones(n, bool)
        new[1:] = (text[1:] != text[:-1]) | (stops[s[1:]] != stops[s[:-1]])
        head = np.flatnonzero(new)
        since = np.arange(n) - np.repeat(head, np.diff(np.append(head, n)))
        new |= since % CHAIN == 0
        self.head = np.flatnonzero(new)
        self.len = np.diff(np.append(self.head, n))
        before, after = np.zeros(n, np.uint64), np.zeros(n, np.uint64)
        before[1:] = np.where(new[1:], 0, word[:-1] ^ _U(0x1234567))
        after[:-1] = np.where(new[1:], 0, word[1:] ^ _U(0x89ABCDE))
        self.before, self.after = before, after
        self.features = [(x * _U(0x9E3779B97F4A7C15) >> _U(64 - BITS)).astype(np.int64) for x in (*self.own, tail, before, after)]
        order = np.argsort(-self.len, kind="stable")
        self.head_sorted, size = self.head[order], self.len[order]
        self.active = [int(np.searchsorted(-size, -k)) for k in range(int(size[0]) if n else 0)]  # chains longer than k


class Field:
    """A two-state conditional random field: weights of state 1 by feature, and 2 x 2 transitions."""

    def __init__(self) -> None:
        self.w, self.bias = np.zeros(1 << BITS), -2.0
        self.edge = np.zeros((2, 2))
        self.doc = np.zeros(4)

    def passes(self, k: Tokens) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Potentials of state 1, and the forward and backward shares of state 1, of each token."""
        z = np.full(len(k.start), self.bias)
        for f in k.features:
            z += self.w[f]
        e = np.exp(np.clip(z, -25, 25))
        a = np.exp(self.edge)
        f, b = np.empty_like(e), np.empty_like(e)
        for step, m in enumerate(k.active):
            i = k.head_sorted[:m] + step
            if step:
                p = f[i - 1]
                u0, u1 = (1 - p) * a[0, 0] + p * a[1, 0], ((1 - p) * a[0, 1] + p * a[1, 1]) * e[i]
                f[i] = u1 / (u0 + u1)
            else:
                f[i] = e[i] / (1 + e[i])
        b[k.head + k.len - 1] = 0.5
        for step in range(len(k.active) - 2, -1, -1):
            i = k.head_sorted[: k.active[step + 1]] + step
            p, x = b[i + 1], e[i + 1]
            u0, u1 = a[0, 0] * (1 - p) + a[0, 1] * x * p, a[1, 0] * (1 - p) + a[1, 1] * x * p
            b[i] = u1 / (u0 + u1)
        return e, f, b

    def marginals(self, k: Tokens) -> np.ndarray:
        _, f, b = self.passes(k)
        return f * b / (f * b + (1 - f) * (1 - b))

    def fit(self, parts: list[tuple[Tokens, np.ndarray]], steps: int = 30, rate: float = 0.3) -> None:
        total = sum(len(y) for _, y in parts) or 1
        m, v = np.zeros((1 << BITS) + 5), np.zeros((1 << BITS) + 5)
        for step in range(1, steps + 1):
            g = np.zeros((1 << BITS) + 5)
            for k, y in parts:
                e, f, b = self.passes(k)
                d = f * b / (f * b + (1 - f) * (1 - b)) - y
                for x in k.features:
                    g[: 1 << BITS] += np.bincount(x, d, 1 << BITS)
                g[1 << BITS] += d.sum()
                i = np.ones(len(y), bool)
                i[k.head] = False
                i = np.flatnonzero(i)
                a = np.exp(self.edge)
                xi = np.stack([fi * a[p, q] * xq * bq for p, fi in enumerate((1 - f[i - 1], f[i - 1])) for q, (xq, bq) in enumerate(((1.0, 1 - b[i]), (e[i], b[i])))])
                xi /= xi.sum(0)
                seen = np.bincount((2 * y[i - 1] + y[i]).astype(np.int64), minlength=4)
                g[(1 << BITS) + 1 :] += xi.sum(1) - seen
            g /= total / 1000
            g[: 1 << BITS] += 1e-3 * self.w
            m += 0.1 * (g - m)
            v += 0.01 * (g * g - v)
            move = rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-3)
            self.w -= move[: 1 << BITS]
            self.bias -= move[1 << BITS]
            self.edge -= move[(1 << BITS) + 1 :].reshape(2, 2)

    @staticmethod
    def summary(p: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Columns 1, log(1 + sum), largest marginal, and log(1 + SHARES * share) of the marginals, for each text."""
        total = per_text(p, at, empty=0.0)
        return np.stack([np.ones(len(at) - 1), np.log1p(total), per_text(p, at, np.maximum, 0.0), np.log1p(SHARES * total / np.maximum(np.diff(at), 1))], 1)

    def score(self, k: Tokens, p: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.summary(p, k.at) @ self.doc, -30, 30)))

    def calibrate(self, x: np.ndarray, y: np.ndarray, weight: np.ndarray) -> None:
        for _ in range(25):  # Newton steps
            p = 1 / (1 + np.exp(-np.clip(x @ self.doc, -30, 30)))
            h = (x * (weight * p * (1 - p))[:, None]).T @ x + 1e-2 * np.eye(4) * weight.mean()
            self.doc -= np.linalg.solve(h, x.T @ (weight * (p - y)) + 1e-2 * self.doc * weight.mean())


def _token_labels(parts: list[Tokens], toxic: np.ndarray) -> list[np.ndarray]:
    """1 for the tokens of toxic documents that have a telling feature."""
    kinds = len(parts[0].own)
    telling = []
    n1, n0 = max(1, int(toxic.sum())), max(1, int((~toxic).sum()))
    for kind in range(kinds):
        docs, near, base = [], [], 0
        for k in parts:
            doc = np.repeat(np.arange(len(k.at) - 1), np.diff(k.at)) + base
            docs.append(np.unique(np.stack([k.own[kind], doc.astype(np.uint64)]), axis=1))
            bad = toxic[doc]
            near.append(np.stack([k.own[kind][bad], k.before[bad], k.after[bad]]))
            base += len(k.at) - 1
        f, d = np.concatenate(docs, axis=1)
        value, where = np.unique(f, return_inverse=True)
        bad = toxic[d.astype(np.int64)]
        pos, neg = np.bincount(where, bad), np.bincount(where, ~bad)
        near = np.concatenate(near, axis=1)
        for side in (1, 2):  # copies of a text repeat a word's neighbours; they count once
            own = np.unique(near[[0, side]], axis=1)[0]
            pos = np.minimum(pos, np.bincount(np.searchsorted(value, own), minlength=len(value)))
        odds = (pos / n1) / (pos / n1 + (neg + 0.1) / n0)
        telling.append(value[(pos >= max(LEAST_DOCS, LEAST_SHARE * n1)) & (odds >= PRECISION)])
    out, base = [], 0
    for k in parts:
        doc = np.repeat(np.arange(len(k.at) - 1), np.diff(k.at)) + base
        hit = np.zeros(len(doc), bool)
        for kind in range(kinds):
            hit |= np.isin(k.own[kind], telling[kind])
        out.append((hit & toxic[doc]).astype(np.float64))
        base += len(k.at) - 1
    return out


def fit_texts(texts: list[str], toxic: np.ndarray) -> Field | None:
    if len(set(toxic.tolist())) < 2:
        return None
    field = Field()
    rows = np.arange(len(texts))
    apart = rows[rows % APART == APART - 1]
    learnt = np.setdiff1d(rows, apart)
    if np.bincount(toxic[apart], minlength=2).min() < LEAST_APART:
        learnt = apart = rows
    of = lambda rows: [Tokens(t) for t in texts_of(pa.array([texts[i] for i in rows], pa.large_string()))]
    parts = of(learnt)
    parts_y = _token_labels(parts, toxic[learnt].astype(bool))
    field.fit([(k, y) for k, y in zip(parts, parts_y) if len(y)])
    x = np.concatenate([field.summary(field.marginals(k), k.at) for k in (parts if apart is learnt else of(apart))])
    y = toxic[apart]
    weight = np.where(y == 1, 0.5 / max(1, y.sum()), 0.5 / max(1, (1 - y).sum())) * len(y)
    field.calibrate(x, y.astype(np.float64), weight)
    return field


def fit(docs: DataFrame, labels: DataFrame) -> Field | None:
    """The field learnt from labelled rows outside the held-out fold."""
    _, texts, y = labelled_sample(docs, labels.filter(remainder(F.col("doc_id"), FOLDS) != 0), "toxic", PER_VALUE)
    return fit_texts(texts, y)


def tag(docs: DataFrame, field: Field | None, text: str = "text") -> DataFrame:
    """docs with ``score`` and ``spans`` (offending "start:end" in code points, joined by commas)."""
    shared = docs.sparkSession.sparkContext.broadcast(field)  # 2**18 weights
    names = [f"c{i}" for i in range(len(docs.columns))]
    at = docs.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        field = shared.value
        for batch in batches:
            for t in texts_of(batch.column(at)):
                score, spans = np.zeros(len(t)), [""] * len(t)
                if field is not None:
                    k = Tokens(t)
                    p = field.marginals(k)
                    score, spans = field.score(k, p), _spans(t, k, p)
                yield pa.RecordBatch.from_arrays([*batch.slice(t.row, len(t)).columns, pa.array(score), pa.array(spans, pa.string())], names=[*names, "score", "spans"])

    plain = docs.toDF(*names)
    return plain.mapInArrow(run, widened(plain, score="double", spans="string")).toDF(*docs.columns, "score", "spans")


def _spans(t: Texts, k: Tokens, p: np.ndarray) -> list[str]:
    out = [""] * len(t)
    bad = np.flatnonzero(p >= 0.5)
    if not len(bad):
        return out
    text = np.searchsorted(k.at, bad, "right") - 1
    first = np.ones(len(bad), bool)
    first[1:] = (np.diff(bad) != 1) | (np.diff(text) != 0)
    last = np.append(first[1:], True)
    chars = t.code_points()
    own = text[first]
    lo, hi = chars[k.start[bad[first]]] - chars[t.cuts[own]], chars[k.stop[bad[last]]] - chars[t.cuts[own]]
    for i, a, b in zip(own.tolist(), lo.tolist(), hi.tolist()):
        out[i] += f",{a}:{b}" if out[i] else f"{a}:{b}"
    return out


def score_documents(docs: DataFrame, labels: DataFrame) -> DataFrame:
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    out = tag(rows, fit(rows, labels))
    return out.select("doc_id", (remainder(F.col("doc_id"), FOLDS) == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), "spans")


def reject(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """docs without those scored 0.5 or more; all columns stay."""
    names = [f"x{i}" for i in range(len(docs.columns))]  # so that no column is taken for a score
    tagged = tag(docs.toDF(*names), fit(docs.select("doc_id", "text"), labels), names[docs.columns.index("text")])
    return tagged.filter("score < 0.5").select(*names).toDF(*docs.columns)
