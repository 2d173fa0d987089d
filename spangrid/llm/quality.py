"""Quality rules: measured properties of whole texts, and a hashed n-gram logistic regression.

Properties come from one pass of array operations over a slice of texts. Words are maximal runs of other bytes
than white space; equal words are found by 64-bit fingerprints. The model learns from a bounded sample of the
labelled rows (PER_VALUE of each label), is calibrated on a fifth of them, and keeps a document at
probability 0.5 or more.

Results by case: a null or empty text has no words, so it fails the base rules; without labelled rows of both
values every document passing the base rules is kept; repeated rows give one row each.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .flat import BYTE_CODE, Texts, mix, per_text, prefix_hash, span_hash, texts_of
from .hashed import Softmax, labelled_sample

PER_VALUE = 700
#: Symbols that count, words in a window, least words, and most repeated words in a hundred.
SYMBOLS = b"#*$%&|<>"
WINDOW, LEAST_WORDS, MOST_REPEATED = 5, 10, 20
KEEP = 0.5
_IS_SYMBOL = np.isin(np.arange(256), np.frombuffer(SYMBOLS, np.uint8))
_U = np.uint64


def properties(t: Texts) -> dict[str, np.ndarray]:
    """n_words, word_chars, n_symbols, n_dup_lines and n_repeat_words of each text."""
    s, e, at = t.words()
    prefix = prefix_hash(BYTE_CODE[t.data])
    chars = t.code_points()
    out = {"n_words": np.diff(at), "word_chars": per_text(chars[e] - chars[s], at)}
    symbols = np.concatenate([[0], np.cumsum(_IS_SYMBOL[t.data])])
    out["n_symbols"] = np.diff(symbols[t.cuts])
    out["n_dup_lines"] = _equal_lines(t, prefix, s)
    word = span_hash(prefix, s, e)
    n = len(word) - WINDOW + 1
    covered = np.zeros(len(word) + 1, np.int64)
    if n > 0:
        g = word[:n].copy()
        for i in range(1, WINDOW):
            g = mix(g * _U(0x9E3779B97F4A7C15) + word[i : i + n])
        text = np.repeat(np.arange(len(t)), np.diff(at))
        within = np.flatnonzero(text[:n] == text[WINDOW - 1 :])
        key = mix(g[within] + text[within].astype(np.uint64) * _U(0xC2B2AE3D27D4EB4F))
        order = np.argsort(key, kind="stable")
        same = key[order][1:] == key[order][:-1]
        twice = np.zeros(len(key), bool)
        twice[order[1:][same]] = True
        twice[order[:-1][same]] = True
        hit = within[twice]
        covered = np.bincount(hit, minlength=len(covered)) - np.bincount(hit + WINDOW, minlength=len(covered))
    out["n_repeat_words"] = per_text((np.cumsum(covered)[:-1] > 0).astype(np.int64), at)
    return out


def _equal_lines(t: Texts, prefix: np.ndarray, word_starts: np.ndarray) -> np.ndarray:
    """Lines with a word that equal an earlier line of their text."""
    feed = np.flatnonzero(t.data == 10)
    lo = np.unique(np.concatenate([t.cuts[:-1], feed + 1]))
    lo = lo[lo < len(t.data)]
    if not len(lo):
        return np.zeros(len(t), np.int64)
    hi = np.append(lo[1:], len(t.data))
    hi = hi - (t.data[hi - 1] == 10)  # without the line feed; a text's last line has none
    ends = np.searchsorted(t.cuts, lo, "right") - 1
    # a text that ends in a line feed is followed by an empty line, which has no word
    hi = np.maximum(hi, lo)
    wordy = np.searchsorted(word_starts, hi) > np.searchsorted(word_starts, lo)
    lo, hi, text = lo[wordy], hi[wordy], ends[wordy]
    key = mix(span_hash(prefix, lo, hi) + text.astype(np.uint64) * _U(0xC2B2AE3D27D4EB4F))
    order = np.argsort(key, kind="stable")
    later = np.zeros(len(key), bool)
    later[order[1:][key[order][1:] == key[order][:-1]]] = True
    return np.bincount(text[later], minlength=len(t))


def fit(docs: DataFrame, labels: DataFrame) -> Softmax | None:
    _, texts, y = labelled_sample(docs, labels, "quality", PER_VALUE)
    return Softmax([0, 1]).fit(texts, y) if len(set(y.tolist())) == 2 else None


def judge(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Per document its properties, whether the base rules fail it, the model's probability, and the verdict."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    shared = docs.sparkSession.sparkContext.broadcast(fit(rows, labels))  # 2**17 weights a block and class

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = shared.value
        for batch in batches:
            for t in texts_of(batch.column("text")):
                p = properties(t)
                failed = (p["n_words"] < LEAST_WORDS) | (100 * p["n_repeat_words"] > MOST_REPEATED * p["n_words"])
                good = model.predict(t)[:, 1] if model else np.ones(len(t))
                yield pa.RecordBatch.from_arrays(
                    [batch.column("doc_id").slice(t.row, len(t)), *(pa.array(x.astype(np.int64)) for x in p.values()), pa.array(failed), pa.array(~failed & (good >= KEEP)), pa.array(good)],
                    names=["doc_id", *p, "base_failed", "kept", "quality"],
                )

    counts = ", ".join(f"{c} long" for c in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"))
    return rows.mapInArrow(run, f"doc_id long, {counts}, base_failed boolean, kept boolean, quality double")
