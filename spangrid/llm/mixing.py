"""Soft-membership mixing of documents to target weights of domains.

A hashed n-gram classifier, learnt from at most PER_DOMAIN labelled documents of each domain (those that the label table names
and whose domain the targets name; all other domains are one more class, OTHER, if there are any), gives each whole text posterior
probabilities p of the domains. With t the text's words, rates r >= 0 solve the least squares problem

    minimise  1/2 |sum_i r_i t_i p_i / T - target|^2  +  ridge/2 sum_i (t_i / T) (r_i - 1)^2

by projected gradients with momentum: one distributed sum of a vector of domains per step gives the gradient of every
row, and rows recompute their own rates from the short list of those vectors since the last written state. The
expected domain totals of the weighted documents then match the targets as far as the documents allow, and rates stay
near 1 where nothing forces them away. The ridge shrinks with the smallest domain's share of the words, so that it moves no
domain's total by more than RIDGE of it. A fit that has not come as near as CLOSE after STEPS steps, or nearer within PATIENCE
steps (as where the documents allow no more), warns, with the gap left.

Results by case: null and empty texts have no words; they get the rate their posterior gives and weigh nothing; a target domain that
no labelled document has is left out and the others are scaled to one; without labelled documents of two classes all rates are 1.
Equal rows share a rate and a number of copies; rows that share an id only have their own.
"""

from __future__ import annotations

import warnings
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .flat import texts_of
from .hashed import Softmax
from .tables import forget, written

#: Labelled documents of each domain that the classifier learns from, at most.
PER_DOMAIN, SPARE = 250, 3
OTHER = "other"
RIDGE, STEPS, PATIENCE, STATE_EVERY, CLOSE = 1e-2, 200, 20, 10, 1e-3


def learn(docs: DataFrame, labels: DataFrame, domains: list[str]) -> Softmax | None:
    """The classifier of rows (doc_id, text, domain) into the domains and OTHER, from labelled rows, those first in a hash's order."""
    known = labels.filter("doc_id is not null").select(F.col("doc_id").cast("long").alias("_d")).distinct()
    own = F.when(F.col("domain").isin(domains), F.col("domain")).otherwise(OTHER)
    # ids only, so that what moves is short
    rows = docs.filter("domain is not null").select(F.col("doc_id").alias("_d"), own.alias("_y")).join(known, "_d", "left_semi")
    rows = written(rows.groupBy("_d").agg(F.min("_y").alias("_y")), "domains")
    # of a class of n rows, hashes up to SPARE * PER_DOMAIN / n hold its first PER_DOMAIN (fewer with a probability under 1e-90), however large n
    n = {r["_y"]: r["count"] for r in rows.groupBy("_y").count().collect()}  # one a class
    if not n:
        return None
    least = F.create_map(*(F.lit(x) for c, many in n.items() for x in (c, SPARE * PER_DOMAIN / many)))[F.col("_y")]
    first = F.row_number().over(Window.partitionBy("_y").orderBy(F.xxhash64("_d"), "_d"))
    some = rows.filter(F.xxhash64("_d") / F.lit(2.0**64) + 0.5 <= least).withColumn("_r", first).filter(F.col("_r") <= PER_DOMAIN)
    texts = docs.withColumn("_o", own).join(F.broadcast(some), (F.col("doc_id") == F.col("_d")) & (F.col("_o") == F.col("_y")))
    texts = texts.select("doc_id", F.coalesce("text", F.lit("")).alias("text"), "_y").toPandas().sort_values(["doc_id", "text"]).drop_duplicates("doc_id")
    forget(rows)
    classes = [c for c in dict.fromkeys([*domains, OTHER]) if (texts["_y"] == c).any()]
    if len(classes) < 2:
        return None
    return Softmax(classes).fit(texts["text"].tolist(), texts["_y"].map(classes.index).to_numpy(np.int64), steps=40)


def posteriors(docs: DataFrame, model: Softmax) -> DataFrame:
    """docs (doc_id, k, text) -> doc_id, k, n_tokens and the posteriors p of the model's classes."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # 2**17 weights a block and class

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = shared.value
        for batch in batches:
            for t in texts_of(batch.column("text")):
                p = own.predict(t)
                lists = pa.FixedSizeListArray.from_arrays(pa.array(p.reshape(-1)), p.shape[1]).cast(pa.list_(pa.float64()))
                ids = [batch.column(c).slice(t.row, len(t)) for c in ("doc_id", "k")]
                yield pa.RecordBatch.from_arrays([*ids, pa.array(np.diff(t.words()[2]).astype(np.int64)), lists], names=["doc_id", "k", "n_tokens", "p"])

    return docs.select("doc_id", "k", "text").mapInArrow(run, "doc_id long, k long, n_tokens long, p array<double>")


def _advance(p: np.ndarray, r: np.ndarray, before: np.ndarray, moves: list[tuple[np.ndarray, float, float]], ridge: float) -> tuple[np.ndarray, np.ndarray]:
    """Rates, and those of the step before, after the moves (gradient vector, step size, momentum)."""
    for g, size, momentum in moves:
        y = r + momentum * (r - before)
        r, before = np.maximum(0.0, y - size * (p @ g + ridge * (y - 1))), r
    return r, before


def _matrix(column: pa.Array, d: int) -> np.ndarray:
    return np.asarray(column.flatten(), np.float64).reshape(-1, d)


def _moved(state: DataFrame, moves: list, d: int, ridge: float) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            r, before = _advance(_matrix(b.column("p"), d), np.asarray(b.column("r")), np.asarray(b.column("before")), moves, ridge)
            yield pa.RecordBatch.from_arrays([*(b.column(c) for c in ("doc_id", "k", "n_tokens", "p")), pa.array(r), pa.array(before)], names=b.schema.names)

    return state.mapInArrow(run, "doc_id long, k long, n_tokens long, p array<double>, r double, before double")


def _totals(state: DataFrame, moves: list, momentum: float, d: int, ridge: float) -> np.ndarray:
    """sum of y_i t_i p_i, where y are the rates after the moves, carried on by the momentum."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(d)
        for b in batches:
            p = _matrix(b.column("p"), d)
            r, before = _advance(p, np.asarray(b.column("r")), np.asarray(b.column("before")), moves, ridge)
            total += ((r + momentum * (r - before)) * np.asarray(b.column("n_tokens"))) @ p
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(d)), pa.array(total)], names=["k", "v"])

    out = np.zeros(d)
    for row in state.mapInArrow(run, "k long, v double").groupBy("k").agg(F.sum("v").alias("v")).collect():  # one a domain
        out[row["k"]] = row["v"]
    return out


def rates(docs: DataFrame, labels: DataFrame, targets: dict[str, float], domain: str = "lang") -> tuple[DataFrame, list[str]]:
    """(doc_id, k, n_tokens, p, rate) of all documents, and the names of the domains that p is about; k is equal for rows of
    equal id and text."""
    text = F.col("text").cast("string")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"), F.col(domain).cast("string").alias("domain")).withColumn("k", _row_key())
    model = learn(rows, labels, sorted(targets))
    if model is None:
        words = F.size(F.regexp_extract_all(F.coalesce("text", F.lit("")), F.lit(r"[^\x20\x09-\x0D]+"), F.lit(0))).cast("long")
        return rows.select("doc_id", "k", words.alias("n_tokens"), F.array(F.lit(1.0)).alias("p"), F.lit(1.0).alias("rate")), ["all"]
    d = len(model.classes)
    goal = np.array([max(0.0, targets.get(c, 0.0)) for c in model.classes])
    goal = goal / goal.sum() if goal.sum() else np.full(d, 1 / d)
    state = written(posteriors(rows, model).withColumn("r", F.lit(1.0)).withColumn("before", F.lit(1.0)), "mixing")
    words = float(state.agg(F.sum("n_tokens")).first()[0] or 0)
    share = _totals(state, [], 0.0, d, 0.0) / words if words else goal
    wanted = share[(goal > 0) & (share > 0)]
    ridge = RIDGE * float(wanted.min()) if len(wanted) else RIDGE
    moves: list = []
    old = []
    left, best, since = np.inf, np.inf, 0
    for step in range(STEPS):
        momentum = step / (step + 3)
        gap = ((_totals(state, moves, momentum, d, ridge) if step else share * words) / words if words else goal) - goal
        left = np.abs(gap).max()
        best, since = (left, step) if left < 0.99 * best else (best, since)
        if left < CLOSE or step - since >= PATIENCE:
            break
        moves = [*moves, (gap, 1 / (1 + ridge), momentum)]
        if len(moves) == STATE_EVERY:
            old.append(state)
            state, moves = written(_moved(state, moves, d, ridge), "mixing"), []
            forget(*old)
            old = []
    if left >= CLOSE:
        warnings.warn(f"mixing: after {step + 1} steps a domain's share is still {left:.4f} from its target", stacklevel=2)
    return _moved(state, moves, d, ridge).select("doc_id", "k", "n_tokens", "p", F.col("r").alias("rate")), model.classes


def _row_key() -> Column:
    return F.xxhash64(F.col("doc_id"), F.coalesce("text", F.lit("")), F.col("text").isNull())


def copies(rate: Column, key: Column, seed: int = 5) -> Column:
    """Whole copies of a document whose expected number is its rate."""
    u = (F.xxhash64(F.lit(seed), key) / F.lit(2.0**63) + 1) / 2
    return F.floor(rate + u * (1 - 1e-12)).cast("int")


def mix_documents(docs: DataFrame, labels: DataFrame, targets: dict[str, float], domain: str = "lang") -> DataFrame:
    """Per document its words, domain posteriors, rate and number of copies."""
    out, names = rates(docs, labels, targets, domain)
    return out.select("doc_id", "n_tokens", *[F.element_at("p", k + 1).alias(f"p_{c}") for k, c in enumerate(names)], "rate", copies(F.col("rate"), F.col("k")).alias("copies"))


def resample(docs: DataFrame, labels: DataFrame, targets: dict[str, float], domain: str = "lang") -> DataFrame:
    """docs, every column kept, each row as many times as its rate asks for."""
    out, _ = rates(docs, labels, targets, domain)
    number = written(out.groupBy("k").agg(F.max("rate").alias("rate")).select("k", copies(F.col("rate"), F.col("k")).alias("n")), "copies")
    names = [f"x{i}" for i in range(len(docs.columns))]  # so that no column is taken for another
    doc_id, text = (F.col(names[docs.columns.index(c)]) for c in ("doc_id", "text"))
    keyed = docs.toDF(*names).select("*", F.struct(doc_id.cast("long").alias("doc_id"), text.cast("string").alias("text")).alias("own"))
    key = F.xxhash64(F.col("own.doc_id"), F.coalesce("own.text", F.lit("")), F.col("own.text").isNull())
    every = F.explode(F.sequence(F.lit(1), F.col("n")))
    out = keyed.withColumn("key", key).join(number.withColumnRenamed("k", "key"), "key").filter("n > 0").withColumn("copy", every)
    return out.select(*names).toDF(*docs.columns)
