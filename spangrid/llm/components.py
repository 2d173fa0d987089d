"""Connected components of an edge table, by alternating large-star and small-star steps.

Edge tables of at most FEW rows are solved by one task instead, as their size is checked and a step costs more.

Each step replaces edges by edges to the smallest neighbour, found by an aggregate that combines map-side; the
join that follows reads that aggregate from a written table, so both sides are plain exchanges and a node
with very many neighbours is split by the skew join. Steps end when the edges no longer change.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .tables import written


#: Edges that one task takes, at most: 4 MB.
FEW = 1 << 18


def least_labels(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The least node of each of n nodes' component in the graph of the edges (a, b)."""
    label = np.arange(n)
    while True:
        low = np.minimum(label[a], label[b])
        new = label.copy()
        np.minimum.at(new, label[a], low)
        np.minimum.at(new, label[b], low)
        new = new[new]
        if (new == label).all():
            return label
        label = new


def _at_once(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    got = [(np.asarray(x.column("u")), np.asarray(x.column("v"))) for x in batches]
    ends = [np.concatenate([x[i] for x in got]) if got else np.zeros(0, np.int64) for i in (0, 1)]
    ids, at = np.unique(np.concatenate(ends), return_inverse=True)
    label = least_labels(len(ids), at[: len(ends[0])], at[len(ends[0]) :])
    yield pa.RecordBatch.from_arrays([pa.array(ids.astype(np.int64)), pa.array(ids[label].astype(np.int64))], names=["node", "component"])


def _step(edges: DataFrame, large: bool) -> DataFrame:
    """edges (u, v) with u > v, replaced by edges to the least neighbours."""
    if large:
        both = edges.select("u", "v").unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = written(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m")), "least")
        out = both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        least = written(edges.groupBy("u").agg(F.min("v").alias("m")), "least")
        near = edges.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v")
        out = near.unionByName(least.select("u", F.col("m").alias("v")))
    return written(out.distinct(), "edges")


def components(edges: DataFrame) -> DataFrame:
    """(node, component) for the nodes of the edges in columns a and b; the component is its smallest node."""
    cur = written(edges.filter("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges")
    if cur.count() <= FEW:
        return written(cur.repartition(1).mapInArrow(_at_once, "node long, component long"), "components")
    state = None
    while True:
        cur = _step(_step(cur, True), False)
        now = cur.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == state:
            break
        state = now
    roots = cur.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    return written(cur.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots), "components")
