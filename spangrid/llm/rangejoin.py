"""Near-duplicate vectors by an exact metric range join on pivots.

Unit vectors at cosine c lie sqrt(2 - 2c) apart, so a cosine threshold is a distance threshold. Equal vectors collapse
first and are counted. Every vector goes home to its nearest pivot; by the triangle inequality a vector x of
home i can have a partner at home in cell j only if (d(x,j)^2 - d(x,i)^2) / (2 d(i,j)) is within the threshold, and
only then is it sent to j as a probe. Of two cells one sends to the other, so that two vectors meet once; in its own cell
a vector is a probe too. Cells are cut into slices of home vectors by slices of probes, each pair of slices
being one group of bounded size; a group returns counts of links and a spanning forest, never its pairs. Slices of homes are
joined in rounds, whose copies of vectors are let go before the next, so disk follows the vectors, not the copies.

In data without structure few cells can be ruled out and the work is quadratic, as for any exact join; the
number of pivots (a sample that grows with the vectors until their distances fill what is shared with all tasks) changes only
the cost.

Results by case: vectors that are null, empty, zero or hold null or non-finite components, and those without an id link
with nothing and are kept; vectors link with those of their own length only, each length being a join of its own; repeated
rows are linked.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .components import components, least_labels
from .tables import forget, release, written

#: Vectors at home in a cell on average, most pivots (whose distances then take 128 MB), and the sizes of slices of vectors of up to
#: LENGTH components (those of longer ones are smaller).
CELL, MOST_PIVOTS, HOMES, PROBES, LENGTH = 8192, 4096, 16384, 32768, 64
BLOCK = 256
#: Copies of all vectors that one round moves, and bytes that it may move in any case.
COPIES, LEAST_BYTES = 2, 64 << 20
#: Rounding of distances that boundary replication allows for.
SLACK = 1e-6


def _unit(raw: list[bytes], kind: type = np.float64) -> np.ndarray:
    """Unit vectors, in double precision, from the bytes of single-precision or double-precision ones."""
    x = np.frombuffer(b"".join(raw), kind).reshape(len(raw), -1).astype(np.float64)
    x = x / np.abs(x).max(1, keepdims=True)
    return x / np.sqrt((x * x).sum(1, keepdims=True))


def _packed(vectors: DataFrame, kind: type) -> DataFrame:
    """(rep, w, vector as an array) -> the vector's bytes in ``v``, in the precision it came in."""
    wide = np.dtype(kind).itemsize

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            lists = b.column("e")
            flat, offs = np.asarray(lists.flatten(), kind), np.asarray(lists.offsets)
            raw, offs = flat.tobytes(), (offs - offs[0]) * wide if len(offs) else offs
            yield pa.RecordBatch.from_arrays([b.column("rep"), b.column("w"), pa.array([raw[i:j] for i, j in zip(offs[:-1].tolist(), offs[1:].tolist())], pa.binary())], names=["rep", "w", "v"])

    return vectors.select("rep", "w", "e").mapInArrow(run, "rep long, w long, v binary")


def _dealt(vectors: DataFrame, pivots: np.ndarray, eps: float, kind: type) -> DataFrame:
    """Vectors with their home and a bit for every cell that they are sent to."""
    apart = np.sqrt(np.maximum(0, 2 - 2 * pivots @ pivots.T))
    shared = vectors.sparkSession.sparkContext.broadcast((pivots, apart))  # at most MOST_PIVOTS vectors

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p, between = shared.value
        cell = np.arange(len(p))
        for whole in batches:
            for i in range(0, whole.num_rows, 2048):
                batch = whole.slice(i, 2048)
                sq = np.maximum(0, 2 - 2 * _unit(batch.column("v").to_pylist(), kind) @ p.T)
                home = sq.argmin(1)
                own = np.arange(len(home))
                gap = sq - sq[own, home][:, None]
                meets = gap <= 2 * between[home] * (eps + SLACK) + SLACK
                meets &= ((home[:, None] + cell) % 2 == 0) == (home[:, None] < cell)  # the one of two cells that sends
                meets[own, home] = True
                bits = np.packbits(meets, axis=1)
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(home.astype(np.int32)), pa.array([r.tobytes() for r in bits], pa.binary())], names=[*batch.schema.names, "home", "meets"])

    return vectors.mapInArrow(run, "rep long, w long, v binary, home int, meets binary")


def _bits(meets: pa.Array, count: int) -> np.ndarray:
    return np.unpackbits(np.frombuffer(b"".join(meets.to_pylist()), np.uint8).reshape(len(meets), -1), axis=1, count=count)


def _sizes(dealt: DataFrame, count: int) -> tuple[np.ndarray, np.ndarray]:
    """Vectors at home in each cell, and those sent to it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        homes, probes = np.zeros(count, np.int64), np.zeros(count, np.int64)
        for b in batches:
            homes += np.bincount(np.asarray(b.column("home")), minlength=count)
            if b.num_rows:
                probes += _bits(b.column("meets"), count).sum(0, dtype=np.int64)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(count)), pa.array(homes), pa.array(probes)], names=["cell", "h", "p"])

    sums = dealt.select("home", "meets").mapInArrow(run, "cell long, h long, p long").groupBy("cell").agg(F.sum("h").alias("h"), F.sum("p").alias("p"))
    homes, probes = np.zeros(count, np.int64), np.zeros(count, np.int64)
    for r in sums.collect():  # one a pivot
        homes[r["cell"]], probes[r["cell"]] = r["h"], r["p"]
    return homes, probes


def _rounds(homes: np.ndarray, probes: np.ndarray, s: np.ndarray, q: np.ndarray, most: float) -> list[list[tuple[int, int]]]:
    """Slices of homes (cell, slice) dealt into rounds that move about ``most`` vectors each, or one slice's."""
    out, held = [[]], 0.0
    for c in range(len(homes)):
        for i in range(int(s[c])):
            cost = homes[c] / s[c] * q[c] + probes[c]
            if out[-1] and held + cost > most:
                out.append([])
                held = 0.0
            out[-1].append((c, i))
            held += cost
    return [r for r in out if r]


def _sent(dealt: DataFrame, part: list[tuple[int, int]], s: np.ndarray, q: np.ndarray) -> DataFrame:
    """The rows of a round's groups (cell, s, q): vectors at home (side 0), once for each slice of probes, and probes (side 1), once
    for each of the round's slices of homes."""
    count = len(s)
    first = np.concatenate([[0], np.cumsum(s)])
    asked = np.zeros(first[-1], bool)
    asked[[first[c] + i for c, i in part]] = True
    shared = dealt.sparkSession.sparkContext.broadcast((s, q, first, asked, part))  # one number a slice

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        s, q, first, asked, part = shared.value
        for b in batches:
            if not b.num_rows:
                continue
            at = (np.asarray(b.column("rep")).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(33)).astype(np.int64)
            home = np.asarray(b.column("home")).astype(np.int64)
            own = np.flatnonzero(asked[first[home] + at % s[home]])
            times = q[home[own]]
            upto = np.cumsum(times)
            bits = _bits(b.column("meets"), count)
            parts = [(np.repeat(own, times), np.repeat(home[own], times), np.repeat((at % s[home])[own], times), np.arange(times.sum()) - np.repeat(upto - times, times), 0)]
            for c, i in part:
                got = np.flatnonzero(bits[:, c])
                parts.append((got, np.full(len(got), c), np.full(len(got), i), at[got] % q[c], 1))
            for row, cell, si, qi, side in parts:
                for k in range(0, len(row), 8192):
                    z = slice(k, k + 8192)
                    ints = [pa.array(x[z].astype(np.int32)) for x in (cell, si, qi)]
                    yield pa.RecordBatch.from_arrays([*(b.column(c).take(pa.array(row[z])) for c in ("rep", "w", "v", "home")), *ints, pa.array(np.full(len(ints[0]), side, np.int32))], names=["rep", "w", "v", "home", "cell", "s", "q", "side"])

    return dealt.mapInArrow(run, "rep long, w long, v binary, home int, cell int, s int, q int, side int")


def _meet(least: float, kind: type):
    def run(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        home, probe = pdf[pdf["side"] == 0], pdf[pdf["side"] == 1]
        empty = pd.DataFrame({"a": np.zeros(0, np.int64), "b": np.zeros(0, np.int64), "n": np.zeros(0, np.int64)})
        if not len(home) or not len(probe):
            return empty
        h, weight, hid, qid = _unit(home["v"].tolist(), kind), home["w"].to_numpy(), home["rep"].to_numpy(), probe["rep"].to_numpy()
        ids, node = np.unique(np.concatenate([hid, qid]), return_inverse=True)
        hn, qn, qw = node[: len(hid)], node[len(hid) :], probe["w"].to_numpy()
        label, links = np.arange(len(ids)), np.zeros(len(ids), np.int64)
        inside = probe["home"].to_numpy() == key[0]  # of two vectors of one cell either is a probe and counts its own links
        rough, slack = h.astype(np.float32).T, (h.shape[1] + 8) * 2.0**-22
        raw = probe["v"].tolist()
        for i in range(0, len(raw), BLOCK):
            x = _unit(raw[i : i + BLOCK], kind)
            q, k = np.nonzero(x.astype(np.float32) @ rough >= least - slack)
            if not len(q):
                continue
            if len(q) > 16 * BLOCK:
                q, k = np.nonzero(x @ h.T >= least)
            else:
                sure = np.einsum("ij,ij->i", x[q], h[k]) >= least
                q, k = q[sure], k[sure]
            apart = qid[i + q] != hid[k]
            q, k = q[apart] + i, k[apart]
            if len(q):
                np.add.at(links, qn[q], weight[k])
                out = ~inside[q]
                np.add.at(links, hn[k[out]], qw[q[out]])
                pair = np.unique(label[qn[q]] * len(ids) + label[hn[k]])
                label = least_labels(len(ids), pair // len(ids), pair % len(ids))[label]
        some = np.flatnonzero(links)
        tied = np.flatnonzero(label != np.arange(len(ids)))
        return pd.DataFrame({"a": np.concatenate([ids[some], ids[tied]]), "b": np.concatenate([np.full(len(some), -1), ids[label[tied]]]), "n": np.concatenate([links[some], np.zeros(len(tied), np.int64)])})

    return run


def _met(groups: DataFrame, length: int, k: int, least: float, kind: type) -> list[DataFrame]:
    """(a, b, n) of the k different vectors of a length: n links of a where n > 0, else an edge of a forest; a table each round."""
    spark = groups.sparkSession
    packed = written(_packed(groups.filter(F.size("e") == length), kind), "packed")
    count = min(MOST_PIVOTS, max(1, round(k / CELL)))
    pivots = _unit([bytes(r["v"]) for r in packed.orderBy(F.xxhash64("rep"), "rep").limit(count).collect()], kind)
    dealt = written(_dealt(packed, pivots, math.sqrt(2 - 2 * least), kind), "cells")
    forget(packed)
    homes, probes = _sizes(dealt, count)
    fit = lambda rows: max(1, min(rows, rows * LENGTH // length))
    s, q = np.maximum(1, -(-homes // fit(HOMES))), np.maximum(1, -(-probes // fit(min(PROBES, max(2048, k // 8)))))  # some groups for every core
    most = max(COPIES * k, LEAST_BYTES / (length * np.dtype(kind).itemsize + 64))
    out = []
    for part in _rounds(homes, probes, s, q, most):
        out.append(written(_sent(dealt, part, s, q).groupBy("cell", "s", "q").applyInPandas(_meet(least, kind), "a long, b long, n long"), "met"))
        release(spark)
    forget(dealt)
    return out


def near_vectors(vectors: DataFrame, least: float = 0.95) -> DataFrame:
    """vec_id, n_links, component_id and kept of every row of vectors (vec_id, embedding)."""
    spark = vectors.sparkSession
    single = vectors.schema["embedding"].dataType.simpleString() == "array<float>"  # kept so on disk; cosines are in double precision
    kind = np.float32 if single else np.float64
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<float>" if single else "array<double>").alias("e"))
    fine = (F.size("e") > 0) & ~F.exists("e", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))) & F.exists("e", lambda x: x != 0)
    rows = rows.withColumn("e", F.when(F.coalesce(fine, F.lit(False)) & F.col("vec_id").isNotNull(), F.col("e")))
    groups = written(rows.filter("e is not null").groupBy("e").agg(F.min("vec_id").alias("rep"), F.count("*").alias("w")), "vectors")
    sizes = groups.groupBy(F.size("e").alias("d")).agg(F.count("*").alias("k")).filter("k > 1").orderBy("d").collect()  # one a length
    if not sizes:
        part, counts = spark.createDataFrame([], "node long, component long"), spark.createDataFrame([], "rep long, n long")
    else:
        release(spark)
        tables = [t for r in sizes for t in _met(groups, r["d"], r["k"], least, kind)]
        met = reduce(DataFrame.unionByName, tables)
        counts = written(met.filter("n > 0").groupBy(F.col("a").alias("rep")).agg(F.sum("n").alias("n")), "counts")
        part = components(met.filter("n = 0").select("a", "b"))
        forget(*tables)
    named = groups.join(part, F.col("rep") == F.col("node"), "left").join(counts, "rep", "left")
    named = written(named.select("e", (F.col("w") - 1 + F.coalesce("n", F.lit(0))).alias("_n"), F.coalesce("component", "rep").alias("_c")), "named")
    forget(groups)
    release(spark)
    out = rows.join(named, "e", "left")
    component = F.coalesce("_c", "vec_id")
    return out.select("vec_id", F.coalesce("_n", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(component == F.col("vec_id"), F.lit(True)).alias("kept"))
