"""A uniform shuffle of rows into shards of exact sizes, by a hypergeometric communication matrix.

Rows first fall into hashed source buckets. From the buckets' row counts alone one matrix is drawn: how many
rows each bucket sends to each shard, distributed as in a uniform permutation of all rows, with shard sizes
at most one apart. A bucket then orders its rows at random and deals them out along its line of the matrix
(first local permutation and exchange); a shard orders what it got at random (second permutation). Every
(bucket, shard) count is exact, so no row moves twice and no shard overflows; a bucket or shard is never
handled whole by one task beyond its bounded share, as buckets and the slots' sub-ranges grow in number with
the rows.

Law: ``rows`` (row counts at most one apart). Equal rows are placed independently; they, null ids and null texts are rows like any other;
a null text has no bytes and the checksum of none. Other columns are ignored.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .tables import written

#: Rows that a source bucket, and a sub-range of a shard's slots, hold on average once there are many.
BUCKET_ROWS = 200_000
LEAST_BUCKETS = 512


def communication_matrix(rows: np.ndarray, shards: int, seed: int) -> np.ndarray:
    """M[b, s]: rows bucket b sends to shard s. Line sums are ``rows``; column sums are at most one apart."""
    total = int(rows.sum())
    left = np.full(shards, total // shards, np.int64)
    left[: total % shards] += 1
    rng = np.random.default_rng(seed)
    out = np.zeros((len(rows), shards), np.int64)
    for b, n in enumerate(rows):
        out[b] = _draw(rng, left, int(n))
        left -= out[b]
    return out


def _drift(a: int, d: int) -> float:
    """log gamma(a + d) - log gamma(a) for a > 0, by differences, as the values themselves are too large to subtract."""
    if a < 1000 or a + d < 1000:
        return math.lgamma(a + d) - math.lgamma(a)
    return (a + d - 0.5) * math.log1p(d / a) + d * (math.log(a) - 1) + (1 / (a + d) - 1 / a) / 12


def hypergeometric(rng: np.random.Generator, good: int, bad: int, n: int) -> int:
    """How many of n draws without return from good + bad are good, for counts of any size: the law is log-concave, so a flat top
    and exponential tails around its mode lie above it, and what falls below it is taken."""
    if max(good, bad) < 1_000_000_000:
        return int(rng.hypergeometric(good, bad, n))
    lo, hi = max(0, n - bad), min(n, good)
    mode = min(hi, max(lo, (n + 1) * (good + 1) // (good + bad + 2)))

    def ratio(x: int) -> float:
        """log of the probability of mode + x over that of the mode."""
        return -(_drift(mode + 1, x) + _drift(good - mode + 1, -x) + _drift(n - mode + 1, -x) + _drift(bad - n + mode + 1, x))

    # the mode's probability, somewhat too small, so that the cover is too wide rather than too narrow
    choose = lambda a, b: _drift(a - b + 1, b) - math.lgamma(b + 1)
    top = 0.99 * min(1.0, math.exp(min(0.0, choose(good, mode) + choose(bad, n - mode) - choose(good + bad, n))))
    if lo == hi:
        return lo
    wide = 1 + top / 2
    while True:
        u, v, w = rng.random(3)
        y = v * wide / top if u <= wide / (1 + wide) else (wide + rng.exponential()) / top
        x = (1 if rng.random() < 0.5 else -1) * round(y)
        if lo <= mode + x <= hi and math.log(w) + min(0.0, wide - top * y) <= ratio(x):
            return mode + x


def _draw(rng: np.random.Generator, left: np.ndarray, n: int) -> np.ndarray:
    """One multivariate hypergeometric draw, by marginals, shard by shard."""
    if left.sum() < 1_000_000_000:
        return rng.multivariate_hypergeometric(left, n, method="marginals")
    out, rest = np.zeros(len(left), np.int64), int(left.sum())
    for s, k in enumerate(left.tolist()):
        rest -= k
        out[s] = hypergeometric(rng, k, rest, n)
        n -= int(out[s])
    return out


def _random(seed: int, *columns: Column) -> Column:
    return F.xxhash64(F.lit(seed), *columns)


def shuffle_into_shards(rows: DataFrame, shards: int, seed: int = 11) -> DataFrame:
    """rows with ``shard`` and a gapless ``slot`` within it. rows should be narrow."""
    spark = rows.sparkSession
    # equal rows are told apart by where they stand, once that is written, so that their places are independent too
    names = [f"x{i}" for i in range(len(rows.columns))]
    own = [F.col(c) for c in (*names, "twin")]
    told = written(rows.toDF(*names).withColumn("twin", F.monotonically_increasing_id()), "rows")
    n = told.count()
    buckets = max(LEAST_BUCKETS, -(-n // BUCKET_ROWS))
    placed = told.withColumn("b", F.pmod(_random(seed, *own), F.lit(buckets)).cast("int"))
    count = dict(placed.groupBy("b").count().collect())  # one number a bucket
    sent = communication_matrix(np.array([count.get(b, 0) for b in range(buckets)], np.int64), shards, seed)
    upto = np.cumsum(sent, axis=1)
    lines = spark.createDataFrame([(b, [int(x) for x in upto[b]]) for b in range(buckets)], "b int, upto array<long>")
    local = Window.partitionBy("b").orderBy(_random(seed + 1, *own), *own)
    dealt = (
        placed.withColumn("r", F.row_number().over(local) - 1)
        .join(lines, "b")
        .withColumn("shard", F.size(F.filter("upto", lambda x: x <= F.col("r"))))
    )
    parts = max(16, -(-n // (shards * BUCKET_ROWS)))
    again = _random(seed + 2, *own)
    dealt = written(dealt.select(*own, "shard", again.alias("x")).withColumn("p", F.floor((F.col("x") / F.lit(2.0**63) + 1) / 2 * (1 - 1e-12) * parts).cast("int")), "dealt")
    sizes = dealt.groupBy("shard", "p").count()
    before = Window.partitionBy("shard").orderBy("p").rowsBetween(Window.unboundedPreceding, -1)
    starts = sizes.select("shard", "p", F.coalesce(F.sum("count").over(before), F.lit(0)).alias("start"))
    within = Window.partitionBy("shard", "p").orderBy("x", *own)
    out = dealt.withColumn("k", F.row_number().over(within) - 1).join(starts, ["shard", "p"])
    return out.select(*names, "shard", (F.col("start") + F.col("k")).cast("long").alias("slot")).toDF(*rows.columns, "shard", "slot")


def shard_documents(docs: DataFrame, shards: int, seed: int = 11) -> DataFrame:
    """Ids, sizes and checksums of all documents with their shard and slot under the law ``rows``."""
    raw = F.coalesce(F.col("text").cast("string"), F.lit("")).cast("binary")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), (F.octet_length(raw) + 8).cast("long").alias("size"), F.crc32(raw).alias("text_crc32"))
    out = shuffle_into_shards(rows, shards, seed)
    return out.select("doc_id", "size", "text_crc32", F.lit("rows").alias("law"), F.col("shard").cast("int").alias("shard"), "slot", F.lit(None).cast("int").alias("grown_shard"))
