"""Near-duplicate documents by b-bit MinHash, confirmed on full shingle sets.

One pass over the texts gives each document its set of word shingles, a digest of that set, HASHES minima of which
only BITS low bits are kept and packed, and band keys from the full minima. Equal sets collapse by digest
first, so copies cost one row. A band bucket does not pair all its members: each is compared with the
smallest, pairs whose packed signatures, corrected for chance collisions, estimate a similarity far below the
threshold are dropped, and the others are confirmed by exact intersection and union of the sets. Those links are joined
into components. Buckets that still hold several components are compared exactly, in groups of slices of bounded size: a
group (without texts that share too few shingles with any other to be linked) multiplies its texts' incidence matrix of shingles with itself and returns edges between components, never its pairs.

At 28 bands of 4 minima a pair at similarity 0.8 shares no bucket with probability 4e-7; the estimate's margin is
over five standard errors.

Results by case: null and empty texts and texts without words have an empty set and no links; with fewer
words than a shingle the whole sequence is one; repeated rows are linked; a row without an id is linked with
nothing, has no component and is kept; texts that share an id count as one document.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .components import components, least_labels
from .flat import BYTE_CODE, LOWER, SLICE_BYTES, Texts, mix, per_text, prefix_hash, span_hash, texts_of
from .tables import flagged, forget, sifted, written

BANDS, ROWS, BITS = 28, 4, 8
HASHES = BANDS * ROWS
#: Estimates below the threshold by more than this are not confirmed.
MARGIN = 0.2
#: Texts of a bucket that are compared in one group with as many others, and shingles taken at once.
SLICE, WIDTH = 512, 4096
_U = np.uint64
_rng = np.random.default_rng(20)
_A = _rng.integers(1 << 31, size=HASHES, dtype=np.uint32) * np.uint32(2) + np.uint32(1)
_B = _rng.integers(1 << 32, size=HASHES, dtype=np.uint32)


def shingle_sets(t: Texts, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Fingerprints of each text's distinct shingles of k words, sorted, and n + 1 offsets."""
    low = LOWER[t.data]
    s, e, at = t.words(low)
    word = span_hash(prefix_hash(BYTE_CODE[low]), s, e)
    count = np.diff(at)
    text = np.repeat(np.arange(len(t)), count)

    def fold(first: np.ndarray, n: int) -> np.ndarray:
        g = np.full(len(first), n, np.uint64)
        for i in range(n):
            g = mix(g * _U(0x9E3779B97F4A7C15) + word[first + i])
        return g

    begin = np.flatnonzero((text[: len(word) - k + 1] == text[k - 1 :])) if len(word) >= k else np.zeros(0, np.int64)
    got, own = [fold(begin, k)], [text[begin]]
    for n in range(1, k):
        few = np.flatnonzero(count == n)
        got.append(fold(at[few], n))
        own.append(few)
    g, own_text = np.concatenate(got), np.concatenate(own)
    order = np.lexsort((g, own_text))
    g, own_text = g[order], own_text[order]
    first = np.ones(len(g), bool)
    first[1:] = (g[1:] != g[:-1]) | (own_text[1:] != own_text[:-1])
    return g[first], np.searchsorted(own_text[first], np.arange(len(t) + 1))


def _signatures(g: np.ndarray, at: np.ndarray) -> np.ndarray:
    h = (g >> _U(32)).astype(np.uint32)
    out = np.zeros((len(at) - 1, HASHES), np.uint32)
    for i in range(HASHES):
        out[:, i] = per_text(h * _A[i] + _B[i], at, np.minimum, 0)
    return out


def features(docs: DataFrame, k: int) -> DataFrame:
    """doc_id, n_shingles, set digest (k1, k2), packed signature (sig) and band keys (bands)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for t in texts_of(batch.column("text")):
                g, at = shingle_sets(t, k)
                n = np.diff(at)
                k1 = per_text(mix(g), at, np.add, 0)
                k2 = per_text(mix(g ^ _U(0x5851F42D4C957F2D)), at, np.bitwise_xor, 0)
                low = _signatures(g, at)
                packed = ((low * np.uint32(2654435761)) >> np.uint32(32 - BITS)).astype(np.uint8)
                sig = np.ascontiguousarray(packed).view(np.int64)
                key = np.tile(np.arange(1, BANDS + 1, dtype=np.uint64), (len(t), 1))
                for r in range(ROWS):
                    key = mix(key * _U(0x9E3779B97F4A7C15) + low[:, r::ROWS].astype(np.uint64))
                lists = lambda x: pa.FixedSizeListArray.from_arrays(pa.array(x.reshape(-1)), x.shape[1]).cast(pa.list_(pa.int64()))
                yield pa.RecordBatch.from_arrays(
                    [batch.column("doc_id").slice(t.row, len(t)), pa.array(n.astype(np.int64)), pa.array(k1.view(np.int64)), pa.array(k2.view(np.int64)), lists(sig), lists(key.view(np.int64))],
                    names=["doc_id", "n_shingles", "k1", "k2", "sig", "bands"],
                )

    return docs.mapInArrow(run, "doc_id long, n_shingles long, k1 long, k2 long, sig array<long>, bands array<long>")


def estimate(x: Column, y: Column) -> Column:
    """The similarity that two packed signatures suggest: the share of equal values, less what chance gives."""

    def differ(a: Column, b: Column) -> Column:
        d = a.bitwiseXOR(b)
        for s in (1, 2, 4):  # folds each byte's bits into its lowest one
            d = d.bitwiseOR(F.shiftrightunsigned(d, s))
        return F.bit_count(d.bitwiseAND(F.lit(0x0101010101010101)))

    equal = 1 - F.aggregate(F.zip_with(x, y, differ), F.lit(0), lambda acc, v: acc + v) / F.lit(HASHES)
    chance = 1 / (1 << BITS)
    return (equal - chance) / (1 - chance)


def _overlaps(pairs: DataFrame, k: int, least: int) -> DataFrame:
    """(a, b) of the pairs (a, b, ta, tb) of whole texts whose shingle sets are similar enough."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            size = np.zeros(batch.num_rows + 1, np.int64)
            for c in ("ta", "tb"):
                size[1:] += np.asarray(pa.compute.fill_null(pa.compute.binary_length(batch.column(c)), 0))
            size = np.cumsum(size)
            i = 0
            while i < batch.num_rows:
                j = max(i + 1, int(np.searchsorted(size, size[i] + SLICE_BYTES, "right")) - 1)
                part = batch.slice(i, j - i)
                i = j
                sets = [shingle_sets(next(texts_of(part.column(c), 1 << 62)), k) for c in ("ta", "tb")]
                n = [np.diff(at) for _, at in sets]
                both = np.concatenate([g for g, _ in sets])
                row = np.concatenate([np.repeat(np.arange(part.num_rows), m) for m in n])
                order = np.lexsort((both, row))
                same = (both[order][1:] == both[order][:-1]) & (row[order][1:] == row[order][:-1])
                common = np.bincount(row[order][1:][same], minlength=part.num_rows)
                ok = (100 * common >= least * (n[0] + n[1] - common)) & (common > 0)
                yield part.select(["a", "b"]).filter(pa.array(ok))

    return pairs.select("a", "b", "ta", "tb").mapInArrow(run, "a long, b long")


def _of(texts: DataFrame, ids: DataFrame) -> DataFrame:
    """The texts with these ids; a shared bitmap drops most others before anything moves."""
    ids = written(ids.distinct(), "ids")
    return sifted(texts, "doc_id", ids).join(ids, "doc_id", "left_semi")


def _spelt(texts: DataFrame, k: int) -> DataFrame:
    """(doc_id, shingles): the fingerprints of each text's shingles."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for t in texts_of(batch.column("text")):
                g, at = shingle_sets(t, k)
                lists = pa.ListArray.from_arrays(pa.array(at.astype(np.int32)), pa.array(g.view(np.int64)))
                yield pa.RecordBatch.from_arrays([batch.column("doc_id").slice(t.row, len(t)), lists], names=["doc_id", "shingles"])

    return texts.select("doc_id", "text").mapInArrow(run, "doc_id long, shingles array<long>")


def _tied(least: int):
    """Of a group of texts (rep, component c, shingles): edges that join the components that links of the group connect."""

    def run(t: pa.Table) -> pa.Table:
        t = t.combine_chunks()
        lists = t.column("shingles").combine_chunks()
        lists = lists.chunk(0) if isinstance(lists, pa.ChunkedArray) else lists
        offs = np.asarray(lists.offsets).astype(np.int64)
        n = np.diff(offs)
        row = np.repeat(np.arange(len(n)), n)
        value = np.asarray(lists.flatten())
        _, where, df = np.unique(value, return_inverse=True, return_counts=True)
        order = np.argsort(where, kind="stable")
        order = order[df[where[order]] > 1]  # shingles of one text alone are in no intersection
        column = np.cumsum(np.concatenate([[0], where[order][1:] != where[order][:-1]])) if len(order) else order
        common = np.zeros((len(n), len(n)), np.float32)
        cuts = np.searchsorted(column, np.arange(0, (column[-1] + 1 if len(column) else 0) + WIDTH, WIDTH))
        for x, y in zip(cuts[:-1], cuts[1:]):
            m = np.zeros((len(n), WIDTH), np.float32)
            m[row[order[x:y]], column[x:y] % WIDTH] = 1
            common += m @ m.T
        comps, c = np.unique(np.asarray(t.column("c")), return_inverse=True)
        a, b = np.nonzero((100 * common >= least * (n[:, None] + n[None, :] - common)) & (c[:, None] < c[None, :]))
        label = least_labels(len(comps), c[a], c[b])
        tied = np.flatnonzero(label != np.arange(len(comps)))
        return pa.table({"a": pa.array(comps[label[tied]].astype(np.int64)), "b": pa.array(comps[tied].astype(np.int64))})

    return run


def near_duplicates(docs: DataFrame, k: int = 5, least: int = 80) -> DataFrame:
    """doc_id, n_shingles, component_id and kept of every row of docs (doc_id, text), in shingles of k words; links need
    100 * intersection >= least * union."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    f = written(features(rows, k), "features")
    known = f.filter("n_shingles > 0 and doc_id is not null")
    sets = written(known.groupBy("k1", "k2").agg(F.min("doc_id").alias("rep"), F.first("n_shingles").alias("size"), F.first("sig").alias("sig"), F.first("bands").alias("bands")), "sets")
    member = sets.select("rep", F.explode("bands").alias("key"))
    buckets = written(member.groupBy("key").agg(F.min("rep").alias("m"), F.max("rep").alias("x")).filter("m <> x").select("key", "m"), "buckets")
    in_bucket = written(member.join(buckets, "key"), "members")

    repeats = known.groupBy("doc_id").count().filter("count > 1").limit(1).count()
    texts = rows.filter("doc_id is not null")
    texts = texts.dropDuplicates(["doc_id", "text"]) if repeats else texts
    sig = lambda c: sets.select(F.col("rep").alias(c), F.col("sig").alias(f"s{c}"))
    likely = estimate(F.col("sa"), F.col("sb")) >= least / 100 - MARGIN

    def confirmed(pairs: DataFrame) -> DataFrame:
        """The pairs (a, b) that are links."""
        pairs = written(pairs.distinct(), "pairs")
        if pairs.isEmpty():
            return pairs
        some = written(_of(texts, pairs.select(F.explode(F.array("a", "b")).alias("doc_id"))), "texts")
        side = lambda c, t: some.select(F.col("doc_id").alias(c), F.col("text").alias(t))
        return written(_overlaps(pairs.join(side("a", "ta"), "a").join(side("b", "tb"), "b"), k, least), "links")

    def placed(members: DataFrame, part: DataFrame) -> DataFrame:
        """The members (key, rep and more), with their components c, of the buckets that hold several components."""
        own = members.join(part, F.col("rep") == F.col("node"), "left").withColumn("c", F.coalesce("component", "rep")).drop("node", "component")
        own = written(own, "placed")
        several = written(own.groupBy("key").agg(F.min("c").alias("lo"), F.max("c").alias("hi")).filter("lo <> hi").select("key"), "open")
        return own.join(several, "key")

    first = in_bucket.filter("rep <> m").select(F.col("m").alias("a"), F.col("rep").alias("b")).distinct()
    links = confirmed(first.join(sig("a"), "a").join(sig("b"), "b").filter(likely).select("a", "b"))
    part = components(links)
    left = written(placed(in_bucket.select("key", "rep"), part), "left")
    if not left.isEmpty():
        spelt = written(_spelt(_of(texts, left.select(F.col("rep").alias("doc_id"))), k).withColumnRenamed("doc_id", "rep"), "spelt")
        # shingles that no other open text has are in no intersection, so few others bound what a text can share in its bucket
        alone = spelt.select("rep", F.explode("shingles").alias("g")).groupBy("g").agg(F.min("rep").alias("rep"), F.max("rep").alias("x")).filter("rep = x")
        alone = written(alone.groupBy("rep").agg(F.count("*").alias("own")), "alone")
        size = spelt.select("rep", F.size("shingles").alias("size")).join(alone, "rep", "left").withColumn("free", F.col("size") - F.coalesce("own", F.lit(0)))
        sized = written(left.join(size.select("rep", "size", "free"), "rep"), "sized")
        least_size = written(sized.groupBy("key").agg(F.min("size").alias("least")), "sizes")
        able = sized.join(least_size, "key").filter((100 + least) * F.col("free") >= least * (F.col("size") + F.col("least")))
        left = written(placed(able.select("key", "rep"), part), "able")
        slices = written(left.groupBy("key").agg(F.ceil(F.count("*") / SLICE).cast("int").alias("n")), "slices")
        own = F.pmod(F.xxhash64("rep"), F.col("n")).cast("int")
        dealt = left.join(slices, "key").withColumn("s", own).withColumn("t", F.explode(F.sequence(F.lit(0), F.col("n") - 1)))
        dealt = dealt.select("key", "rep", "c", F.least("s", "t").alias("i"), F.greatest("s", "t").alias("j")).join(spelt, "rep")
        more = written(dealt.groupBy("key", "i", "j").applyInArrow(_tied(least), "a long, b long").distinct(), "ties")
        part = components(links.unionByName(more))
    named = sets.join(part, F.col("rep") == F.col("node"), "left").select("k1", "k2", F.coalesce("component", "rep").alias("_c"))
    named = written(named, "named")
    out = f.select("doc_id", "n_shingles", "k1", "k2").join(named, ["k1", "k2"], "left")
    component = F.when(F.col("n_shingles") > 0, F.least("_c", "doc_id")).otherwise(F.col("doc_id"))
    component = F.when(F.col("doc_id").isNotNull(), component)
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(component == F.col("doc_id"), F.lit(True)).alias("kept"))


def keep_one(docs: DataFrame, k: int = 5, least: int = 80) -> DataFrame:
    """docs with one document of each group of near-duplicates, that of the smallest id; all columns stay. Of rows that repeat
    both an id and a text one stays."""
    names = [f"x{i}" for i in range(len(docs.columns))]  # so that no column is taken for another
    own, text = (names[docs.columns.index(c)] for c in ("doc_id", "text"))
    found = written(near_duplicates(docs.select("doc_id", "text"), k, least).select("doc_id", "kept"), "found")
    gone = written(found.filter("not kept").select(F.col("doc_id").alias("gone")), "gone")
    # only rows that the bitmap takes for gone may move to meet the ids; the others stay where they are
    rows = flagged(docs.toDF(*names), own, gone, "_maybe")
    met = rows.filter("_maybe").join(gone, F.col(own).cast("long") == F.col("gone"), "left_anti")
    left = rows.filter("not _maybe").unionByName(met).drop("_maybe")
    if not found.filter("doc_id is not null").groupBy("doc_id").count().filter("count > 1").isEmpty():
        left = left.filter(F.col(own).isNotNull()).dropDuplicates([own, text]).unionByName(left.filter(F.col(own).isNull()))
    return left.toDF(*docs.columns)
