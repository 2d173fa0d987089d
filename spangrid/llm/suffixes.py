"""Exact removal of repeated byte strings with a suffix array over the suffixes that can repeat.

A byte goes if a string of LENGTH bytes that covers it starts anywhere else too. Sorting every suffix would move hundreds of bytes for
each byte of text, so suffixes are first told apart by anchors: the anchor of a start is the least-fingerprint gram of
GRAM bytes within its string. Equal strings have equal anchors, so

1. starts fall into classes, runs of neighbouring starts with one anchor occurrence; a class whose anchor occurs nowhere else is done;
2. a class whose whole segment (all bytes its strings cover) occurs again repeats entirely;
3. of the others, one copy of each different segment is range-partitioned by its anchor, with
   splitters sampled by the range exchange. A bucket lists the suffixes of its segments, sorts them locally by multikey
   quicksort (anchor, leading bytes, then a fingerprint of the string's rest), and neighbours that agree over LENGTH bytes repeat;
4. anchors with many different segments are not kept together: their suffixes are range-partitioned one by one, with ties broken
   by owner, so that a very frequent string may spread over buckets; buckets are then compared across their boundaries.

Fingerprints have 64 bits and are always joined with another 64 bits (anchor or leading bytes).

Results by case: null and empty texts have no bytes; texts under LENGTH bytes keep all; strings do not cross texts; repeated rows
repeat each other; rows without an id are rows like any other.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .flat import BYTE_CODE, prefix_hash, span_hash, texts_of
from .tables import flagged, forget, sifted, written

LENGTH, GRAM = 400, 128
#: Different segments of one anchor that are sorted together, at most.
TOGETHER = 64
#: Suffixes that a bucket lists at once.
LISTED = 150_000
#: Bytes of texts, and rows, that one array operation takes (a text is never cut).
SLICE, SLICE_ROWS = 1 << 20, 500


def _least(g: np.ndarray, width: int) -> np.ndarray:
    """Least of g[i : i + width] for each i."""
    cur, span = g, 1
    while span * 2 <= width:
        cur = np.minimum(cur[:-span], cur[span:])
        span *= 2
    n = len(g) - width + 1
    return np.minimum(cur[:n], cur[width - span : width - span + n])


def _classes(docs: DataFrame, length: int, gram: int) -> DataFrame:
    """(a, s, k, q, n): anchor and segment fingerprints, row key, first start and number of starts of each class."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for t in texts_of(batch.column("text"), SLICE):
                m = len(t.data) - length + 1
                if m <= 0:
                    continue
                prefix = prefix_hash(BYTE_CODE[t.data])
                i = np.arange(len(t.data) - gram + 1)
                g = span_hash(prefix, i, i + gram)
                least = _least(g, length - gram + 1)
                text = np.repeat(np.arange(len(t)), np.diff(t.cuts))[:m]
                ok = i[:m] + length <= t.cuts[1:][text]
                new = np.ones(m, bool)
                new[1:] = ~ok[:-1] | (least[1:] != least[:-1]) | (g[: m - 1] == least[:-1])
                new |= ~ok
                q = np.flatnonzero(new)
                n = np.diff(np.append(q, m))
                q, n = q[ok[q]], n[ok[q]]
                own = text[q]
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(least[q].view(np.int64)),
                        pa.array(span_hash(prefix, q, q + n - 1 + length).view(np.int64)),
                        batch.column("k").slice(t.row, len(t)).take(pa.array(own)),
                        pa.array((q - t.cuts[own]).astype(np.int32)),
                        pa.array(n.astype(np.int32)),
                    ],
                    names=["a", "s", "k", "q", "n"],
                )

    return docs.select("k", "text").mapInArrow(run, "a long, s long, k long, q int, n int")


def multikey_order(*keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """An order by the keys in turn, and whether each row in it equals its predecessor in all of them.

    Each key sorts only the rows that still tie on those before it.
    """
    order = np.argsort(keys[0], kind="stable")
    tie = np.zeros(len(order), bool)
    tie[1:] = keys[0][order][1:] == keys[0][order][:-1]
    for key in keys[1:]:
        tied = tie.copy()
        tied[:-1] |= tie[1:]
        at = np.flatnonzero(tied)
        if not len(at):
            break
        run = np.cumsum(~tie[at])
        sub = order[at]
        inner = np.lexsort((key[sub], run))
        order[at] = sub[inner]
        value = key[order[at]]
        still = np.zeros(len(at), bool)
        still[1:] = (value[1:] == value[:-1]) & (run[1:] == run[:-1])
        tie[at] = still
    return order, tie


def _suffix_keys(data: np.ndarray, starts: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Leading 8 bytes (as an ordered number) and the fingerprint of the string of each start."""
    lead = np.zeros(len(starts), np.uint64)
    for j in range(8):
        lead = (lead << np.uint64(8)) | data[starts + j].astype(np.uint64)
    return lead, span_hash(prefix_hash(BYTE_CODE[data]), starts, starts + length)


def _ranges(starts: np.ndarray, length: int) -> tuple[np.ndarray, np.ndarray]:
    """Covered ranges of sorted starts."""
    if not len(starts):
        return starts, starts
    head = np.concatenate([[True], np.diff(starts) > length])
    first = np.flatnonzero(head)
    return starts[first], starts[np.append(first[1:], len(starts)) - 1] + length


def _segments(texts: DataFrame, length: int) -> DataFrame:
    """One row with its bytes for each wanted segment of the rows (k, text, segs)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (b.slice(i, SLICE_ROWS) for b in batches for i in range(0, b.num_rows, SLICE_ROWS)):
            out: list = []
            for k, text, segs in zip(batch.column("k").to_pylist(), batch.column("text").to_pylist(), batch.column("segs").to_pylist()):
                raw = text.encode()
                for x in segs:
                    out.append((x["a"], x["s"], x["c"], x["many"], k, x["q"], x["n"], raw[x["q"] : x["q"] + x["n"] - 1 + length]))
            if out:
                kinds = (pa.int64(), pa.int64(), pa.int64(), pa.bool_(), pa.int64(), pa.int32(), pa.int32(), pa.binary())
                yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(zip(*out), kinds)], names=["a", "s", "c", "many", "k", "q", "n", "raw"])

    return texts.mapInArrow(run, "a long, s long, c long, many boolean, k long, q int, n int, raw binary")


def _listed(rows: pa.Table, length: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Lead, fingerprint, row and offset of every suffix of the rows' segments."""
    n = np.asarray(rows.column("n")).astype(np.int64)
    raw = rows.column("raw").to_pylist()
    cut = np.concatenate([[0], np.cumsum([len(x) for x in raw])])
    row = np.repeat(np.arange(len(n)), n)
    off = np.arange(len(row)) - np.repeat(np.cumsum(n) - n, n)
    lead, print_ = _suffix_keys(np.frombuffer(b"".join(raw), np.uint8), cut[row] + off, length)
    return lead, print_, row, off


def _sorted_together(segments: DataFrame, length: int) -> DataFrame:
    """(k, lo, hi) covered in segments of anchors that are kept together; rows come sorted by anchor."""

    def solve(t: pa.Table) -> pa.RecordBatch:
        lead, print_, row, off = _listed(t, length)
        anchor = np.asarray(t.column("a")).view(np.uint64)[row]
        order, tie = multikey_order(anchor, lead, print_)
        hit = tie.copy()
        hit[:-1] |= tie[1:]
        again = np.zeros(len(row), bool)
        again[order[hit]] = True
        again &= np.asarray(t.column("c"))[row] == 1  # the others repeat entirely
        # a segment's hits, one range after another
        at = np.flatnonzero(again)
        far = row[at] * (1 << 40) + off[at]
        lo, hi = _ranges(far, length)
        own = lo >> 40
        q = np.asarray(t.column("q")).astype(np.int64)[own]
        return pa.RecordBatch.from_arrays([t.column("k").combine_chunks().take(pa.array(own)), pa.array(q + (lo & ((1 << 40) - 1))), pa.array(q + (hi & ((1 << 40) - 1)))], names=["k", "lo", "hi"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.Table] = []
        size = 0
        for batch in batches:
            for i in range(0, batch.num_rows, SLICE_ROWS):
                part = pa.Table.from_batches([batch.slice(i, SLICE_ROWS)])
                held.append(part)
                size += int(np.asarray(part.column("n")).sum())
                if size < LISTED:
                    continue
                whole = pa.concat_tables(held)
                a = np.asarray(whole.column("a"))
                full = int(np.flatnonzero(a != a[-1])[-1]) + 1 if (a != a[-1]).any() else 0  # all but the last anchor
                if full:
                    yield solve(whole.slice(0, full))
                held = [whole.slice(full)]
                size = int(np.asarray(held[0].column("n")).sum())
        if size:
            yield solve(pa.concat_tables(held))

    return segments.mapInArrow(run, "k long, lo long, hi long")


def _sorted_apart(segments: DataFrame, length: int) -> DataFrame:
    """(k, lo, hi) covered in segments of anchors with many different ones, whose suffixes are dealt out one by one."""
    spark = segments.sparkSession

    def spell(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(0, batch.num_rows, SLICE_ROWS):
                t = pa.Table.from_batches([batch.slice(i, SLICE_ROWS)])
                lead, print_, row, off = _listed(t, length)
                flip = np.uint64(1 << 63)  # signed order as the bytes' order
                q = np.asarray(t.column("q")).astype(np.int64)[row] + off
                yield pa.RecordBatch.from_arrays(
                    [pa.array((lead ^ flip).view(np.int64)), pa.array((print_ ^ flip).view(np.int64)), t.column("k").combine_chunks().take(pa.array(row)), pa.array(q), pa.array(np.asarray(t.column("c"))[row] == 1)],
                    names=["lead", "rest", "k", "q", "single"],
                )

    suffixes = segments.mapInArrow(spell, "lead long, rest long, k long, q long, single boolean")
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = suffixes.repartitionByRange(parts, "lead", "rest", "k", "q").sortWithinPartitions("lead", "rest", "k", "q")

    def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows with an equal neighbour (edge 0), and the bucket's first and last rows (edge 1)."""
        names = ["lead", "rest", "k", "q", "single"]
        last: tuple | None = None
        held: pa.RecordBatch | None = None  # the last row so far
        told = True

        def rows(t: pa.RecordBatch, take: np.ndarray, edge: int) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([*t.take(pa.array(np.flatnonzero(take))).columns, pa.array(np.full(int(take.sum()), edge, np.int32))], names=[*names, "edge"])

        for b in batches:
            if not b.num_rows:
                continue
            lead, rest = np.asarray(b.column("lead")), np.asarray(b.column("rest"))
            _, tie = multikey_order(lead, rest)  # the exchange has sorted the rows; ties are what is new
            hit = tie.copy()
            hit[:-1] |= tie[1:]
            one = np.ones(1, bool)
            if held is None:
                yield rows(b.slice(0, 1), one, 1)
            elif last == (lead[0], rest[0]):
                hit[0] = True
                if not told:
                    yield rows(held, one, 0)
            if hit.any():
                yield rows(b, hit, 0)
            held, last, told = b.slice(b.num_rows - 1, 1), (lead[-1], rest[-1]), bool(hit[-1])
        if held is not None:
            yield rows(held, np.ones(1, bool), 1)

    met = written(dealt.mapInArrow(compare, "lead long, rest long, k long, q long, single boolean, edge int"), "suffixes")
    edges = met.filter("edge = 1").select("lead", "rest", "k", "q", "single").distinct()  # two a bucket
    shared = edges.groupBy("lead", "rest").count().filter("count > 1").select("lead", "rest")
    hits = met.filter("edge = 0 and single").select("k", "q").unionByName(edges.filter("single").join(shared, ["lead", "rest"], "left_semi").select("k", "q"))
    return hits.select("k", F.col("q").alias("lo"), (F.col("q") + length).alias("hi"))


def _merged(spans: DataFrame) -> DataFrame:
    """(k, cover): each row's covered ranges, sorted and joined, as lo, hi, lo, hi ..."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            covers = []
            for x in b.column("spans").to_pylist():
                lo, hi = (np.array([v[c] for v in x], np.int64) for c in ("lo", "hi"))
                order = np.argsort(lo, kind="stable")
                lo, top = lo[order], np.maximum.accumulate(hi[order])
                head = np.concatenate([[True], lo[1:] > top[:-1]])
                ends = np.append(np.flatnonzero(head)[1:], len(lo)) - 1
                covers.append(np.stack([lo[head], top[ends]], 1).reshape(-1).tolist())
            yield pa.RecordBatch.from_arrays([b.column("k"), pa.array(covers, pa.list_(pa.int64()))], names=["k", "cover"])

    return spans.groupBy("k").agg(F.collect_set(F.struct("lo", "hi")).alias("spans")).mapInArrow(run, "k long, cover array<long>")


def covers(keyed: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """(k, cover) of the rows (k, text) with bytes to remove."""
    classes = written(_classes(keyed, length, gram), "classes")
    anchors = classes.groupBy("a").agg(F.count("*").alias("m"), F.min("s").alias("s0"), F.max("s").alias("s1")).filter("m > 1")
    anchors = written(anchors.select("a", (F.col("s0") != F.col("s1")).alias("mixed")), "anchors")
    again = written(classes.join(anchors, "a"), "again")
    whole = again.filter("not mixed").select("k", "q", "n")
    mixed = again.filter("mixed")
    segs = written(mixed.groupBy("a", "s").agg(F.count("*").alias("c"), F.first("k").alias("k"), F.first("q").alias("q"), F.first("n").alias("n")), "segments")
    many = written(segs.groupBy("a").agg(F.count("*").alias("v")).filter(F.col("v") > TOGETHER).select(F.col("a").alias("_a")), "many")
    twice = written(segs.filter("c > 1").select(F.col("a").alias("_a"), F.col("s").alias("_s")), "twice")
    whole = whole.unionByName(mixed.join(twice, (F.col("a") == F.col("_a")) & (F.col("s") == F.col("_s")), "left_semi").select("k", "q", "n"))
    spans = whole.select("k", F.col("q").cast("long").alias("lo"), (F.col("q") + F.col("n") - 1 + length).cast("long").alias("hi"))
    flagged = segs.join(many, F.col("a") == F.col("_a"), "left").withColumn("many", F.col("_a").isNotNull())
    wanted = written(flagged.groupBy("k").agg(F.collect_list(F.struct("a", "s", "c", "many", "q", "n")).alias("segs")), "wanted")
    some = sifted(keyed, "k", wanted.select("k")).join(wanted.hint("merge"), "k")
    found = written(_segments(some, length).dropDuplicates(["k", "q"]), "found")
    parts = int(keyed.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    together = found.filter("not many").repartitionByRange(parts, "a").sortWithinPartitions("a")
    spans = spans.unionByName(_sorted_together(together, length)).unionByName(_sorted_apart(found.filter("many"), length))
    out = written(_merged(spans), "covers")
    forget(classes, anchors, again, segs, many, twice, wanted, found)
    return out


def remove_repeats(docs: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """Per document: n_bytes, n_removed, n_spans, the digest of what is left, and what is left (bytes)."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    keyed = rows.withColumn("k", F.xxhash64("doc_id", "text"))
    cover = covers(keyed.select("k", "text"), length, gram)
    # only rows that may have a cover meet the covers
    marked = flagged(keyed, "k", cover.select("k"), "may")
    joined = marked.filter("may").join(cover.hint("merge"), "k", "left").select("doc_id", "text", "cover")
    joined = joined.unionByName(marked.filter("not may").select("doc_id", "text", F.lit(None).cast("array<long>").alias("cover")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in (x.slice(i, SLICE_ROWS) for x in batches for i in range(0, x.num_rows, SLICE_ROWS)):
            out = []
            for text, own in zip(b.column("text").to_pylist(), b.column("cover").to_pylist()):
                raw = text.encode()
                cut = [0, *(own or ()), len(raw)]
                left = b"".join(raw[i:j] for i, j in zip(cut[::2], cut[1::2]))
                out.append((len(raw), len(raw) - len(left), len(own or ()) // 2, hashlib.sha256(left).hexdigest(), left))
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary())
            columns = [pa.array(v, t) for v, t in zip(zip(*out), kinds)] if out else [pa.array([], t) for t in kinds]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), *columns], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"])

    return joined.mapInArrow(run, "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, kept binary")
