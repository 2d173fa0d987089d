"""Language-model scoring with a probabilistic suffix tree over tokens, with a tree over word forms as its back-off.

The token tree's states are contexts of one to TOKENS preceding tokens, told apart by fingerprints. A context is counted
if it occurs LEAST_COUNT times, with what follows it; what follows fewer than LEAST_PAIR times goes to the mass that its
shorter suffix shares out. It stays if what follows diverges from that suffix by more than chance explains, and with it stay
its suffixes. Contexts and what follows are counted, tested and met in joins, so their number is bounded by the corpus alone.
As a longer context's log probability is that of its suffix, its escape, and a bonus for what it has seen, a text's score is
a sum of values met by key. Where no token context stays, the word-form tree says all:

A token's symbol is the class of its form (its last letter, its longer characters, digits, other, or the text's end).
This tree's states are contexts of at most DEPTH symbols. A context stays if its next-symbol counts diverge from what
its shorter suffix predicts by more than chance explains (a likelihood-ratio test against its degrees of freedom), and
with it stay its suffixes. Distributions are smoothed towards the shorter suffix, weighted by how many different
symbols follow. A token's probability is that of its symbol in the longest suffix state, times that of the
token among the tokens of its class, where counts are smoothed as in the base score and one share is the unknown token's.

Everything the model learns is counted over all training documents. The word-form tree is bounded by its alphabet; counts of
words and token contexts are not, so only those frequent enough to be few (MOST_SHARED, SHARED_STATES) are shared with all
tasks, and the others meet their counts by bucket, in compressed pieces. A task that is run again must read its rows in the same order. Bitmaps of keys, which let through too much but never too little,
keep out of joins what meets nothing. Words are told apart by 64-bit fingerprints.

Results by case: null and empty texts consist of the end token; without training documents all counts are zero; repeated rows
give one row each; a row without an id is never held out.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import packed
from .flat import BYTE_CODE, LOWER, Texts, mix, per_text, prefix_hash, span_hash, texts_of
from .tables import files_dropped, forget, release, remainder, sifted, written

FOLDS, DEPTH, TOKENS = 10, 3, 3
#: Symbols: the end, the start, 16 classes of longer characters, 26 last letters, digits, others.
END, START, ALPHABET = 0, 1, 46
ADD = 0.1
#: Words shared with all tasks, at most; tokens a task counts before it hands counts on.
MOST_SHARED, HAND_ON = 1 << 18, 2_000_000
#: A context needs so many occurrences, and a statistic so many deviations above what chance gives.
LEAST_COUNT, DEVIATIONS = 20, 4.0
#: What follows a context needs so many occurrences to have a value of its own.
LEAST_PAIR = 3
#: Values of token contexts shared with all tasks, at most; bits of a bitmap of keys, at most, as a power of two.
SHARED_STATES, MOST_BITS = 1 << 20, 27
#: Rows that are merged at once, or so; bits of a part of a bitmap, as a power of two; texts whose questions leave a task together,
#: at most; parts of one in which sums of logs are moved.
BUCKET, RANGE, MOST_TEXTS, FIXED = 1 << 20, 20, 1 << 16, 2.0**30
END_WORD, START_WORD, AS_CONTEXT = np.uint64(0x454E44), np.uint64(0x5354415254), np.uint64(0x5A6C3B1D97E4F208)


class Sequence:
    """The token sequences of a slice: words' fingerprints and, if ``forms``, symbols, each text closed by the end token."""

    def __init__(self, t: Texts, forms: bool = True):
        low = LOWER[t.data]
        s, e, at = t.words(low)
        n = np.diff(at)
        self.at = np.concatenate([[0], np.cumsum(n + 1)])
        place = np.arange(len(s)) + np.repeat(np.arange(len(t)), n)
        prefix = prefix_hash(BYTE_CODE[low])
        self.word = np.full(self.at[-1], END_WORD, np.uint64)
        self.word[place] = span_hash(prefix, s, e)
        self.text = np.repeat(np.arange(len(t)), n + 1)
        self.since = np.arange(self.at[-1]) - self.at[self.text]
        self.key = mix(span_hash(prefix, t.cuts[:-1], t.cuts[1:]))
        if not forms:
            return
        self.symbol = np.full(self.at[-1], END, np.int64)
        if len(s):
            self.symbol[place] = self._classes(low, s, e)
        self.code = self.symbol.copy()  # of the symbol after its DEPTH predecessors
        self.context = np.zeros_like(self.code)
        for d in range(1, DEPTH + 1):
            before = np.full_like(self.symbol, START)
            before[d:] = self.symbol[: len(before) - d]
            before[self.since < d] = START
            self.context += before * ALPHABET ** (d - 1)
        self.code += self.context * ALPHABET

    def token_contexts(self) -> Iterator[tuple[int, np.ndarray, np.ndarray, np.ndarray, np.ndarray]]:
        """For each length: the length, places that have such a context, and there the keys of the context, of the context with
        the token that follows, and of its suffix with that token. A key with a token is that of the longer context after it."""
        last = self.word
        for d in range(1, TOKENS + 1):
            context = np.empty_like(last)
            context[1:] = last[:-1]
            if d == 1:
                context[self.since == 0] = START_WORD
            key = mix(mix(context + np.uint64(d)) ^ last)
            place = np.flatnonzero(self.since >= d - 1)
            yield d, place, context[place], key[place], last[place]
            last = key

    @staticmethod
    def _classes(low: np.ndarray, s: np.ndarray, e: np.ndarray) -> np.ndarray:
        longer = np.maximum.reduceat(np.where((low >= 0x80) & (low < 0xC0), low, 0), s).astype(np.int64)
        last = low[e - 1].astype(np.int64)
        letter = (last >= 97) & (last <= 122)
        last = np.where(letter | (e - s < 2), last, low[np.maximum(e - 2, 0)])
        letter = (last >= 97) & (last <= 122)
        plain = np.where(letter, 18 + last - 97, np.where((last >= 48) & (last <= 57), 44, 45))
        return np.where(longer > 0, 2 + (longer & 15), plain)


def _counts(docs: DataFrame) -> DataFrame:
    """(h, cls, n): training counts of words by fingerprint and class, and with class -1 those of symbol codes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        words: list[np.ndarray] = []
        codes: list[np.ndarray] = []

        def hand_on() -> Iterator[pa.RecordBatch]:
            if words:
                w, c = np.concatenate([x for x, _ in words]), np.concatenate([x for _, x in words])
                words.clear()  # before more is made of them
                first = np.argsort(w)
                h, (head, n) = w[first], packed.runs_of(w[first])
                h, first = h[head], first[head]
                k, m = np.unique(np.concatenate(codes), return_counts=True)
                codes.clear()
                out = pa.RecordBatch.from_arrays(
                    [pa.array(np.concatenate([h.view(np.int64), k])), pa.array(np.concatenate([c[first], np.full(len(k), -1)]).astype(np.int32)), pa.array(np.concatenate([n, m]).astype(np.int64))],
                    names=["h", "cls", "n"],
                )
                del w, c, h, first, head, n, k, m
                yield from (out.slice(i, MOST_TEXTS) for i in range(0, out.num_rows, MOST_TEXTS))

        for batch in batches:
            for t in texts_of(batch.column("text")):
                q = Sequence(t)
                words.append((q.word, q.symbol.astype(np.int8)))
                codes.append(q.code.astype(np.int32))
                if sum(map(len, codes)) >= HAND_ON // 2:  # counts meet again before they move
                    yield from hand_on()
        yield from hand_on()

    seen = docs.filter("train").select("text").mapInArrow(run, "h long, cls int, n long")
    return seen.groupBy("h", "cls").agg(F.sum("n").alias("n"))


class Tree:
    """Retained contexts and their smoothed next-symbol distributions."""

    def __init__(self, codes: np.ndarray, counts: np.ndarray):
        a = ALPHABET
        full = np.zeros(a ** (DEPTH + 1))
        full[codes] = counts
        level = [full.reshape(-1, a)]  # counts by context of DEPTH symbols, the nearest symbol last
        for d in range(DEPTH - 1, -1, -1):
            level.insert(0, level[0].reshape(a, -1, a).sum(0))
        root = (level[0][0] + ADD) / (level[0][0].sum() + ADD * a)
        smooth, tested = [root[None, :]], [np.ones(1, bool)]
        for d in range(1, DEPTH + 1):
            n, up = level[d], np.tile(smooth[-1], (a, 1))
            total, kinds = n.sum(1), (n > 0).sum(1)
            with np.errstate(divide="ignore", invalid="ignore"):
                g = 2 * np.where(n > 0, n * np.log(n / (total[:, None] * up)), 0).sum(1)
            tested.append((total >= LEAST_COUNT) & (g > kinds + DEVIATIONS * np.sqrt(2 * kinds)))
            smooth.append(np.where(total[:, None] > 0, (n + kinds[:, None] * up) / np.maximum(total + kinds, 1)[:, None], up))
        kept = tested
        for d in range(DEPTH - 1, 0, -1):
            kept[d] |= kept[d + 1].reshape(a, -1).any(0)  # suffixes of what stays
        state = np.zeros(1, np.int64)
        rows, base = [smooth[0]], 1
        for d in range(1, DEPTH + 1):
            # a context that goes hands its place to its suffix; one that stays is smoothed by its suffix's state
            own = np.flatnonzero(kept[d])
            state = np.tile(state, a)
            table = np.concatenate(rows)
            n = level[d][own]
            kinds, total = (n > 0).sum(1), n.sum(1)
            rows.append((n + kinds[:, None] * table[state[own]]) / np.maximum(total + kinds, 1)[:, None])
            state[own] = base + np.arange(len(own))
            base += len(own)
        self.state, self.log = state.astype(np.int32), np.log10(np.maximum(np.concatenate(rows), 1e-300)).astype(np.float32)

    def logs(self, q: Sequence) -> np.ndarray:
        return self.log[self.state[q.context], q.symbol].astype(np.float64)


class Bits:
    """A bitmap of 64-bit keys by their leading bits: has() is never wrong about a key that is in it."""

    def __init__(self, keys: DataFrame, column: str, n: int):
        self.log = log = min(MOST_BITS, max(10, (16 * n).bit_length()))

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for k in _gathered(batches, 0):
                at = np.unique(k[0] >> np.uint64(64 - log))
                yield packed.rows([(b, packed.pack(packed.steps(at[own]))) for b, own in packed.cut((at >> np.uint64(RANGE)).astype(np.int64))])

        def either(t: pa.Table) -> pa.Table:
            bits = np.zeros(1 << min(RANGE, log), np.uint8)
            for piece in packed.pieces_of(t):
                bits[np.cumsum(packed.unpack(piece)[0]) & np.uint64((1 << RANGE) - 1)] = 1
            return pa.table({"b": t.column("b").slice(0, 1), "w": pa.array([np.packbits(bits, bitorder="little").tobytes()], pa.binary())})

        parts = keys.select(column).mapInArrow(run, packed.PIECES).groupBy("b").applyInArrow(either, "b long, w binary").toArrow()
        self.bits = np.zeros(1 << (log - 6), np.uint64)
        for r in parts.to_pylist():  # 2 ** MOST_BITS bits in all
            w = np.frombuffer(r["w"], np.uint64)
            self.bits[r["b"] << (RANGE - 6) :][: len(w)] = w

    def __getstate__(self) -> tuple[int, bytes]:
        return self.log, packed.squeeze(self.bits.tobytes())

    def __setstate__(self, state: tuple[int, bytes]) -> None:
        self.log, self.bits = state[0], np.frombuffer(packed.unsqueeze(state[1]), np.uint64)

    def has(self, keys: np.ndarray) -> np.ndarray:
        at = keys >> np.uint64(64 - self.log)
        return (self.bits[(at >> np.uint64(6)).astype(np.int64)] >> (at & np.uint64(63))) & np.uint64(1) > 0


def _gathered(batches: Iterator[pa.RecordBatch], *columns: int) -> Iterator[list[np.ndarray]]:
    """Columns of a task's batches, HAND_ON rows or a few more at once; longs as unsigned."""
    some: list[list[np.ndarray]] = []
    for b in batches:
        some.append([np.asarray(b.column(c)) for c in columns])
        if sum(len(c[0]) for c in some) >= HAND_ON:
            yield [_unsigned(np.concatenate(c)) for c in zip(*some)]
            some = []
    if some:
        yield [_unsigned(np.concatenate(c)) for c in zip(*some)]


def _joined(rows: list[tuple[np.ndarray, ...]]) -> list[np.ndarray]:
    """The columns of ``rows``, which end up empty, so that both are not held while more is made of them."""
    columns = [list(c) for c in zip(*rows)]
    rows.clear()
    return [np.concatenate(columns.pop(0)) for _ in range(len(columns))]


def _unsigned(c: np.ndarray) -> np.ndarray:
    return c.view(np.uint64) if c.dtype == np.int64 else c


def _followed(docs: DataFrame, depth: int, among: Bits, often_enough: Bits, able: DataFrame, often: Places, total: int) -> DataFrame:
    """(k, x, y, n): training counts, LEAST_PAIR at least, of what follows the contexts of ``depth`` tokens that ``among`` lets
    through. What follows a suffix fewer times follows the context fewer times too, so ``often_enough`` drops it unmoved.

    A piece has contexts (with their suffixes, from which y is found) and the last tokens, those of ``often`` by their place there. Of
    ``total`` tokens' contexts BUCKET or so are merged at once: buckets go by context, but those ``able`` to fill a part of one by what follows too.
    """
    log = (total // BUCKET).bit_length()
    wide, _ = _parted(able.filter(F.col("n") > BUCKET // 16), MOST_SHARED)
    wide = Places(np.sort(wide.select("k").toPandas()["k"].to_numpy(np.int64).view(np.uint64)) if wide is not None else np.zeros(0, np.uint64))
    shared = docs.sparkSession.sparkContext.broadcast((among, often_enough, wide, often))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        among, often_enough, wide, often = shared.value
        some: list[tuple[np.ndarray, ...]] = []

        def hand_on() -> Iterator[pa.RecordBatch]:
            if some:
                k, w, *x = _joined(some)
                first = np.argsort(k)
                head, n = packed.runs_of(k[first])
                first = first[head]
                for c in (k, w, *x):
                    c[: len(first)] = c[first]
                k, w, *x = (c[: len(first)] for c in (k, w, *x))
                b = packed.bucket(np.where(wide.find(x[0])[1], k, mix(x[0])), log)
                at, hit = often.find(w)
                code = np.where(hit, at + 1, 0)
                order = np.argsort(code, kind="stable")
                order = order[np.argsort(x[0][order], kind="stable")]
                order = order[np.argsort(b[order], kind="stable")]
                w, n, code, x = w[order], n[order], code[order], [c[order] for c in x]
                out = []
                for i, own in packed.cut(b[order]):
                    head, length = packed.runs_of(x[0][own])
                    change = np.diff(code[own], prepend=0)
                    change[head] = code[own][head]  # ascending within a context
                    out.append((i, packed.pack(length, change, w[own][code[own] == 0], n[own], packed.steps(x[0][own][head]), *(c[own][head] for c in x[1:]))))
                del k, w, n, code, order, b, x, c, first, at, hit
                yield packed.rows(out)

        for batch in batches:
            for t in texts_of(batch.column("text")):
                q = Sequence(t, forms=False)
                suffixes: list[np.ndarray] = []
                for d, place, x, k, y in q.token_contexts():
                    if d == depth:
                        break
                    suffixes.insert(0, np.zeros_like(q.word))
                    suffixes[0][place] = x
                in_ = among.has(x)
                in_[in_] = often_enough.has(y[in_])
                some.append((k[in_], q.word[place[in_]], x[in_], *(c[place[in_]] for c in suffixes)))
                if sum(len(c[0]) for c in some) >= HAND_ON // 2:  # of up to five columns
                    yield from hand_on()
        yield from hand_on()

    def merged(t: pa.Table) -> pa.Table:
        often, parts = shared.value[3].keys, []
        for piece in packed.pieces_of(t):
            length, change, rare, n, x, *suffixes = packed.unpack(piece)
            length, x = length.view(np.int64), np.cumsum(x)
            code = np.cumsum(change.view(np.int64))
            head = np.cumsum(length) - length
            code -= np.repeat(np.where(head > 0, code[head - 1], 0), length)
            y = np.zeros(len(code), np.uint64)
            y[code == 0] = rare
            y[code > 0] = often[code[code > 0] - 1]
            for d, c in enumerate(reversed(suffixes), 1):
                y = mix(np.repeat(mix(c + np.uint64(d)), length) ^ y)
            parts.append((np.repeat(x, length), y, n))
        x, y, n = (np.concatenate(c) for c in zip(*parts))
        k = mix(mix(x + np.uint64(depth)) ^ y)
        order = np.argsort(k)
        head, _ = packed.runs_of(k[order])
        n = np.add.reduceat(n[order].view(np.int64), head) if len(head) else np.zeros(0, np.int64)
        own = order[head[n >= LEAST_PAIR]]
        return pa.table({**{c: pa.array(v[own].view(np.int64)) for c, v in (("k", k), ("x", x), ("y", y))}, "n": pa.array(n[n >= LEAST_PAIR])})

    return docs.filter("train").select("text").mapInArrow(run, packed.PIECES).groupBy("b").applyInArrow(merged, "k long, x long, y long, n long")


def _token_states(docs: DataFrame, words: DataFrame, often: Places, total: int, distinct: int, ends: int) -> list[DataFrame]:
    """(h, n, v), a table for each length: by key, the log escapes of the contexts that stay (keys xor AS_CONTEXT) and the bonuses
    of what they have seen."""
    start = docs.sparkSession.range(1).select(F.lit(int(START_WORD)).alias("k"), F.lit(int(ends)).cast("long").alias("n"))
    above = words.select(F.col("h").alias("k"), "n").unionByName(start).withColumn("lp", F.log((F.col("n") + ADD) / (total + ADD * (distinct + 1))))
    tables: list[DataFrame] = []
    stay: list[DataFrame] = []
    for d in range(1, TOKENS + 1):
        able = above.filter(F.col("n") >= LEAST_COUNT)
        n_able = able.count()
        if not n_able:
            break
        enough = above.filter(F.col("n") >= LEAST_PAIR)
        seen = written(_followed(docs, d, Bits(able, "k", n_able), Bits(enough, "k", enough.count()), able, often, total), "followed")
        release(docs.sparkSession)
        up = written(seen.join(above.select(F.col("k").alias("y"), F.col("lp").alias("up")), "y"), "suffixes")
        forget(seen)
        # all sums of the test are over n and up, so contexts are counted and tested before their rows move
        sums = {"s": F.col("n"), "nl": F.col("n") * F.log("n"), "nu": F.col("n") * F.col("up"), "q": F.exp("up")}
        per = up.groupBy("x").agg(F.count("*").alias("kinds"), *(F.sum(v).alias(c) for c, v in sums.items())).join(able.select(F.col("k").alias("x"), F.col("n").alias("total")), "x")
        every = F.col("total") + F.col("kinds")
        left = every - F.col("s")
        rest = F.col("total") - F.col("s")
        cells = F.col("kinds") + (rest > 0).cast("int")
        g = F.col("nl") - F.col("s") * F.log("total") - F.col("nu")
        other = F.when(rest > 0, rest * F.log(rest / (F.col("total") * F.greatest(F.lit(1e-12), 1 - F.col("q"))))).otherwise(0.0)
        # what has no value of its own is one cell of the test
        stays = 2 * (g + other) > cells + DEVIATIONS * F.sqrt(2 * cells)
        tested = written(per.select("x", "total", "kinds", "s", F.log10(left / every).alias("escape"), stays.alias("stays")), "tested")
        p = (F.col("n") + left * F.exp("up")) / every
        valued = up.join(tested, "x").select("k", "x", "y", "n", F.log(p).alias("lp"), (F.log10(p) - F.log10(left / every) - F.col("up") / math.log(10)).alias("bonus"))
        here = written(valued, "contexts")
        forget(up)
        tables.append(here)
        stay.append(tested)
        above = here.select("k", "n", "lp")
        release(docs.sparkSession)
    out: list[DataFrame] = []
    longer = above = None  # suffixes of what stays, and what they are read from
    for d in range(len(tables) - 1, -1, -1):
        kept = stay[d].filter("stays").select("x")
        kept = written((kept if longer is None else kept.unionByName(longer)).distinct(), "kept")
        if above is not None:
            forget(above)
        states = stay[d].join(kept, "x", "left_semi").select(F.col("x").bitwiseXOR(F.lit(int(AS_CONTEXT))).alias("h"), F.col("total").alias("n"), F.col("escape").alias("v"))
        both = states.unionByName(tables[d].join(kept, "x", "left_semi").select(F.col("k").alias("h"), "n", F.col("bonus").alias("v")))
        out.append(written(both, "states"))
        forget(tables[d], stay[d])
        if d:
            of = kept.select(F.col("x").alias("k"))
            longer = sifted(tables[d - 1].select("k", "y"), "k", of).join(of, "k", "left_semi").select(F.col("y").alias("x"))
        above = kept
        del states, both
        release(docs.sparkSession)
    if above is not None:
        forget(above)
    return out


def _parted(table: DataFrame, most: int) -> tuple[DataFrame | None, DataFrame]:
    """The rows with the largest n, as far as whole bins of n hold at most ``most`` rows, and the others."""
    bins = table.groupBy(F.floor(4 * F.log2("n")).alias("b")).count().orderBy(F.desc("b")).collect()  # a few hundred at most
    least, some = None, 0
    for r in bins:
        some += r["count"]
        if some > most:
            break
        least = r["b"]
    if least is None:
        return None, table
    frequent = F.floor(4 * F.log2("n")) >= F.lit(least)
    return table.filter(frequent), table.filter(~frequent)


def _fixed(v: np.ndarray) -> np.ndarray:
    """Sums of logs in parts of FIXED, in which they are shorter and add up the same in any order."""
    return packed.signed(np.rint(v * FIXED))


class Places:
    """Ascending 64-bit keys, found from where those with the same leading bits begin."""

    def __init__(self, keys: np.ndarray):
        self.n, self.log = len(keys), max(1, (2 * len(keys)).bit_length())
        self.keys = np.append(keys, np.uint64(2**64 - 1))
        each = np.bincount((keys >> np.uint64(64 - self.log)).view(np.int64), minlength=1 << self.log)
        self.start = np.cumsum(each, dtype=np.int32)
        self.start -= each.astype(np.int32)

    def __reduce__(self) -> tuple:
        return Places._of, (packed.pack(packed.steps(self.keys[: self.n])),)

    @staticmethod
    def _of(piece: bytes) -> Places:
        return Places(np.cumsum(packed.unpack(piece)[0]))

    def find(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where keys stand, and whether they do; where they do not, the place may be one past the last."""
        k = self.start[(keys >> np.uint64(64 - self.log)).view(np.int64)]
        at = self.keys[k]
        open_ = np.flatnonzero(at < keys)
        while len(open_):
            k[open_] += 1
            at[open_] = self.keys[k[open_]]
            open_ = open_[at[open_] < keys[open_]]
        return k, (at == keys) & (k < self.n)


def _rounds(tokens: int) -> int:
    """Rounds in which texts ask: more where the shared states answer less."""
    return 2 + (tokens // (128 * BUCKET)).bit_length() if tokens > BUCKET else 1


def score_documents(docs: DataFrame) -> DataFrame:
    """Per document: doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score."""
    with files_dropped(docs.sparkSession):
        return _scores(docs)


def _scores(docs: DataFrame) -> DataFrame:
    """What score_documents returns, written: each query in here runs once."""
    spark = docs.sparkSession
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    held = F.col("doc_id").isNotNull() & (remainder(F.col("doc_id"), FOLDS) == 0)
    rows = rows.withColumn("train", ~held)
    table = written(_counts(rows), "counts")
    release(spark)
    words = table.filter("cls >= 0")
    codes = table.filter("cls = -1").select("h", "n").toPandas()  # at most ALPHABET ** (DEPTH + 1) rows
    tree = Tree(codes["h"].to_numpy(np.int64), codes["n"].to_numpy(np.float64))
    by_class = {r["cls"]: (r["n"], r["v"]) for r in words.groupBy("cls").agg(F.sum("n").alias("n"), F.count("*").alias("v")).collect()}  # one a class
    total, distinct = sum(n for n, _ in by_class.values()), sum(v for _, v in by_class.values())
    log_all = math.log10(total + ADD * (distinct + 1))
    log_class = np.array([math.log10(by_class.get(c, (0, 0))[0] + ADD * (by_class.get(c, (0, 0))[1] + 1)) for c in range(ALPHABET)])
    frequent, rare = _parted(words, MOST_SHARED)
    shared_words = frequent.select("h", "n").toArrow() if frequent is not None else None
    often, count = (shared_words[c].to_numpy() for c in ("h", "n")) if shared_words is not None else np.zeros((2, 0), np.int64)
    order = np.argsort(often.view(np.uint64))
    known = Places(often.view(np.uint64)[order]), count[order]
    ends = by_class.get(END, (0, 0))[0]
    parts = _token_states(rows, words, known[0], total, distinct, ends) if ends else []
    states = reduce(DataFrame.unionByName, parts) if parts else None
    n_states = states.count() if states is not None else 0
    valued = (Places(np.zeros(0, np.uint64)), np.zeros(0), None)
    if n_states:
        top, seldom = _parted(states, SHARED_STATES)
        top = (states.limit(0) if top is None else top).select("h", "v").toArrow()
        keys = top["h"].to_numpy().view(np.uint64)
        order = np.argsort(keys)
        valued = (Places(keys[order]), top["v"].to_numpy()[order], Bits(states, "h", n_states))
    shared = spark.sparkContext.broadcast((tree, *known, log_class, ends, valued))
    log = (total // (4 * BUCKET)).bit_length()
    rounds = _rounds(total)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, often, count, per_class, ends, (keys, values, bits) = shared.value
        log_count = np.append(np.log10(count + ADD), 0.0)
        asked: list[tuple[np.ndarray, ...]] = []
        texts: list[tuple[np.ndarray, ...]] = []

        def hand_on() -> Iterator[pa.RecordBatch]:
            """What the texts so far ask, by bucket, and the texts themselves; g tells them from all others but their equals."""
            if texts:
                key, *each = _joined(texts)
                g = int(np.bitwise_xor.reduce(mix(key + np.arange(1, len(key) + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15))).view(np.int64))
                ask, of, extra = _joined(asked)
                order = np.argsort(ask)
                for c in (ask, of, extra):
                    c[:] = c[order]
                del order
                out = [(int(g & ((1 << log) - 1)), packed.pack(*each))]
                for i, at in packed.cut(packed.bucket(ask, log)):
                    head, length = packed.runs_of(ask[at])
                    is_word = np.isnan(extra[at][head])
                    swaps = np.flatnonzero(np.nan_to_num(extra[at]))
                    out.append((i, packed.pack(packed.steps(ask[at][head]), is_word, length, of[at], packed.steps(swaps), _fixed(extra[at][swaps]))))
                del ask, of, extra
                sides = [3] + [0] * (len(out) - 1)
                yield packed.rows(out, ("g", pa.array([g] * len(out), pa.int64())), ("side", pa.array(sides, pa.int32())))
        for batch in batches:
            for t in texts_of(batch.column("text")):
                q = Sequence(t)
                before = sum(len(c[0]) for c in texts)
                ids = batch.column("doc_id").slice(t.row, len(t))
                key = mix(q.key ^ mix(np.asarray(ids.fill_null(-1)).astype(np.int64).view(np.uint64) + np.uint64(77)))
                k, hit = often.find(q.word)
                value = np.where(hit, log_count[k], 0.0)
                last = q.symbol == END
                value[last] = math.log10(ends + ADD)
                sure = hit | last
                # the end is the only token of its class, so its class says all
                model = own.logs(q) - np.where(last, 0.0, per_class[q.symbol])
                n = len(t)
                score = per_text(model + np.where(last, 0.0, value), q.at, empty=0.0)
                tail = np.flatnonzero(~sure)
                asked.append((q.word[tail], (before + q.text[tail]).astype(np.uint32), np.full(len(tail), np.nan)))  # nan: a word
                if bits is not None:
                    # from the word-form tree to the base score, from which token contexts go on
                    swap = np.where(last, value, 0.0) - log_all - model
                    open_ = np.ones(len(q.word), bool)
                    for d, place, x, y, _ in q.token_contexts():
                        # suffixes of what stays stay, and only what stays has bonuses: the bitmap is asked on along such chains alone
                        on = open_[place]
                        on[on] = bits.has(x[on] ^ AS_CONTEXT)
                        place, x, y = place[on], x[on] ^ AS_CONTEXT, y[on]
                        open_ = np.zeros(len(q.word), bool)
                        open_[place] = True
                        seen = bits.has(y)
                        for at, of, extra in ((x, place, swap[place] if d == 1 else np.zeros(len(place))), (y[seen], place[seen], np.zeros(seen.sum()))):
                            k, hit = keys.find(at)
                            if hit.any():
                                score = score + np.bincount(q.text[of[hit]], values[k[hit]] + extra[hit], n)
                            asked.append((at[~hit], (before + q.text[of[~hit]]).astype(np.uint32), extra[~hit]))
                hits = per_text((sure & (value > math.log10(ADD) + 1e-9)).astype(np.int64), q.at)
                texts.append((key, np.asarray(ids.fill_null(0)).astype(np.int64), np.asarray(ids.is_null()), np.diff(q.at), hits, per_text(value, q.at, empty=0.0), score))
                if sum(len(c[0]) for c in asked) >= HAND_ON or before + n >= MOST_TEXTS:
                    yield from hand_on()
        yield from hand_on()

    def table_of(is_word: bool):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for h, v in _gathered(batches, 0, 1):
                order = np.argsort(h)
                h, v = h[order], v[order] if is_word else _fixed(v[order])
                out = [(i, packed.pack(packed.steps(h[at]), v[at])) for i, at in packed.cut(packed.bucket(h, log))]
                yield packed.rows(out, ("g", pa.array([0] * len(out), pa.int64())), ("side", pa.array([1 + is_word] * len(out), pa.int32())))

        return run

    def answered(t: pa.Table) -> pa.Table:
        """For each piece of a bucket's questions, what they add to its texts. Sides: 0 questions, 1 states, 2 words, 3 texts."""
        side = np.asarray(t.column("side"))
        found = []
        for s in (1, 2):
            parts = [packed.unpack(p) for p in packed.pieces_of(t.filter(pa.array(side == s)))]
            h, v = ([np.cumsum(x) for x, _ in parts], [x for _, x in parts])
            h, v = (np.concatenate(h), np.concatenate(v)) if parts else (np.zeros(0, np.uint64), np.zeros(0, np.uint64))
            order = np.argsort(h)
            v = packed.unsigned(v[order]) / FIXED if s == 1 else np.log10(v[order] + ADD)
            found.append((Places(h[order]), np.append(v, 0.0)))
        ask = t.filter(pa.array(side == 0))
        out = []
        for piece in packed.pieces_of(ask):
            h, is_word, length, of, at, swaps = packed.unpack(piece)
            h, is_word, length, of = np.cumsum(h), is_word > 0, length.view(np.int64), of.view(np.int64)
            extra = np.zeros(len(of))
            extra[np.cumsum(at).view(np.int64)] = packed.unsigned(swaps) / FIXED
            k, hit = found[0][0].find(h)
            hit &= ~is_word
            v = np.where(hit, found[0][1][k], 0.0)
            k, known = found[1][0].find(h)
            known &= is_word
            w = np.where(is_word, np.where(known, found[1][1][k], math.log10(ADD)), 0.0)
            each = lambda x: np.repeat(x, length)
            m = int(of.max()) + 1 if len(of) else 0
            sums = [np.bincount(of, x, m) for x in (each(known), each(w), each(v) + np.where(each(hit), extra, 0.0))]
            some = np.flatnonzero((sums[0] != 0) | (sums[1] != 0) | (sums[2] != 0))
            out.append(packed.pack(packed.steps(some), sums[0][some].astype(np.int64), *(_fixed(x[some]) for x in sums[1:])))
        texts = t.filter(pa.array(side == 3)).select(["g", "side", "piece"])  # on their way to the answers
        return pa.concat_tables([pa.table({"g": ask.column("g"), "side": ask.column("side"), "piece": pa.array(out, pa.binary())}), texts])

    def scored(t: pa.Table) -> pa.Table:
        own = np.asarray(t.column("side")) == 3
        equal = list(packed.pieces_of(t.filter(pa.array(own))))
        ids, null, n_tokens, hits, base, model = packed.unpack(equal[0])
        more, add, swap = np.zeros((3, len(ids)), np.int64)
        for piece in packed.pieces_of(t.filter(pa.array(~own))):
            at, *sums = packed.unpack(piece)
            at = np.cumsum(at).view(np.int64)
            more[at] += sums[0].view(np.int64)
            add[at] += packed.unsigned(sums[1])
            swap[at] += packed.unsigned(sums[2])
        m = len(equal)  # equal pieces share g, and all came together
        add, swap, n_tokens, base = add / (m * FIXED), swap / (m * FIXED), n_tokens.view(np.int64), base.view(np.float64)
        out = pa.table({
            "doc_id": pa.array(ids.view(np.int64), mask=null > 0), "n_tokens": pa.array(n_tokens), "n_known": pa.array(hits.view(np.int64) + more // m),
            "base_score": pa.array(base + add - n_tokens * log_all), "score": pa.array(model.view(np.float64) + add + swap),
        })
        return pa.concat_tables([out] * m)

    # what is not shared is asked for in rounds of texts, whose shuffle files are let go: questions grow faster than the texts
    sided = f"{packed.PIECES}, g long, side int"
    lists = rare.select("h", "n").mapInArrow(table_of(True), sided)
    if n_states:
        lists = lists.unionByName(seldom.select("h", "v").mapInArrow(table_of(False), sided))
    lists = written(lists, "lists")
    forget(table, *parts)
    release(spark)
    out = None
    for i in range(rounds):
        some = rows.select("doc_id", "text")
        if rounds > 1:
            some = some.filter(F.pmod(F.xxhash64("doc_id", "text"), F.lit(rounds)) == i)
        moved = some.mapInArrow(run, sided).unionByName(lists)
        met = moved.groupBy("b").applyInArrow(answered, "g long, side int, piece binary").groupBy("g").applyInArrow(scored, "doc_id long, n_tokens long, n_known long, base_score double, score double")
        met = written(met, "scores")
        out = met if out is None else out.unionByName(met)
        del moved
        release(spark)
    forget(lists)
    shared.destroy()
    held = F.col("doc_id").isNotNull() & (remainder(F.col("doc_id"), FOLDS) == 0)
    return out.select("doc_id", held.alias("held_out"), "n_tokens", "n_known", F.lit(int(total)).cast("long").alias("train_tokens"), "base_score", "score")
