"""Byte-level BPE encoding and decoding in batched numpy merge rounds.

All words that a batch needs for the first time lie in one flat symbol array. A round looks up every
adjacent pair by binary search in the sorted pair keys, takes each word's lowest rank, and merges all
its occurrences at once; words without a mergeable pair leave the array. As every merge of the vocabulary
makes a symbol of its own, no later pair can rank below the one being merged, so a round gives what
merging one occurrence at a time gives. A word may be of any length: rounds act on arrays, so time
and memory follow its length.

Results by case: null and empty texts encode to no ids; the special token's string in a text is its id;
repeated rows and null ids give one result row each; other columns of the input are ignored.
"""

from __future__ import annotations

import functools
import hashlib
import json
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute  # noqa: F401
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .flat import texts_of
from .tables import widened

#: Fixed value: the public pattern that cuts texts into words before merging.
WORDS = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
#: Words remembered by a Python worker before it starts anew.
REMEMBERED = 200_000
_NONE = np.iinfo(np.int32).max


def _visible() -> dict[str, int]:
    """The printable character that stands for each byte in byte-level vocabularies."""
    plain = [b for b in range(256) if 33 <= b <= 126 or 161 <= b <= 172 or 174 <= b <= 255]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


@functools.cache
def basic_plane_words() -> re.Pattern:
    """WORDS for texts within the basic plane, in the standard library's faster engine: the same classes, spelt as ranges."""

    def ranges(kind: str) -> str:
        is_in = regex.compile(kind).match
        codes = np.array([c for c in range(0x10000) if not 0xD800 <= c <= 0xDFFF and is_in(chr(c))])
        ends = np.flatnonzero(np.diff(codes, append=-9) != 1)
        return "".join(f"\\u{codes[a]:04x}-\\u{codes[b]:04x}" for a, b in zip([0, *(ends[:-1] + 1)], ends))

    letter, number, space = ranges(r"\p{L}"), ranges(r"\p{N}"), ranges(r"\s")
    return re.compile(f" ?[{letter}]+|'(?:[stmd]|re|ve|ll)| ?[{number}]+| ?[^{space}{letter}{number}]+|[{space}]+(?![^{space}])|[{space}]+")


class Vocabulary:
    """Merge tables and token bytes of a byte-level BPE vocabulary file; picklable."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        model, byte_of = spec["model"], _visible()
        ids = model["vocab"]
        self.special = {x["content"]: x["id"] for x in spec.get("added_tokens", ())}
        self.size = max([*ids.values(), *self.special.values()]) + 1
        token = [b""] * self.size
        for text, i in ids.items():
            token[i] = bytes(byte_of[c] for c in text)
        for text, i in self.special.items():
            token[i] = text.encode()
        self.first = np.zeros(256, np.int32)
        for c, b in byte_of.items():
            self.first[b] = ids[c]
        pairs = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        key = np.array([ids[a] * self.size + ids[b] for a, b in pairs], np.int64)
        made = np.array([ids[a + b] for a, b in pairs], np.int32)
        order = np.argsort(key)
        self.pair, self.rank, self.made = key[order], order.astype(np.int32), made[order]
        both = self.first.astype(np.int64)[:, None] * self.size + self.first
        at = np.minimum(np.searchsorted(self.pair, both), len(self.pair) - 1)
        self.of_bytes = np.where(self.pair[at] == both, at, -1).astype(np.int32)
        self.cut = np.zeros(self.size + 1, np.int64)
        np.cumsum([len(t) for t in token], out=self.cut[1:])
        self.bytes = np.frombuffer(b"".join(token), np.uint8)

    def merge(self, words: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all words in one array, and the words' n + 1 offsets in it."""
        size = np.fromiter(map(len, words), np.int64, len(words))
        raw = np.frombuffer(b"".join(words), np.uint8)
        sym, first = self.first[raw], True
        word = np.repeat(np.arange(len(words)), size)
        done_sym, done_word = [], []
        while len(sym):
            rank, made = np.full(len(sym), _NONE, np.int32), np.zeros(len(sym), np.int32)
            if first and len(sym) > 1:  # symbols are single bytes still: a table of all their pairs
                at = self.of_bytes[raw[:-1], raw[1:]]
                hit = (at >= 0) & (word[:-1] == word[1:])
                rank[:-1][hit], made[:-1][hit] = self.rank[at[hit]], self.made[at[hit]]
            elif len(sym) > 1:
                key = sym[:-1].astype(np.int64) * self.size + sym[1:]
                at = np.minimum(np.searchsorted(self.pair, key), len(self.pair) - 1)
                hit = (self.pair[at] == key) & (word[:-1] == word[1:])
                rank[:-1][hit], made[:-1][hit] = self.rank[at[hit]], self.made[at[hit]]
            head = np.flatnonzero(np.concatenate([[True], word[1:] != word[:-1]]))
            least = np.repeat(np.minimum.reduceat(rank, head), np.diff(np.append(head, len(sym))))
            over = least == _NONE
            if over.any():
                first = False
                done_sym.append(sym[over])
                done_word.append(word[over])
            take = np.flatnonzero((rank == least) & ~over)
            if not len(take):
                break
            # of touching occurrences (one symbol repeated) every second one merges, from the left
            run = np.concatenate([[True], np.diff(take) != 1])
            began = np.maximum.accumulate(np.where(run, take, -1))
            take = take[(take - began) % 2 == 0]
            sym[take], first = made[take], False
            keep = ~over
            keep[take + 1] = False
            sym, word = sym[keep], word[keep]
        if not done_sym:
            return np.zeros(0, np.int32), np.zeros(len(words) + 1, np.int64)
        sym, word = np.concatenate(done_sym), np.concatenate(done_word)
        order = np.argsort(word, kind="stable")
        cut = np.zeros(len(words) + 1, np.int64)
        np.cumsum(np.bincount(word, minlength=len(words)), out=cut[1:])
        return sym[order], cut


def decoded(v: Vocabulary, ids: np.ndarray, cut: np.ndarray) -> list[bytes]:
    """UTF-8 of each decoded text; bytes that form no character become the replacement character."""
    data, size = gather(v.bytes, v.cut, ids)
    ends = np.concatenate([[0], np.cumsum(size)])[cut]
    raw = data.tobytes()
    return [raw[a:b].decode("utf-8", "replace").encode() for a, b in zip(ends[:-1].tolist(), ends[1:].tolist())]


def gather(values: np.ndarray, cut: np.ndarray, which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The pieces values[cut[w]:cut[w + 1]] for w in which, joined, and their lengths."""
    size = cut[which + 1] - cut[which]
    ends = np.cumsum(size)
    if not len(ends):
        return values[:0], size
    return values[np.repeat(cut[which] - (ends - size), size) + np.arange(ends[-1])], size


class Encoder:
    """Encodes batches with a memory of the words met so far."""

    def __init__(self, vocabulary: Vocabulary):
        self.v, self.words, self.basic = vocabulary, regex.compile(WORDS), basic_plane_words()
        self.specials = regex.compile("(" + "|".join(map(regex.escape, vocabulary.special)) + ")") if vocabulary.special else None
        self._forget()

    def _forget(self) -> None:
        self.slot: dict[str, int] = {}
        self.ids, self.cut = np.zeros(0, np.int32), np.zeros(1, np.int64)
        for text, i in self.v.special.items():
            self._add([("\0special", text)], np.array([i], np.int32), np.array([0, 1]))

    def _add(self, words: list, ids: np.ndarray, cut: np.ndarray) -> None:
        n = len(self.slot)
        self.slot.update(zip(words, range(n, n + len(words))))
        self.cut = np.concatenate([self.cut, cut[1:] + self.cut[-1]])
        self.ids = np.concatenate([self.ids, ids])

    def _words(self, text: str) -> list[str]:
        within = text.isascii() or len(text.encode("utf-16-le")) == 2 * len(text)
        return (self.basic if within else self.words).findall(text)

    def _cut(self, text: str) -> list:
        if self.specials is None or not any(s in text for s in self.v.special):
            return self._words(text)
        out: list = []
        for k, part in enumerate(self.specials.split(text)):
            out += [("\0special", part)] if k % 2 else self._words(part)
        return out

    def encode(self, texts: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts in one array, and the texts' n + 1 offsets in it."""
        if len(self.slot) > REMEMBERED:
            self._forget()
        pieces, count = [], np.zeros(len(texts) + 1, np.int64)
        for k, t in enumerate(texts):
            pieces += self._cut(t)
            count[k + 1] = len(pieces)
        new = list(set(pieces).difference(self.slot))
        if new:
            self._add(new, *self.v.merge([w.encode() for w in new]))
        which = np.fromiter(map(self.slot.__getitem__, pieces), np.int64, len(pieces))
        ids, size = gather(self.ids, self.cut, which)
        ends = np.concatenate([[0], np.cumsum(size)])
        return ids, ends[count]


def _coded(batches: Iterator[pa.RecordBatch], vocabulary: Vocabulary, text: int) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """Slices of the batches with the ids of their texts, column ``text``, and the texts' offsets in them."""
    encoder = Encoder(vocabulary)
    for batch in batches:
        for part in texts_of(batch.column(text)):
            raw, c = part.data.tobytes(), part.cuts.tolist()
            yield batch.slice(part.row, len(part)), *encoder.encode([raw[a:b].decode() for a, b in zip(c, c[1:])])


def _shared(df: DataFrame, path: str):
    return df.sparkSession.sparkContext.broadcast(Vocabulary(path))  # as large as the vocabulary file


def _strings(texts: list[bytes]) -> pa.Array:
    return pa.array(texts, pa.binary()).cast(pa.string())


def encode(df: DataFrame, path: str, text: str = "text", into: str = "ids", back: str | None = None) -> DataFrame:
    """df with one more column: the ids (array of int) of each whole text; and, named ``back``, the text they stand for."""
    shared = _shared(df, path)
    names = [f"c{i}" for i in range(len(df.columns))]
    more = {"ids": "array<int>"} | ({"back": "string"} if back else {})
    at = df.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, ids, cut in _coded(batches, shared.value, at):
            lists = pa.ListArray.from_arrays(pa.array(cut.astype(np.int32)), pa.array(ids))
            texts = [_strings(decoded(shared.value, ids, cut))] if back else []
            yield pa.RecordBatch.from_arrays([*rows.columns, lists, *texts], names=[*names, *more])

    plain = df.toDF(*names)
    return plain.mapInArrow(run, widened(plain, **more)).toDF(*df.columns, into, *([back] if back else []))


def decode(df: DataFrame, path: str, ids: str = "ids", into: str = "decoded") -> DataFrame:
    """df with one more column: the text that the ids stand for; null ids stand for the empty text."""
    shared = _shared(df, path)
    names = [f"c{i}" for i in range(len(df.columns))]
    at = df.columns.index(ids)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lists = batch.column(at)
            size = np.asarray(pa.compute.fill_null(pa.compute.list_value_length(lists), 0))
            flat = np.asarray(lists.flatten(), np.int32)  # without what null lists hold
            texts = decoded(shared.value, flat, np.concatenate([[0], np.cumsum(size, dtype=np.int64)]))
            yield pa.RecordBatch.from_arrays([*batch.columns, _strings(texts)], names=[*names, "back"])

    plain = df.toDF(*names)
    return plain.mapInArrow(run, widened(plain, back="string")).toDF(*df.columns, into)


def digests(docs: DataFrame, path: str) -> DataFrame:
    """Per document the count and digest of its ids, and the digest of what they decode to."""
    shared = _shared(docs, path)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows, ids, cut in _coded(batches, shared.value, 1):
            raw = ids.astype("<u4").tobytes()
            yield pa.RecordBatch.from_arrays(
                [
                    rows.column(0),
                    pa.array(np.diff(cut)),
                    pa.array([hashlib.sha256(raw[4 * a : 4 * b]).hexdigest() for a, b in zip(cut[:-1].tolist(), cut[1:].tolist())], pa.string()),
                    pa.array([hashlib.sha256(t).hexdigest() for t in decoded(shared.value, ids, cut)], pa.string()),
                ],
                names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"],
            )

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
