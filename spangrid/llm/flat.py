"""Flat-byte kernels shared by the text operators.

An Arrow batch of texts is one byte buffer plus offsets. Every kernel here works on that buffer with
numpy, so a batch of a thousand texts costs the same number of Python calls as one text. Batches are
cut into slices of bounded size, but a text is never cut: a slice holds at least one whole text.

Null texts count as empty. White space is the six ASCII bytes of ``[\\x20\\x09-\\x0D]``; as UTF-8 never
uses those bytes inside a longer character, words can be found on bytes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SLICE_BYTES = 1 << 20

_U = np.uint64
SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_BASE = _U(0x9E3779B97F4A7C15)
_BASE_INV = _U(pow(0x9E3779B97F4A7C15, -1, 1 << 64))


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser (xor-shift and odd multipliers)."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x ^= x >> _U(27)
    x = x * _U(0x94D049BB133111EB)
    x ^= x >> _U(31)
    return x


BYTE_CODE = mix(np.arange(1, 257, dtype=np.uint64) * _U(0xD1342543DE82EF95))
_powers: dict[str, np.ndarray] = {}


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i modulo 2**64 for i below n."""
    if "up" not in _powers or len(_powers["up"]) < n:
        size = max(n, SLICE_BYTES + 1)
        for name, b in (("up", _BASE), ("down", _BASE_INV)):
            x = np.full(size, b, np.uint64)
            x[0] = 1
            _powers[name] = np.multiply.accumulate(x)
    return _powers["up"][:n], _powers["down"][:n]


def prefix_hash(codes: np.ndarray) -> np.ndarray:
    """P with P[j] the polynomial value of the first j codes; see span_hash()."""
    out = np.zeros(len(codes) + 1, np.uint64)
    np.cumsum(codes * powers(len(codes))[0], out=out[1:])
    return out


def span_hash(prefix: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """64-bit fingerprints of the spans [lo, hi): equal content gives equal values wherever it stands."""
    down = powers(len(prefix))[1]
    return mix((prefix[hi] - prefix[lo]) * down[lo] + (hi - lo).astype(np.uint64) * _U(0xA0761D6478BD642F))


class Texts:
    """Some whole texts: ``data`` (bytes), ``cuts`` (n + 1 byte offsets), ``row`` (their rows in the batch)."""

    def __init__(self, data: np.ndarray, cuts: np.ndarray, row: int):
        self.data, self.cuts, self.row = data, cuts, row

    def __len__(self) -> int:
        return len(self.cuts) - 1

    def words(self, data: np.ndarray | None = None, inside: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Starts and ends of maximal runs of bytes for which ``inside`` holds (default: not white space), and
        each text's first word as n + 1 offsets."""
        ok = (~SPACE if inside is None else inside)[self.data if data is None else data]
        n = len(ok)
        first = np.zeros(n + 1, bool)
        first[self.cuts] = True
        before = np.zeros(n + 1, bool)
        before[1:] = ok
        start = ok & ~(before[:-1] & ~first[:-1])
        after = np.zeros(n, bool)
        after[:-1] = ok[1:]
        stop = ok & ~(after & ~first[1:])
        s, e = np.flatnonzero(start), np.flatnonzero(stop) + 1
        return s, e, np.searchsorted(s, self.cuts)

    def code_points(self) -> np.ndarray:
        """c with c[j] the number of characters that begin before byte j."""
        out = np.zeros(len(self.data) + 1, np.int64)
        np.cumsum((self.data & 0xC0) != 0x80, out=out[1:])
        return out


def texts_of(column: pa.Array | pa.ChunkedArray, limit: int = SLICE_BYTES) -> Iterator[Texts]:
    """Slices of whole texts with at most ``limit`` bytes, or one longer text."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if len(column) == 0:
        return
    if pa.types.is_null(column.type):
        column = column.cast(pa.string())
    column = column.fill_null("")
    kind = np.int64 if pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type) else np.int32
    _, offs, data = column.buffers()
    cuts = np.frombuffer(offs, kind, len(column) + 1, column.offset * np.dtype(kind).itemsize).astype(np.int64)
    data = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    i = 0
    while i < len(column):
        j = max(i + 1, int(np.searchsorted(cuts, cuts[i] + limit, "right")) - 1)
        yield Texts(data[cuts[i] : cuts[j]], cuts[i : j + 1] - cuts[i], i)
        i = j


def per_text(values: np.ndarray, at: np.ndarray, ufunc=np.add, empty=0) -> np.ndarray:
    """ufunc over values[at[i]:at[i+1]] for each text, ``empty`` where there is none."""
    out = np.full(len(at) - 1, empty, dtype=np.result_type(values.dtype, type(empty)) if values.dtype.kind != "u" else values.dtype)
    full = np.flatnonzero(at[1:] > at[:-1])
    if len(full):
        out[full] = ufunc.reduceat(values, at[full])
    return out
