"""Rows of 64-bit keys moved as compressed pieces: a task sorts what it has, cuts it by the leading bits of a key, and each piece is
one row of a shuffle. A bucket's pieces are merged in memory, so there must be as many buckets as the rows ask for; equal
keys come once from each piece, so a frequent key makes no bucket large."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Schema of what moves: the bucket, and the piece.
PIECES = "b long, piece binary"


def pack(*columns: np.ndarray) -> bytes:
    """Columns of integers (floats by their bits) as one piece: byte by byte of all values, compressed."""
    head, body = [len(columns)], []
    for c in columns:
        c = np.ascontiguousarray(c)
        c = c.view(np.uint64) if c.dtype.itemsize == 8 else c.astype(np.uint64)
        wide = (int(c.max()).bit_length() + 7) // 8 if len(c) else 0
        head += [len(c), wide]
        body.append(np.ascontiguousarray(c.view(np.uint8).reshape(-1, 8)[:, :wide].T).tobytes())
    return squeeze(np.array(head, "<i8").tobytes() + b"".join(body))


def squeeze(raw: bytes) -> bytes:
    return len(raw).to_bytes(8, "little") + pa.compress(raw, codec="zstd", asbytes=True)


def unsqueeze(piece: bytes) -> bytes:
    return pa.decompress(piece[8:], decompressed_size=int.from_bytes(piece[:8], "little"), codec="zstd", asbytes=True)


def unpack(piece: bytes) -> list[np.ndarray]:
    raw = unsqueeze(piece)
    m = int.from_bytes(raw[:8], "little")
    head = np.frombuffer(raw, "<i8", 2 * m, 8).reshape(m, 2)
    at, out = 8 + 16 * m, []
    for n, wide in head.tolist():
        c = np.zeros((n, 8), np.uint8)
        c[:, :wide] = np.frombuffer(raw, np.uint8, n * wide, at).reshape(wide, n).T
        out.append(c.reshape(-1).view(np.uint64))
        at += n * wide
    return out


def steps(c: np.ndarray) -> np.ndarray:
    """Ascending values as their differences, which are shorter; np.cumsum gives them back."""
    return np.diff(c.astype(np.uint64), prepend=np.uint64(0))


def signed(v: np.ndarray) -> np.ndarray:
    """Signed integers with the sign in the lowest bit, so that small ones are short."""
    v = v.astype(np.int64)
    return ((v << 1) ^ (v >> 63)).view(np.uint64)


def unsigned(z: np.ndarray) -> np.ndarray:
    return (z >> np.uint64(1)).view(np.int64) ^ -(z & np.uint64(1)).view(np.int64)


def runs_of(c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Where runs of equal values begin, and their lengths."""
    if not len(c):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    head = np.flatnonzero(np.concatenate([[True], c[1:] != c[:-1]]))
    return head, np.diff(np.append(head, len(c)))


def bucket(keys: np.ndarray, log: int) -> np.ndarray:
    """The leading ``log`` bits."""
    return (keys >> np.uint64(64 - log)).astype(np.uint16 if log <= 16 else np.uint32) if log else np.zeros(len(keys), np.uint16)


def cut(buckets: np.ndarray) -> Iterator[tuple[int, slice]]:
    """Each bucket of ascending ones, and where it lies."""
    head, n = runs_of(buckets)
    for a, m in zip(head.tolist(), n.tolist()):
        yield int(buckets[a]), slice(a, a + m)


def rows(pieces: list[tuple[int, bytes]], *more: tuple[str, pa.Array]) -> pa.RecordBatch:
    b, p = ([x[i] for x in pieces] for i in (0, 1))
    return pa.RecordBatch.from_arrays([pa.array(b, pa.int64()), pa.array(p, pa.binary()), *(c for _, c in more)], names=["b", "piece", *(n for n, _ in more)])


def pieces_of(t: pa.Table, column: str = "piece") -> Iterator[bytes]:
    for chunk in t.column(column).chunks:
        for p in chunk:
            yield p.as_py()
