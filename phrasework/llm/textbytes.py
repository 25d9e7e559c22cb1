"""Vectorised work on the UTF-8 bytes of Arrow string columns.

A batch of texts stays one byte buffer with offsets. Words are maximal runs of bytes other
than 0x20 and 0x09-0x0D, which in UTF-8 is the same as splitting the decoded text.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U64 = np.uint64
#: Bytes of text that a kernel holds as numpy arrays at a time (one longer text stands alone).
SLICE_BYTES = 1 << 20

IS_SPACE = np.zeros(256, bool)
IS_SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
TO_SPACE = np.where(IS_SPACE, 0x20, np.arange(256)).astype(np.uint8)
LOW_BYTES = np.array([(1 << (8 * k)) - 1 for k in range(8)] + [(1 << 64) - 1], dtype=U64)

# The five primes of XXH64.
PRIME_1 = U64(11400714785074694791)
PRIME_2 = U64(14029467366897019727)
PRIME_3 = U64(1609587929392839161)
PRIME_4 = U64(9650029242287828579)
PRIME_5 = U64(2870177450012600261)


def utf8(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and offsets (one more than there are rows) of a string column; null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = column.fill_null("")
    column = column.cast(pa.large_binary())
    _, offsets, data = column.buffers()
    n = len(column)
    at = np.frombuffer(offsets, np.int64)[column.offset : column.offset + n + 1] if n else np.zeros(1, np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8)
    return raw[at[0] : at[-1]], at - at[0]


def slices(batch: pa.RecordBatch, text: str | int = "text", limit: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut a batch into row ranges of about ``limit`` bytes of text, one row at least."""
    if not batch.num_rows:
        return
    _, at = utf8(batch.column(text))
    first = 0
    while first < batch.num_rows:
        end = max(first + 1, int(np.searchsorted(at, at[first] + limit, "right")) - 1)
        yield batch.slice(first, end - first)
        first = end


class Words:
    """Words of a batch: bytes with one space between words, their spans, and row boundaries."""

    def __init__(self, raw: np.ndarray, at: np.ndarray, lower: bool = False):
        space = IS_SPACE[raw]
        first = np.zeros(len(raw) + 1, bool)
        first[at] = True  # a row starts here
        opens = ~space
        opens[1:] &= space[:-1] | first[1:-1]
        starts = np.flatnonzero(opens)
        closes = ~space
        closes[:-1] &= space[1:] | first[1:-1]
        ends = np.flatnonzero(closes) + 1
        #: ``rows[i]:rows[i + 1]`` are the words of row i.
        self.rows = np.searchsorted(starts, at)
        keep = ~space
        keep[1:] |= ~space[:-1] & ~first[1:-1]
        if len(keep):
            keep[0] = not space[0]
        moved = np.zeros(len(raw) + 1, np.int32 if len(raw) < 1 << 31 else np.int64)
        np.cumsum(keep, out=moved[1:], dtype=moved.dtype)
        text = raw[keep]
        self.text = (LOWER[TO_SPACE] if lower else TO_SPACE)[text]
        #: Where the words stand in ``text``, and where they begin in the bytes given.
        self.starts, self.ends, self.given = moved[starts].astype(np.int64), moved[ends].astype(np.int64), starts

    def __len__(self) -> int:
        return len(self.starts)

    @property
    def counts(self) -> np.ndarray:
        return np.diff(self.rows)

    def part(self, first: int, last: int) -> "Words":
        """Words ``first`` to ``last`` as one row of their own."""
        out = Words.__new__(Words)
        base, end = (self.starts[first], self.ends[last - 1]) if last > first else (0, 0)
        out.text, out.starts, out.ends = self.text[base:end], self.starts[first:last] - base, self.ends[first:last] - base
        out.rows, out.given = np.array([0, last - first]), self.given[first:last]
        return out

    def padded(self) -> np.ndarray:
        """All eight-byte groups of the text, one starting at each byte."""
        buffer = np.zeros(len(self.text) + 8, np.uint8)
        buffer[: len(self.text)] = self.text
        return np.ndarray((len(self.text) + 1,), dtype="<u8", buffer=buffer.data, strides=(1,))

    def row_bytes(self, i: int) -> bytes:
        """The words of row i joined by one space."""
        a, b = self.rows[i], self.rows[i + 1]
        return self.text[self.starts[a] : self.ends[b - 1]].tobytes() if b > a else b""


def mix(x: np.ndarray) -> np.ndarray:
    """A full 64-bit avalanche."""
    x = x ^ (x >> U64(33))
    x *= PRIME_2
    x ^= x >> U64(29)
    x *= PRIME_3
    x ^= x >> U64(32)
    return x


def span_hashes(groups: np.ndarray, starts: np.ndarray, ends: np.ndarray, seed: int) -> np.ndarray:
    """A 64-bit hash of each byte span; not a published one, used inside this package only."""
    size = ends - starts
    out = mix(size.astype(U64) + U64(seed * int(PRIME_1) & ((1 << 64) - 1)))
    live = np.arange(len(starts))
    at, left = starts.copy(), size.copy()
    while len(live):
        lane = groups[at] & LOW_BYTES[np.minimum(left, 8)]
        out[live] = mix(out[live] * PRIME_5 + lane)
        more = left > 8
        live, at, left = live[more], at[more] + 8, left[more] - 8
    return out


def _rotate(x: np.ndarray, k: int) -> np.ndarray:
    return (x << U64(k)) | (x >> U64(64 - k))


def _round(acc: np.ndarray, lane: np.ndarray) -> np.ndarray:
    return _rotate(acc + lane * PRIME_2, 31) * PRIME_1


def xxh64(groups: np.ndarray, starts: np.ndarray, ends: np.ndarray, seed: int = 42) -> np.ndarray:
    """XXH64 of each byte span, computed side by side for all spans."""
    n, size, s = len(starts), ends - starts, U64(seed)
    with np.errstate(over="ignore"):
        first = (s + PRIME_1 + PRIME_2, s + PRIME_2, s, s - PRIME_1)
        acc = np.full(n, s + PRIME_5)
    at = starts.copy()
    wide = np.flatnonzero(size >= 32)
    if len(wide):
        lanes = [np.full(len(wide), v) for v in first]
        live, p, left = np.arange(len(wide)), at[wide].copy(), size[wide].copy()
        while len(live):
            for k in range(4):
                lanes[k][live] = _round(lanes[k][live], groups[p + 8 * k])
            more = left >= 64
            live, p, left = live[more], p[more] + 32, left[more] - 32
        got = sum((_rotate(x, k) for x, k in zip(lanes[1:], (7, 12, 18))), _rotate(lanes[0], 1))
        for x in lanes:
            got = (got ^ _round(np.zeros_like(x), x)) * PRIME_1 + PRIME_4
        acc[wide] = got
        at[wide] += size[wide] & ~31
    acc += size.astype(U64)
    left = ends - at
    live = np.flatnonzero(left >= 8)
    while len(live):
        lane = _round(np.zeros(len(live), U64), groups[at[live]])
        acc[live] = _rotate(acc[live] ^ lane, 27) * PRIME_1 + PRIME_4
        at[live] += 8
        live = live[ends[live] - at[live] >= 8]
    live = np.flatnonzero(ends - at >= 4)
    if len(live):
        acc[live] = _rotate(acc[live] ^ ((groups[at[live]] & U64(0xFFFFFFFF)) * PRIME_1), 23) * PRIME_2 + PRIME_3
        at[live] += 4
    live = np.flatnonzero(ends > at)
    while len(live):
        acc[live] = _rotate(acc[live] ^ ((groups[at[live]] & U64(0xFF)) * PRIME_5), 11) * PRIME_1
        at[live] += 1
        live = live[ends[live] > at[live]]
    acc ^= acc >> U64(33)
    acc *= PRIME_2
    acc ^= acc >> U64(29)
    acc *= PRIME_3
    acc ^= acc >> U64(32)
    return acc
