"""Vectorised hashing over the byte buffers of Arrow string columns.

A batch's texts lie end to end in one byte array. Words are keyed by mixing their bytes
(16 at once; longer words by xxh3), so unequal words share a 64-bit key by chance only.

Prefix sums of a polynomial over 64-bit wrap-around integers give a hash of any byte
range in O(1). Some unequal byte strings always share such a hash (long Thue-Morse
words, for one), so it only picks places, as anchors and chunk borders; what is taken as
equal is compared by :func:`range_keys` or by word keys. Nulls count as empty texts.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash

U = np.uint64
_B = 0x9E3779B97F4A7C15 | 1
_B_INV = pow(_B, -1, 1 << 64)
SLICE_BYTES = 1 << 20


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on uint64."""
    x = x.copy()
    x ^= x >> U(30)
    x *= U(0xBF58476D1CE4E5B9)
    x ^= x >> U(27)
    x *= U(0x94D049BB133111EB)
    x ^= x >> U(31)
    return x


_BYTE_KEYS = mix(np.arange(1, 257, dtype=np.uint64) * U(0xD6E8FEB86659FD93))
_powers = {"b": np.ones(1, np.uint64), "inv": np.ones(1, np.uint64)}


def powers(n: int, which: str = "b") -> np.ndarray:
    """The first n powers of the base (or of its inverse) modulo 2**64."""
    have = _powers[which]
    if len(have) < n:
        step = _B if which == "b" else _B_INV
        while len(have) < n:
            factor = U(pow(step, len(have), 1 << 64))
            have = np.concatenate([have, have * factor])
        _powers[which] = have
    return have[:n]


@dataclass
class Buffer:
    """Texts as one byte array with ``len(offs) - 1`` of them; ``first`` is the index of the first in its batch."""

    data: np.ndarray
    offs: np.ndarray
    first: int

    def prefix(self, table: np.ndarray = _BYTE_KEYS) -> np.ndarray:
        out = np.zeros(len(self.data) + 1, np.uint64)
        np.cumsum(table[self.data] * powers(len(self.data)), out=out[1:])
        return out

    def text(self, i: int) -> bytes:
        return self.data[self.offs[i] : self.offs[i + 1]].tobytes()


def range_hash(prefix: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """Place-picking hash of the byte ranges [start, end), the same for equal bytes anywhere."""
    inv = powers(len(prefix), "inv")
    h = (prefix[end] - prefix[start]) * inv[start]
    return mix(h + (end - start).astype(np.uint64) * U(0xA24BAED4963EE407))


def range_keys(symbols: np.ndarray, start: np.ndarray, end: np.ndarray, seed: np.ndarray) -> np.ndarray:
    """xxh3 keys of the ranges [start, end) of a contiguous array, each under its own seed."""
    if not len(start):
        return np.zeros(0, np.uint64)
    view, size = memoryview(np.ascontiguousarray(symbols)).cast("B"), symbols.itemsize
    ends = (end * size).tolist()
    keys = [xxhash.xxh3_64_intdigest(view[a:b], s) for a, b, s in zip((start * size).tolist(), ends, seed.tolist())]
    return np.array(keys, np.uint64)


def string_buffers(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string or binary column; nulls become empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        column = pc.fill_null(column, b"" if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else "")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    kind = np.int64 if wide else np.int32
    _, offsets, data = column.buffers()
    if len(column) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offs = np.frombuffer(offsets, kind)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offs[0] : offs[-1]], offs - offs[0]


def slices(column: pa.Array, limit: int = SLICE_BYTES) -> Iterator[Buffer]:
    """The column in runs of whole texts of about ``limit`` bytes (a longer text is a run of its own)."""
    data, offs = string_buffers(column)
    n, i = len(offs) - 1, 0
    while i < n:
        j = int(np.searchsorted(offs, offs[i] + limit, "right")) - 1
        j = min(n, max(j, i + 1))
        yield Buffer(data[offs[i] : offs[j]], offs[i : j + 1] - offs[i], i)
        i = j


_WORD = np.ones(256, bool)
_WORD[[9, 10, 11, 12, 13, 32]] = False
FOLD_ASCII = np.arange(256, dtype=np.uint8)
FOLD_ASCII[65:91] += 32


@dataclass
class Words:
    """Words ``[^\\x20\\x09-\\x0D]+`` of a buffer: byte ranges, hashes, and each text's range of words."""

    start: np.ndarray
    end: np.ndarray
    key: np.ndarray
    offs: np.ndarray


def words(buf: Buffer, lower: bool = False) -> Words:
    data = FOLD_ASCII[buf.data] if lower else buf.data
    n = len(data)
    if n == 0:
        z = np.zeros(0, np.int64)
        return Words(z, z, np.zeros(0, np.uint64), np.zeros(len(buf.offs), np.int64))
    inside = _WORD[data]
    head = np.zeros(n, bool)
    head[buf.offs[:-1][buf.offs[:-1] < n]] = True
    before = np.empty(n, bool)
    before[0], before[1:] = False, inside[:-1]
    start = np.flatnonzero(inside & (~before | head))
    tail = np.zeros(n, bool)
    tail[buf.offs[1:][buf.offs[1:] > 0] - 1] = True
    after = np.empty(n, bool)
    after[-1], after[:-1] = False, inside[1:]
    end = np.flatnonzero(inside & (~after | tail)) + 1
    return Words(start, end, word_keys(data, start, end), np.searchsorted(start, buf.offs, "left"))


_LOW_BYTES = np.array([(1 << (8 * k)) - 1 for k in range(9)], np.uint64)


def word_keys(data: np.ndarray, start: np.ndarray, end: np.ndarray) -> np.ndarray:
    """A key of each byte range [start, end), of any length; the ranges are short as a rule."""
    eight = np.ndarray(len(data) + 9, "<u8", np.concatenate([data, np.zeros(16, np.uint8)]), strides=(1,)).copy()
    size = end - start
    low = eight[start] & _LOW_BYTES[np.minimum(size, 8)]
    high = eight[np.minimum(start + 8, len(data))] & _LOW_BYTES[np.clip(size - 8, 0, 8)]
    key = mix(mix(mix(low + U(0xA24BAED4963EE407)) ^ high) + size.astype(np.uint64) * U(_B))
    long = np.flatnonzero(size > 16)
    key[long] = range_keys(data, start[long], end[long], np.zeros(len(long), np.int64))
    return key


def gram_keys(key: np.ndarray, width: int) -> np.ndarray:
    """Hash of each run of ``width`` consecutive keys (of length len(key) - width + 1)."""
    n = len(key) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.zeros(n, np.uint64)
    for j in range(width):
        out *= U(_B)
        out += key[j : j + n]
    return mix(out)


def sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each run of ``width`` entries, by doubling."""
    span, out = 1, x
    while span * 2 <= width:
        out = np.minimum(out[:-span], out[span:])
        span *= 2
    if span < width:
        rest = width - span
        out = np.minimum(out[: len(out) - rest], out[rest:])
    return out


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


def ragged_arange(start: np.ndarray, count: np.ndarray) -> np.ndarray:
    """start[0], start[0]+1, ... (count[0] of them), start[1], ..."""
    total = int(count.sum())
    if total == 0:
        return np.zeros(0, np.int64)
    ends = np.cumsum(count)
    out = np.arange(total, dtype=np.int64)
    return out + np.repeat(start - (ends - count), count)
