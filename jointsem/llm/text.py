"""Flat numpy views of Arrow text columns, shared by the operators of this package.

A slice of documents is held as one byte array, and words, hashes and windows
are computed over the whole slice at once.  Slices are bounded in bytes, so the
memory of a task does not depend on the number of rows of an Arrow batch; one
document longer than the bound makes a slice of its own.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

SLICE_BYTES = 1 << 19
_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_BASE_INV = np.uint64(pow(0x9E3779B97F4A7C15 | 1, -1, 1 << 64))
_BYTE_CODE = np.random.default_rng(20240229).integers(1, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_powers = np.ones(1, np.uint64)
_inverse = np.ones(1, np.uint64)


def space_table() -> np.ndarray:
    """True for the bytes of words `[^\\x20\\x09-\\x0D]+`."""
    t = np.ones(256, bool)
    t[[0x20, *range(0x09, 0x0E)]] = False
    return t


def alnum_table() -> np.ndarray:
    """True for the bytes of words of lower-cased letters, digits and non-ASCII characters."""
    t = np.zeros(256, bool)
    t[0x30:0x3A] = t[0x61:0x7B] = t[0x80:] = True
    return t


LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 32


def mix(h: np.ndarray) -> np.ndarray:
    """A bijective 64-bit finaliser, so that every bit of a hash is usable."""
    h = h ^ (h >> np.uint64(30))
    h *= np.uint64(0xBF58476D1CE4E5B9)
    h ^= h >> np.uint64(27)
    h *= np.uint64(0x94D049BB133111EB)
    h ^= h >> np.uint64(31)
    return h


def _grow(n: int) -> None:
    global _powers, _inverse
    if len(_powers) < n:
        n = max(n, 1 << 16)
        one = np.ones(1, np.uint64)
        _powers = np.cumprod(np.concatenate([one, np.full(n, _BASE)]))
        _inverse = np.cumprod(np.concatenate([one, np.full(n, _BASE_INV)]))


class Prefix:
    """Prefix polynomial hashes of an array of 64-bit codes; span(a, b) hashes any span in O(1)."""

    def __init__(self, codes: np.ndarray):
        _grow(len(codes) + 1)
        self.sums = np.zeros(len(codes) + 1, np.uint64)
        np.cumsum(codes * _powers[: len(codes)], out=self.sums[1:])

    @classmethod
    def of_bytes(cls, data: np.ndarray) -> Prefix:
        return cls(_BYTE_CODE[data])

    def span(self, start: np.ndarray, stop: np.ndarray) -> np.ndarray:
        return (self.sums[stop] - self.sums[start]) * _inverse[start]

    def grams(self, k: int) -> np.ndarray:
        """Hashes of all spans of k codes, in order."""
        n = len(self.sums) - k
        return (self.sums[k:] - self.sums[:n]) * _inverse[:n] if n > 0 else np.zeros(0, np.uint64)


def binaries(column: pa.Array) -> list[bytes]:
    """The UTF-8 bytes of each text; null is empty."""
    return [b"" if x is None else x for x in column.cast(pa.binary()).to_pylist()]


def slices(batches: Iterator[pa.RecordBatch], text: str = "text", limit: int = SLICE_BYTES) -> Iterator[tuple[pa.RecordBatch, list[bytes]]]:
    """Rows of bounded bytes, each with the texts as bytes."""
    for batch in batches:
        column = batch.column(batch.schema.get_field_index(text))
        sizes = _lengths(column)
        start = 0
        ends = np.cumsum(sizes)
        while start < len(sizes):
            base = ends[start - 1] if start else 0
            stop = max(start + 1, int(np.searchsorted(ends, base + limit, "right")))
            part = batch.slice(start, stop - start)
            yield part, binaries(part.column(part.schema.get_field_index(text)))
            start = stop


def _lengths(column: pa.Array) -> np.ndarray:
    import pyarrow.compute as pc

    return pc.binary_length(column.cast(pa.binary())).fill_null(0).to_numpy(zero_copy_only=False).astype(np.int64)


class Words:
    """The words of a slice: byte spans, the document of each, and the first word of each document.

    data holds the texts with one space after each, so that no word spans two texts.
    """

    def __init__(self, texts: list[bytes], table: np.ndarray, lower: bool = False):
        raw = b" ".join([b"", *texts, b""])
        self.data = np.frombuffer(raw, np.uint8)
        if lower:
            self.data = LOWER[self.data]
        lengths = np.fromiter(map(len, texts), np.int64, len(texts))
        self.offsets = np.concatenate([np.ones(1, np.int64), 1 + np.cumsum(lengths + 1)])
        inside = table[self.data]
        edges = np.flatnonzero(inside[1:] != inside[:-1]) + 1
        self.starts, self.ends = edges[::2], edges[1::2]
        self.first = np.searchsorted(self.starts, self.offsets)
        self.doc = np.repeat(np.arange(len(texts)), np.diff(self.first))

    def __len__(self) -> int:
        return len(self.starts)

    def hashes(self) -> np.ndarray:
        h = Prefix.of_bytes(self.data).span(self.starts, self.ends)
        return mix(h + (self.ends - self.starts).astype(np.uint64))


def sliding_min(values: np.ndarray, width: int) -> np.ndarray:
    """Minimum of each window of `width` values, by doubling."""
    if len(values) < width:
        return values[:0]
    span = 1
    while 2 * span <= width:
        values = np.minimum(values[:-span], values[span:])
        span *= 2
    rest = width - span
    return np.minimum(values[: len(values) - rest], values[rest:]) if rest else values


def gather(flat: np.ndarray, start: np.ndarray, size: np.ndarray, block: int = 1 << 20) -> np.ndarray:
    """flat[start[i] : start[i] + size[i]] for all i, joined; the index arrays it needs are bounded."""
    ends = np.cumsum(size)
    out = np.empty(int(ends[-1]) if len(ends) else 0, flat.dtype)
    i = 0
    while i < len(ends):
        base = int(ends[i - 1]) if i else 0
        j = max(i + 1, int(np.searchsorted(ends, base + block, "right")))
        n = size[i:j]
        out[base : int(ends[j - 1])] = flat[np.repeat(start[i:j] - (ends[i:j] - n - base), n) + np.arange(int(ends[j - 1]) - base)]
        i = j
    return out


def starts_of_runs(*keys: np.ndarray) -> np.ndarray:
    """True where any key differs from the row before."""
    new = np.ones(len(keys[0]), bool)
    if len(new) > 1:
        new[1:] = False
        for k in keys:
            new[1:] |= k[1:] != k[:-1]
    return new


def merged(starts: np.ndarray, stops: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Sorted, disjoint, non-touching spans with the same union."""
    if not len(starts):
        return starts, stops
    order = np.argsort(starts, kind="stable")
    a, b = starts[order], np.maximum.accumulate(stops[order])
    new = np.ones(len(a), bool)
    new[1:] = a[1:] > b[:-1]
    heads = np.flatnonzero(new)
    return a[heads], b[np.append(heads[1:] - 1, len(b) - 1)]
