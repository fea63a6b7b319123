"""Words of Arrow string columns as NumPy arrays: spans, 64-bit hashes and hashes of word runs.

A word is a maximal run of bytes other than 0x20 and 0x09-0x0D. All hashing is by prefix sums of a polynomial
modulo 2**64 followed by a mixing step, so a block of text costs a few vector operations per byte and no loop.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

BLOCK_BYTES = 1 << 20
HASH_BYTES = 1 << 18  # text hashed at once; bounds the tables of powers
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_P, _Q = np.uint64(0x9E6C63D0876A9A47), np.uint64(0xD1342543DE82EF95)
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def mix(x: np.ndarray) -> np.ndarray:
    """Bijective scrambling of 64-bit integers."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _pow(base: np.uint64, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers 0..n of an odd base and of its inverse modulo 2**64."""
    key = int(base)
    have = _powers.get(key)
    if have is None or len(have[0]) <= n:
        size = max(1 << 16, 1 << (n + 1).bit_length())
        inv = pow(key, -1, 1 << 64)
        made = []
        for b in (key, inv):
            a = np.full(size, b, np.uint64)
            a[0] = 1
            made.append(np.cumprod(a))
        have = (made[0], made[1])
        if size <= 1 << 20:
            _powers[key] = have
    return have


def run_hash(h: np.ndarray, k: int) -> np.ndarray:
    """Hash of each run of k consecutive values: len(h) - k + 1 results."""
    n = len(h) - k + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    out = np.empty(n, np.uint64)
    step = 1 << 17
    up, down = _pow(_Q, min(len(h), step + k) + 1)
    for a in range(0, n, step):
        part = h[a : min(a + step, n) + k - 1]
        c = np.zeros(len(part) + 1, np.uint64)
        np.cumsum(part * up[: len(part)], out=c[1:])
        m = len(part) - k + 1
        out[a : a + m] = mix((c[k:] - c[:m]) * down[:m])
    return out


class Words:
    """Words of a block of rows: start, end (byte positions), row, and where each row's words begin."""

    def __init__(self, col: pa.Array, lower: bool = False, hashes: bool = True):
        data, off = text_bytes(col)
        self.data, self.offsets, self.rows = data, off, len(off) - 1
        if lower:
            data = _LOWER[data]
        blank = _SPACE[data]
        edge = np.zeros(len(data) + 1, bool)
        edge[off] = True
        before = np.empty(len(data), bool)
        before[:1], before[1:] = True, blank[:-1]
        after = np.empty(len(data), bool)
        after[-1:], after[:-1] = True, blank[1:]
        self.start = np.flatnonzero(~blank & (before | edge[:-1]))
        self.end = np.flatnonzero(~blank & (after | edge[1:])) + 1
        self.bounds = np.searchsorted(self.start, off)
        self.counts = np.diff(self.bounds)
        self.row = np.repeat(np.arange(self.rows), self.counts)
        self.hash = self._hash(data) if hashes else None

    def _hash(self, data: np.ndarray) -> np.ndarray:
        out = np.empty(len(self.start), np.uint64)
        i, n = 0, len(out)
        while i < n:
            base = self.start[i]
            j = max(i + 1, int(np.searchsorted(self.end, base + HASH_BYTES, "right")))
            part = data[base : self.end[j - 1]]
            up, down = _pow(_P, len(part) + 1)
            c = np.zeros(len(part) + 1, np.uint64)
            np.cumsum((part.astype(np.uint64) + np.uint64(1)) * up[: len(part)], out=c[1:])
            s, e = self.start[i:j] - base, self.end[i:j] - base
            out[i:j] = mix((c[e] - c[s]) * down[s] + (e - s).astype(np.uint64) * _Q)
            i = j
        return out

    def inside(self, k: int) -> np.ndarray:
        """For each run of k words of the block: does it lie in one row?"""
        if len(self.row) < k:
            return np.empty(0, bool)
        return self.row[: len(self.row) - k + 1] == self.row[k - 1 :]


def text_bytes(col: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of a string column (null: empty) and the rows' offsets."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    col = pc.fill_null(col.cast(pa.large_string()), "")
    off = np.frombuffer(col.buffers()[1], np.int64)[col.offset : col.offset + len(col) + 1]
    raw = col.buffers()[2]
    data = np.frombuffer(raw, np.uint8)[off[0] : off[-1]] if raw is not None and len(off) > 1 else np.empty(0, np.uint8)
    return data, (off - off[0]) if len(off) else np.zeros(1, np.int64)


def blocks(batches: Iterator[pa.RecordBatch], text: str, limit: int = BLOCK_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut batches into runs of rows of about `limit` bytes of text; one longer row stands alone."""
    for b in batches:
        i = b.schema.get_field_index(text)
        size = pc.fill_null(pc.binary_length(b.column(i)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        end = np.cumsum(size)
        a = 0
        while a < b.num_rows:
            z = int(np.searchsorted(end, (end[a - 1] if a else 0) + limit, "right"))
            z = max(z, a + 1)
            yield b.slice(a, z - a)
            a = z
