"""Vectorised text primitives over Arrow string columns.

All functions work on the UTF-8 bytes of a whole batch at once.  A word is a
run of bytes outside ``space``; bytes from 0x80 up always belong to a word, so
no code point is ever cut.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

U = np.uint64
_rng = np.random.Generator(np.random.PCG64(20240229))
BYTE_KEY = _rng.integers(1, 2**63, 256, dtype=np.uint64) | U(1)
BASE = U(0x9E3779B97F4A7C15 | 1)
BASE_INV = U(pow(int(BASE), -1, 2**64))
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
WHITE = np.zeros(256, bool)
WHITE[[32, 9, 10, 11, 12, 13]] = True
_pow: dict[str, np.ndarray] = {"base": np.ones(1, np.uint64), "inv": np.ones(1, np.uint64)}


def powers(which: str, n: int) -> np.ndarray:
    """First n powers of BASE or its inverse modulo 2**64."""
    if len(_pow[which]) < n:
        step = BASE if which == "base" else BASE_INV
        p = np.full(max(n, 1 << 20), step, np.uint64)
        p[0] = 1
        _pow[which] = np.multiply.accumulate(p)
    return _pow[which][:n]


def mix(h: np.ndarray) -> np.ndarray:
    """64-bit finaliser (two xor-shift-multiply rounds)."""
    h = h ^ (h >> U(32))
    h = h * U(0xD6E8FEB86659FD93)
    h = h ^ (h >> U(32))
    h = h * U(0xD6E8FEB86659FD93)
    return h ^ (h >> U(32))


def column_bytes(col) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and n+1 offsets of a string column; null counts as empty."""
    if isinstance(col, pa.ChunkedArray):
        col = col.combine_chunks()
    if len(col) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    if col.null_count:
        col = col.fill_null("")
    col = col.cast(pa.large_binary())
    _, offs, data = col.buffers()
    offs = np.frombuffer(offs, np.int64)[col.offset : col.offset + len(col) + 1]
    if data is None or offs[-1] == offs[0]:
        return np.zeros(0, np.uint8), offs - offs[0]
    return np.frombuffer(data, np.uint8)[offs[0] : offs[-1]], offs - offs[0]


def slices(batch: pa.RecordBatch, col: str, most: int = 4 << 20):
    """Parts of a batch with about ``most`` text bytes each (one row at least)."""
    if batch.num_rows == 0:
        return
    _, offs = column_bytes(batch.column(batch.schema.get_field_index(col)))
    i = 0
    while i < batch.num_rows:
        j = max(i + 1, int(np.searchsorted(offs, offs[i] + most, "right")) - 1)
        yield batch.slice(i, j - i)
        i = j


class Words:
    """Word starts, ends and 64-bit hashes of a batch of texts.

    ``of`` holds n+1 offsets: document d owns words of[d]:of[d+1].
    """

    def __init__(self, data: np.ndarray, offs: np.ndarray, lower: bool = True, space: np.ndarray = WHITE):
        self.offs = offs
        self.data = LOWER[data] if lower else data
        n = len(data)
        if not n:
            self.start = self.end = np.zeros(0, np.int64)
            self.hash = np.zeros(0, np.uint64)
            self.of = np.zeros(len(offs), np.int64)
            return
        word = ~space[data]
        st = word.copy()
        st[1:] &= ~word[:-1]
        en = word.copy()
        en[:-1] &= ~word[1:]
        cut = offs[1:-1]
        cut = cut[(cut > 0) & (cut < n)]
        st[cut] = word[cut]
        en[cut - 1] = word[cut - 1]
        self.start = np.flatnonzero(st)
        self.end = np.flatnonzero(en) + 1
        c = np.zeros(n + 1, np.uint64)
        np.cumsum(BYTE_KEY[self.data] * powers("base", n), out=c[1:])
        h = (c[self.end] - c[self.start]) * powers("inv", n)[self.start]
        self.hash = mix(h + (self.end - self.start).astype(np.uint64) * U(0xA24BAED4963EE407))
        self.of = np.searchsorted(self.start, offs)

    def text(self, i: int) -> bytes:
        return self.data[self.start[i] : self.end[i]].tobytes()

    def sequence_keys(self) -> tuple[np.ndarray, np.ndarray]:
        """Two 64-bit keys of each document's whole word sequence."""
        n = np.diff(self.of)
        k = np.arange(len(self.hash)) - np.repeat(self.of[:-1], n)
        p = powers("base", int(n.max(initial=0)) + 1)[k]
        out = []
        for salt in (U(0x632BE59BD9B4E019), U(0xE220A8397B1DCDAF)):
            v = mix(self.hash ^ salt) * p
            out.append(mix(segment_sum(v, self.of) + n.astype(np.uint64) * salt))
        return out[0], out[1]

    def shingles(self, size: int) -> tuple[np.ndarray, np.ndarray]:
        """Hashes of each document's word n-grams with offsets; a text of fewer
        words, but not none, has its whole sequence as the only one."""
        n = np.diff(self.of)
        m = np.where(n >= size, n - size + 1, np.minimum(n, 1))
        of = np.zeros(len(n) + 1, np.int64)
        np.cumsum(m, out=of[1:])
        if not len(self.hash):
            return np.zeros(0, np.uint64), of
        h = self.hash
        full = np.zeros(len(h), np.uint64)
        k = U(0xC2B2AE3D27D4EB4F)
        last = len(h) - size + 1
        if last > 0:
            acc = h[:last].copy()
            for j in range(1, size):
                acc = acc * k + h[j : j + last]
            full[:last] = mix(acc)
        short = (n > 0) & (n < size)
        if short.any():
            a, _ = self.sequence_keys()
            full[self.of[:-1][short]] = a[short]
        at = np.arange(of[-1]) - np.repeat(of[:-1], m) + np.repeat(self.of[:-1], m)
        return full[at], of


def segment_sum(v: np.ndarray, of: np.ndarray) -> np.ndarray:
    """Sums of v over the segments of[i]:of[i+1]; 0 where empty."""
    out = np.zeros(len(of) - 1, v.dtype)
    full = np.flatnonzero(np.diff(of))
    if len(full):
        out[full] = np.add.reduceat(v, of[:-1][full])
    return out
