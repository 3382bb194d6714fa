"""Array kernels that run inside executor tasks: everything works on the UTF-8 bytes of an Arrow batch."""

from __future__ import annotations

import ctypes

import numpy as np
import pyarrow as pa

from . import common

common.by_value(__name__)

U64 = np.uint64
_BYTE_BASE = 0x9E3779B97F4A7C15 | 1
_WORD_BASE = 0xD6E8FEB86659FD93 | 1
_OTHER_BASE = 0xA0761D6478BD642F | 1
#: Documents are handled in slices of about this many bytes; one longer document makes its own slice.
SLICE_BYTES = 2_000_000


def hand_back() -> None:
    """Gives the memory that is free in this process back to the system; without glibc only Arrow's."""
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
    if trim is not None:
        trim(0)


def tidy(kernel):
    """The kernel, handing back free memory at the end of each task: idle workers hold what they have."""
    after = hand_back

    def run(batches):
        try:
            yield from kernel(batches)
        finally:
            after()

    return run


def string_views(arr: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """(bytes, offsets) of a string column; nulls become empty."""
    if isinstance(arr, pa.ChunkedArray):
        arr = arr.combine_chunks()
    if arr.null_count:
        arr = arr.fill_null("")
    wide = pa.types.is_large_string(arr.type)
    bufs = arr.buffers()
    n = len(arr)
    if n == 0 or bufs[1] is None:
        return np.zeros(0, np.uint8), np.zeros(n + 1, np.int64)
    offs = np.frombuffer(bufs[1], np.int64 if wide else np.int32)[arr.offset : arr.offset + n + 1].astype(np.int64)
    data = np.frombuffer(bufs[2], np.uint8) if bufs[2] is not None else np.zeros(0, np.uint8)
    return data[offs[0] : offs[-1]], offs - offs[0]


def slices(offsets: np.ndarray, limit: int = SLICE_BYTES):
    """Row ranges of about `limit` bytes."""
    n, at = len(offsets) - 1, 0
    while at < n:
        end = int(np.searchsorted(offsets, offsets[at] + limit, side="right")) - 1
        end = min(n, max(end, at + 1))
        yield at, end
        at = end


def mixed(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (shift, multiply, shift)."""
    x = x ^ (x >> U64(30))
    x = x * U64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U64(27))
    x = x * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


def _inverse(base: int) -> int:
    return pow(base, -1, 1 << 64)


def powers(base: int, n: int) -> np.ndarray:
    out = np.full(max(n, 1), U64(base), U64)
    out[0] = 1
    return np.cumprod(out, dtype=U64)


class PowerTable:
    """Powers of a base and of its inverse, grown on demand."""

    def __init__(self, base: int):
        self.base, self.up, self.down = base, powers(base, 1024), powers(_inverse(base), 1024)

    def upto(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(self.up) < n:
            size = 1 << int(n - 1).bit_length()
            self.up, self.down = powers(self.base, size), powers(_inverse(self.base), size)
        return self.up[:n], self.down[:n]


class Prefix:
    """Polynomial prefix sums of a sequence; gives the hash of any range."""

    def __init__(self, values: np.ndarray, powers_of: PowerTable):
        up, self.down = powers_of.upto(len(values) + 1)
        self.sums = np.zeros(len(values) + 1, U64)
        np.cumsum(values * up[: len(values)], out=self.sums[1:])

    def of(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        return mixed((self.sums[ends] - self.sums[starts]) * self.down[starts] + (ends - starts).astype(U64))


SPACE = np.zeros(256, bool)
SPACE[[32, *range(9, 14)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


class Words:
    """Words of the documents of one slice: byte ranges, hashes and the first word of each document."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, tables: dict, lower: bool = False):
        base = offsets[0]
        self.data = data[base : offsets[-1]]
        if lower:
            self.data = LOWER[self.data]
        n = len(self.data)
        inside = ~SPACE[self.data]
        edge = np.zeros(n + 1, bool)
        edge[offsets - base] = True
        before = np.empty(n, bool)
        after = np.empty(n, bool)
        if n:
            before[0], after[-1] = False, False
            before[1:], after[:-1] = inside[:-1], inside[1:]
        self.start = np.flatnonzero(inside & (~before | edge[:n]))
        self.end = np.flatnonzero(inside & (~after | edge[1:])) + 1
        self.first = np.searchsorted(self.start, offsets - base)
        self.hash = Prefix(self.data.astype(U64) + U64(1), tables.setdefault("byte", PowerTable(_BYTE_BASE))).of(self.start, self.end)

    def __len__(self) -> int:
        return len(self.start)


def gram_hashes(word_hash: np.ndarray, k: int, base: int = _WORD_BASE) -> np.ndarray:
    """Hash of the k words from each position on; positions with fewer than k words left are not returned."""
    n = len(word_hash) - k + 1
    if n <= 0:
        return np.zeros(0, U64)
    acc = np.zeros(n, U64)
    for j in range(k):
        acc = acc * U64(base) + word_hash[j : j + n]
    return mixed(acc)


def sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    """Minimum over each window of `width`, by doubling."""
    if len(x) < width:
        return x[:0]
    have, out = 1, x
    while have * 2 <= width:
        out = np.minimum(out[:-have], out[have:])
        have *= 2
    if have < width:
        gap = width - have
        out = np.minimum(out[:-gap], out[gap:])
    return out


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


WORD_BASE, OTHER_BASE = _WORD_BASE, _OTHER_BASE
