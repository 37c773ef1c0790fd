"""Vectorised text kernels on Arrow string buffers (no Python object per word)."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

_rng = np.random.default_rng(20240607)
_ODD = np.uint64(0x9E3779B97F4A7C15)
#: One random 64-bit value per byte, and the same with A-Z read as a-z.
BYTE_VALUES = _rng.integers(1, 2**64, 256, dtype=np.uint64) | np.uint64(1)
FOLDED_VALUES = BYTE_VALUES.copy()
FOLDED_VALUES[65:91] = BYTE_VALUES[97:123]
#: Bytes that separate words: space and 0x09 to 0x0D.
IS_WORD = np.ones(256, dtype=bool)
IS_WORD[[0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D]] = False
_BASE = int(_rng.integers(1, 2**63)) * 2 + 1
_BASE_INVERSE = pow(_BASE, -1, 2**64)
_SEQUENCE_BASES = [int(_rng.integers(1, 2**62)) * 4 + 1 for _ in range(2)]
_powers: dict[int, np.ndarray] = {}


def powers(base: int, n: int) -> np.ndarray:
    """base**0 .. base**(n-1) modulo 2**64, kept at the largest size asked for."""
    held = _powers.get(base)
    if held is None or len(held) < n:
        size = max(n, 1 << 16)
        held = np.full(size, base, dtype=np.uint64)
        held[0] = 1
        _powers[base] = held = np.cumprod(held, dtype=np.uint64)
    return held[:n]


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit reaches every output bit."""
    x = x ^ (x >> np.uint64(31))
    x = x * np.uint64(0x7FB5D329728EA185)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x81DADEF4BC2DD44D)
    x ^= x >> np.uint64(33)
    return x


def text_buffer(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of a string column and the offset of each row in them; null is empty."""
    if not len(column):
        return np.zeros(0, dtype=np.uint8), np.zeros(1, dtype=np.int64)
    if column.null_count:
        column = column.fill_null("")
    wide = pa.types.is_large_string(column.type) or pa.types.is_large_binary(column.type)
    _, offsets, data = column.buffers()
    off = np.frombuffer(offsets, dtype=np.int64 if wide else np.int32)[column.offset : column.offset + len(column) + 1].astype(np.int64)
    if data is None:
        return np.zeros(0, dtype=np.uint8), np.zeros(len(column) + 1, dtype=np.int64)
    return np.frombuffer(data, dtype=np.uint8)[off[0] : off[-1]], off - off[0]


def slices(off: np.ndarray, limit: int = 1 << 20) -> Iterator[tuple[int, int]]:
    """Row ranges of at most ``limit`` bytes each (one row at least), so that scratch arrays stay small."""
    i, n = 0, len(off) - 1
    while i < n:
        j = max(i + 1, int(np.searchsorted(off, off[i] + limit, side="right")) - 1)
        yield i, min(j, n)
        i = min(j, n)


class Words:
    """Word bounds and 64-bit word hashes of some rows; ``first[i]:first[i+1]`` are row i's words."""

    def __init__(self, data: np.ndarray, off: np.ndarray, folded: bool):
        n = len(data)
        inside = IS_WORD[data]
        before = np.empty(n, dtype=bool)
        after = np.empty(n, dtype=bool)
        if n:
            before[0] = after[-1] = False
            before[1:] = inside[:-1]
            after[:-1] = inside[1:]
            begins = off[:-1][off[:-1] < n]
            before[begins] = False
            after[begins[begins > 0] - 1] = False
        self.start = np.flatnonzero(inside & ~before)
        self.end = np.flatnonzero(inside & ~after) + 1
        self.first = np.searchsorted(self.start, off)
        sums = np.zeros(n + 1, dtype=np.uint64)
        np.cumsum((FOLDED_VALUES if folded else BYTE_VALUES)[data] * powers(_BASE, n), out=sums[1:])
        self.hash = mix((sums[self.end] - sums[self.start]) * powers(_BASE_INVERSE, n + 1)[self.start])


    @classmethod
    def whole(cls, data: np.ndarray, off: np.ndarray, folded: bool) -> Words:
        """The same for many rows: worked out slice by slice, so only the words' own arrays grow with the input."""
        cuts = list(slices(off))
        parts = [cls(data[off[i] : off[j]], off[i : j + 1] - off[i], folded) for i, j in cuts]
        out = cls.__new__(cls)
        join = lambda arrays, kind: np.concatenate([*arrays, np.zeros(0, dtype=kind)])
        out.start, out.end = (join([getattr(p, x) + off[i] for p, (i, _) in zip(parts, cuts, strict=True)], np.int64) for x in ("start", "end"))
        out.hash = join([p.hash for p in parts], np.uint64)
        counts = join([np.diff(p.first) for p in parts], np.int64)
        out.first = np.concatenate([[0], np.cumsum(counts)])
        return out


def sequence_digest(hashes: np.ndarray) -> tuple[int, int]:
    """128 bits of a sequence of word hashes, as two signed 64-bit numbers."""
    n = len(hashes)
    sums = np.asarray([np.dot(hashes, powers(b, n)) for b in _SEQUENCE_BASES], dtype=np.uint64)
    return tuple(mix(sums + np.full(2, n, dtype=np.uint64) * _ODD).view(np.int64).tolist())


_SHINGLE = _rng.integers(1, 2**63, 5, dtype=np.uint64) * np.uint64(2) + np.uint64(1)


def shingle_hashes(hashes: np.ndarray) -> np.ndarray:
    """Hashes of all windows of five words, over one array (windows across rows are cut out by the caller)."""
    n = len(hashes) - 4
    if n <= 0:
        return np.zeros(0, dtype=np.uint64)
    total = hashes[:n] * _SHINGLE[0]
    for k in range(1, 5):
        total += hashes[k : k + n] * _SHINGLE[k]
    return mix(total)


def shingle_set(hashes: np.ndarray, windows: np.ndarray | None = None) -> np.ndarray:
    """Sorted distinct five-word shingles of one text's words; fewer words count as one shingle."""
    n = len(hashes)
    if n == 0:
        return np.zeros(0, dtype=np.uint64)
    if n < 5:
        return np.asarray([sequence_digest(hashes)[0]], dtype=np.int64).view(np.uint64)
    return np.unique(shingle_hashes(hashes) if windows is None else windows[: n - 4])
