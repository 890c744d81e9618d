"""Words of many texts at once, as numpy arrays over their UTF-8 bytes.

A word is a maximal run of bytes outside 0x20 and 0x09-0x0D.  Those bytes never
occur inside a multi-byte character, so runs of bytes are runs of characters.
"""

from __future__ import annotations

import struct
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard

BLANK = np.zeros(256, bool)
BLANK[[0x20, *range(0x09, 0x0E)]] = True

_U = np.uint64


@dataclass
class Words:
    """``data[start[i]:end[i]]`` is word i; text t owns words ``first[t]:first[t + 1]``."""

    data: np.ndarray
    start: np.ndarray
    end: np.ndarray
    first: np.ndarray
    offsets: np.ndarray

    @property
    def text_of(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.first) - 1), np.diff(self.first))

    def text_bytes(self, t: int) -> bytes:
        return self.data[self.offsets[t] : self.offsets[t + 1]].tobytes()


def flat_bytes(column) -> tuple[np.ndarray, np.ndarray]:
    """All texts of an Arrow string column end to end (null: empty), and their offsets."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_binary())
    if column.null_count:
        column = column.fill_null(b"")
    off = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    body = column.buffers()[2]
    data = np.frombuffer(body, np.uint8) if body is not None else np.zeros(0, np.uint8)
    return data[off[0] : off[-1]], off - off[0]


def words_of(column) -> Words:
    data, off = flat_bytes(column)
    n = len(data)
    word = ~BLANK[data]
    head, tail = word.copy(), word.copy()
    head[1:] &= ~word[:-1]
    tail[:-1] &= ~word[1:]
    inner = off[:-1][(off[:-1] > 0) & (off[:-1] < n)]  # a text's first byte starts a word anew
    head[inner] = word[inner]
    tail[inner - 1] = word[inner - 1]
    start, end = np.flatnonzero(head), np.flatnonzero(tail) + 1
    return Words(data, start, end, np.searchsorted(start, off), off)


def mixed(x: np.ndarray) -> np.ndarray:
    """Bijective scrambling of 64-bit values."""
    x = x.copy()
    x ^= x >> _U(33)
    x *= _U(0xFF51AFD7ED558CCD)
    x ^= x >> _U(33)
    x *= _U(0xC4CEB9FE1A85EC53)
    x ^= x >> _U(33)
    return x


_TABLES: dict[int, np.ndarray] = {}
_POWERS: dict[int, np.ndarray] = {}


def _table(seed: int) -> np.ndarray:
    if seed not in _TABLES:
        _TABLES[seed] = mixed(np.arange(1, 257, dtype=_U) * _U(0x9E3779B97F4A7C15) + _U(seed))
    return _TABLES[seed]


def powers(base: int, n: int) -> np.ndarray:
    """base^0 .. base^(n-1) modulo 2^64; base odd."""
    had = _POWERS.get(base)
    if had is None or len(had) < n:
        p = np.full(max(n, 1024), base, _U)
        p[0] = 1
        _POWERS[base] = had = np.multiply.accumulate(p)
    return had[:n]


def run_hashes(data: np.ndarray, start: np.ndarray, end: np.ndarray, seed: int = 1) -> np.ndarray:
    """64-bit hash of each byte run; the runs are disjoint and in order."""
    if not len(start):
        return np.zeros(0, _U)
    length = end - start
    base = (0x2545F4914F6CDD1D + 8 * seed) | 5
    at = np.arange(length.sum()) - np.repeat(np.cumsum(length) - length, length)
    value = _table(seed)[data[np.repeat(start, length) + at]]
    value *= powers(base, int(length.max()))[at]
    return mixed(np.add.reduceat(value, np.cumsum(length) - length))


def window_hashes(h: np.ndarray, k: int, base: int = 0x9FB21C651E98DF25) -> np.ndarray:
    """Rabin-Karp values of every k consecutive hashes, rolled by prefix sums, scrambled."""
    n = len(h) - k + 1
    if n <= 0:
        return np.zeros(0, _U)
    total = np.zeros(len(h) + 1, _U)
    np.cumsum(h * powers(base, len(h)), out=total[1:])
    back = pow(base, -1, 1 << 64)
    return mixed((total[k:] - total[:-k]) * powers(back, n))


def whole_windows(first: np.ndarray, k: int) -> np.ndarray:
    """Which windows of k words over the joined words lie inside one text."""
    n = int(first[-1]) - k + 1
    if n <= 0:
        return np.zeros(0, bool)
    left = np.repeat(first[1:], np.diff(first))[:n]
    return np.arange(n) + k <= left


#: Ends a packed value of which most entries are alike: number of entries, that entry, bytes of the bit map.
_ALIKE = struct.Struct("<QQQB")


def pack(values: np.ndarray, sort: bool = True) -> bytes:
    """Unsigned values, as gaps if rising, split into byte planes and compressed.

    Where over two thirds are the same, a bit tells the others, and those alone are split.
    """
    v = np.asarray(values, _U)
    if not sort and len(v) > 64:
        usual = np.partition(v, len(v) // 2)[len(v) // 2]
        other = v != usual
        if 3 * np.count_nonzero(other) < len(v):
            bits = zstandard.ZstdCompressor(level=1).compress(np.packbits(other).tobytes())
            return _planes(v[other]) + bits + _ALIKE.pack(len(v), int(usual), len(bits), 255)
    if sort and len(v):
        v = np.concatenate([v[:1], np.diff(v)])
    return _planes(v)


#: Values from which on each byte plane has its own compressed frame, so that even planes do not spoil the codes of others.
_APART = 512
_FRAMES = 16


def _planes(v: np.ndarray) -> bytes:
    planes = np.ascontiguousarray(v.astype("<u8").view(np.uint8).reshape(-1, 8).T)
    used = int(np.flatnonzero(planes.any(axis=1))[-1]) + 1 if len(v) and planes.any() else 1
    z = zstandard.ZstdCompressor(level=1)
    if len(v) < _APART:
        return z.compress(planes[:used].tobytes()) + bytes([used])
    frames = [z.compress(p.tobytes()) for p in planes[:used]]
    return b"".join(frames) + struct.pack(f"<{used}Q", *map(len, frames)) + bytes([used | _FRAMES])


def _raw(blob: bytes) -> tuple[bytes, int]:
    """The byte planes end to end, and how many they are."""
    z, used = zstandard.ZstdDecompressor(), blob[-1] & (_FRAMES - 1)
    if not blob[-1] & _FRAMES:
        return z.decompress(blob[:-1]), used
    border = np.cumsum([0, *struct.unpack(f"<{used}Q", blob[-1 - 8 * used : -1])])
    return b"".join(z.decompress(blob[a:b]) for a, b in zip(border, border[1:], strict=False)), used


def unpack(blob: bytes, sort: bool = True) -> np.ndarray:
    if blob[-1] == 255:
        n, usual, size, _ = _ALIKE.unpack(blob[-_ALIKE.size :])
        bits = zstandard.ZstdDecompressor().decompress(blob[-_ALIKE.size - size : -_ALIKE.size])
        v = np.full(n, usual, _U)
        v[np.unpackbits(np.frombuffer(bits, np.uint8), count=n).view(bool)] = unpack(blob[: -_ALIKE.size - size], False)
        return v
    body, used = _raw(blob)
    raw = np.frombuffer(body, np.uint8)
    n = len(raw) // used
    wide = np.zeros((n, 8), np.uint8)
    wide[:, :used] = raw.reshape(used, n).T
    v = wide.view("<u8").ravel().astype(_U)
    return np.cumsum(v, dtype=_U) if sort else v
