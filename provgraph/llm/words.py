"""Words of many texts at once, as numpy arrays.

Texts are handled in blocks of a few megabytes, so the memory of a task doesn't depend on how many
rows an Arrow batch has.  A word is known by a 64-bit hash of its bytes.
"""
from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

BLOCK = 1 << 19
U64 = np.uint64
_BASE = 0x9E3779B97F4A7C15
_LENGTH = U64(0xC2B2AE3D27D4EB4F)
_UPPER = bytes(range(65, 91))
_LOWER = bytes(range(97, 123))


def _table(lower: bool, is_space) -> bytes:
    t = bytearray(range(256))
    if lower:
        t[65:91] = _LOWER
    for i in range(256):
        if is_space(t[i]):
            t[i] = 32
    return bytes(t)


#: Byte tables: runs of bytes other than 32 are words.
BLANK = _table(False, lambda b: b == 0x20 or 0x09 <= b <= 0x0D)
BLANK_LOWER = _table(True, lambda b: b == 0x20 or 0x09 <= b <= 0x0D)
ALNUM_LOWER = _table(True, lambda b: not (0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A or b >= 0x80))

_powers: list[np.ndarray] = [np.ones(1, U64), np.ones(1, U64)]


def _power(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers[0]) < n:
        size = max(n, BLOCK + 1)
        for k, base in enumerate((_BASE, pow(_BASE, -1, 1 << 64))):
            a = np.full(size, base, U64)
            a[0] = 1
            _powers[k] = np.multiply.accumulate(a)
    return _powers[0], _powers[1]


def mix(h: np.ndarray) -> np.ndarray:
    h = h ^ (h >> U64(33))
    h *= U64(0xFF51AFD7ED558CCD)
    h ^= h >> U64(33)
    h *= U64(0xC4CEB9FE1A85EC53)
    h ^= h >> U64(33)
    return h


def hash_spans(buf: np.ndarray, s: np.ndarray, *ends: np.ndarray) -> list[np.ndarray]:
    """64-bit hashes of buf[s:e] for increasing starts, one array for each of ``ends``; the last ends are the farthest."""
    out = [np.empty(len(s), U64) for _ in ends]
    i = 0
    while i < len(s):
        at = int(s[i])
        j = max(i + 1, int(np.searchsorted(ends[-1], at + BLOCK, "right")))
        seg = buf[at : int(ends[-1][j - 1])]
        p, q = _power(len(seg) + 1)
        h = np.zeros(len(seg) + 1, U64)
        np.cumsum((seg.astype(U64) + U64(1)) * p[: len(seg)], out=h[1:])
        a = s[i:j] - at
        for x, e in zip(out, ends):
            b = e[i:j] - at
            x[i:j] = mix((h[b] - h[a]) * q[a] + (b - a).astype(U64) * _LENGTH)
        i = j
    return out


class Block:
    """The words of some texts.  ``first[d] : first[d + 1]`` are the words of text d."""

    def __init__(self, texts: list[bytes | None], table: bytes):
        self.raw = b" ".join(t or b"" for t in texts).translate(table)
        self.buf = np.frombuffer(self.raw, np.uint8)
        sizes = np.fromiter((len(t or b"") + 1 for t in texts), np.int64, len(texts))
        self.at = np.concatenate([[0], np.cumsum(sizes)])
        word = np.zeros(len(self.buf) + 2, np.int8)
        word[1:-1] = self.buf != 32
        edge = np.diff(word)
        self.s, self.e = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
        self.first = np.searchsorted(self.s, self.at)
        self.count = np.diff(self.first)

    def hashes(self) -> np.ndarray:
        return hash_spans(self.buf, self.s, self.e)[0]

    def doc(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.count)), self.count)

    def word(self, i: int) -> bytes:
        return self.raw[self.s[i] : self.e[i]]


def blocks(texts, table: bytes, size: int = BLOCK) -> Iterator[tuple[int, int, Block]]:
    """(lo, hi, Block of texts[lo:hi]); a text longer than ``size`` has a block of its own.

    ``texts``: a list of bytes, or a ``Texts``, of which only one block's copies exist at a time.
    """
    lo, total = 0, 0
    for i, n in enumerate(texts.sizes if isinstance(texts, Texts) else [len(t or b"") for t in texts]):
        if i > lo and total + n > size:
            yield lo, i, Block(texts[lo:i], table)
            lo, total = i, 0
        total += n
    if lo < len(texts):
        yield lo, len(texts), Block(texts[lo:], table)


class Texts:
    """The UTF-8 bytes of an Arrow string column, copied out only where they are sliced or iterated."""

    def __init__(self, column):
        self.column = column.cast(pa.binary() if not pa.types.is_large_string(column.type) else pa.large_binary())
        self.sizes = pc.fill_null(pc.binary_length(self.column), 0).to_pylist()

    def __len__(self) -> int:
        return len(self.sizes)

    def __getitem__(self, at: slice) -> list[bytes | None]:
        return self.column[at].to_pylist()

    def __iter__(self) -> Iterator[bytes | None]:
        return (x.as_py() for x in self.column)


def bytes_of(column) -> Texts:
    return Texts(column)


def window_hashes(h: np.ndarray, n: int) -> np.ndarray:
    """Hashes of h[i : i + n] for all i; fewer than n words: none."""
    if len(h) < n:
        return np.empty(0, U64)
    p, q = _power(len(h) + 1)
    c = np.zeros(len(h) + 1, U64)
    np.cumsum(h * p[: len(h)], out=c[1:])
    m = len(h) - n + 1
    return mix((c[n:] - c[:m]) * q[:m])
