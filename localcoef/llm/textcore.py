"""Words, 64-bit word hashes and window hashes of whole texts, vectorised over a bounded block of documents.

A word is a maximal run of bytes outside space and tab..carriage return, which for UTF-8 text is the
pattern ``[^\\x20\\x09-\\x0D]+``. A null text has no words.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

BLOCK_BYTES = 1 << 18
_U = np.uint64
_BLANK = np.zeros(256, bool)
_BLANK[[32, 9, 10, 11, 12, 13]] = True
_RNG = np.random.default_rng(20240611)
_BYTE = _RNG.integers(1, 2**63, 256, dtype=np.uint64) | _U(1)
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


class _Powers:
    """Powers of an odd base and of its inverse modulo 2**64, grown on demand."""

    def __init__(self, base: int):
        self.base, self.inverse = base, pow(base, -1, 1 << 64)
        self.up = self.down = np.ones(1, _U)

    def get(self, n: int) -> tuple[np.ndarray, np.ndarray]:
        while len(self.up) < n:
            k = len(self.up)
            self.up = np.concatenate([self.up, self.up * _U(pow(self.base, k, 1 << 64))])
            self.down = np.concatenate([self.down, self.down * _U(pow(self.inverse, k, 1 << 64))])
        return self.up[:n], self.down[:n]


_BYTES, _WORDS = _Powers(0x9E3779B97F4A7C15 | 1), _Powers(0xC2B2AE3D27D4EB4F | 1)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambler of 64-bit values."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> _U(27))
    x = x * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


class WordBlock:
    """The words of several texts: byte spans, hashes, and the first word of each text."""

    def __init__(self, texts: list[str | None], lower: bool = False):
        raw = [b"" if t is None else t.encode("utf-8", "surrogatepass") for t in texts]
        self.raw = raw
        data = np.frombuffer(b"\n".join(raw) + b"\n", np.uint8)
        if lower:
            data = _LOWER[data]
        self.data = data
        sizes = np.fromiter((len(r) + 1 for r in raw), np.int64, len(raw))
        self.offset = np.concatenate([[0], np.cumsum(sizes)])
        blank = _BLANK[data]
        edge = np.diff(np.concatenate([[True], blank]).astype(np.int8))
        self.start = np.flatnonzero(edge == -1)
        self.end = np.flatnonzero(edge == 1)
        self.first = np.searchsorted(self.start, self.offset)
        self.n = len(self.start)

    def hashes(self) -> np.ndarray:
        up, down = _BYTES.get(len(self.data))
        total = np.concatenate([np.zeros(1, _U), np.cumsum(_BYTE[self.data] * up, dtype=_U)])
        length = (self.end - self.start).astype(_U)
        return mix((total[self.end] - total[self.start]) * down[self.start] + length)

    def doc_of(self) -> np.ndarray:
        return np.repeat(np.arange(len(self.raw)), np.diff(self.first))

    def room(self) -> np.ndarray:
        """How many words remain in the text from each word on, itself included."""
        return np.repeat(self.first[1:], np.diff(self.first)) - np.arange(self.n)


def window_hashes(words: np.ndarray, width: int) -> np.ndarray:
    """Hash of each run of ``width`` consecutive word hashes; runs may cross texts (see ``WordBlock.room``)."""
    n = len(words) - width + 1
    if n <= 0:
        return np.zeros(0, _U)
    up, down = _WORDS.get(len(words) + 1)
    total = np.concatenate([np.zeros(1, _U), np.cumsum(words * up[: len(words)], dtype=_U)])
    return mix((total[width:] - total[:n]) * down[:n])


def blocks(texts: list[str | None], limit: int = BLOCK_BYTES) -> Iterator[tuple[int, int]]:
    """Consecutive slices of about ``limit`` characters; a longer text is a slice of its own."""
    low, size = 0, 0
    for i, t in enumerate(texts):
        n = len(t) if t else 0
        if size and size + n > limit:
            yield low, i
            low, size = i, 0
        size += n + 1
    if low < len(texts):
        yield low, len(texts)


def text_blocks(column: pa.Array, limit: int = BLOCK_BYTES) -> Iterator[tuple[int, int, list[str | None]]]:
    """(from, to, texts) of consecutive slices of a text column, so that only a slice at a time is Python strings."""
    sizes = pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False)
    low, size = 0, 0
    for i, n in enumerate(sizes.tolist()):
        if size and size + n > limit:
            yield low, i, column.slice(low, i - low).to_pylist()
            low, size = i, 0
        size += n + 1
    if low < len(sizes):
        yield low, len(sizes), column.slice(low, len(sizes) - low).to_pylist()
