"""Vectorised text kernel shared by the text operators.

Texts arrive as Arrow string columns.  A column is cut into sub-batches of a
bounded number of bytes, and every per-character step (case folding, finding
words, hashing them) is one NumPy pass over the bytes of a sub-batch, so memory
is bounded by the sub-batch or by the longest single text, never by a partition.

Words are maximal runs of bytes other than ``0x20`` and ``0x09-0x0D``.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

SUB_BATCH_BYTES = 1 << 20

_SPACE = np.zeros(256, dtype=bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[ord("A") : ord("Z") + 1] += 32

_rng = np.random.default_rng(20_240_117)
_BYTE_CODE = _rng.integers(1, 2**63, 256, dtype=np.uint64) | np.uint64(1)
_BASE = np.uint64(0x9E3779B97F4A7C15 | 1)
_BASE_INV = np.uint64(pow(int(_BASE), -1, 2**64))
_SLOT = _rng.integers(1, 2**63, 64, dtype=np.uint64) | np.uint64(1)
_powers = [np.ones(1, dtype=np.uint64), np.ones(1, dtype=np.uint64)]


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser that spreads 64-bit values (bijective)."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    if len(_powers[0]) < n:
        size = max(n, SUB_BATCH_BYTES + 1)
        for k, base in enumerate((_BASE, _BASE_INV)):
            table = np.full(size, base, dtype=np.uint64)
            table[0] = 1
            _powers[k] = np.cumprod(table, dtype=np.uint64)
    out = _powers[0], _powers[1]
    if n > 8 * SUB_BATCH_BYTES:  # one giant text must not pin memory for good
        _powers[0], _powers[1] = _powers[0][:1].copy(), _powers[1][:1].copy()
    return out


@dataclass
class Words:
    """Words of a sub-batch of texts.

    ``raw`` are the bytes of all texts end to end, ``offsets`` (n + 1) where
    each text begins, ``start``/``end`` the byte range of every word and
    ``first`` (n + 1) the index of each text's first word.
    """

    raw: np.ndarray
    offsets: np.ndarray
    start: np.ndarray
    end: np.ndarray
    first: np.ndarray

    def hashes(self, fold: bool = True) -> np.ndarray:
        """A 64-bit hash of every word; ``fold`` lower-cases A-Z first."""
        if not len(self.start):
            return np.empty(0, dtype=np.uint64)
        up, down = _power_tables(len(self.raw) + 1)
        data = _FOLD[self.raw] if fold else self.raw
        run = np.empty(len(data) + 1, dtype=np.uint64)
        run[0] = 0
        codes = _BYTE_CODE[data]
        codes *= up[: len(data)]
        np.cumsum(codes, out=run[1:])
        return mix64((run[self.end] - run[self.start]) * down[self.start])


def text_slices(column: pa.Array | pa.ChunkedArray) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """Yields (first row, last row + 1, bytes, offsets) sub-batches of a string column.

    Null texts count as empty.
    """
    chunks = column.chunks if isinstance(column, pa.ChunkedArray) else [column]
    base = 0
    for chunk in chunks:
        if pa.types.is_null(chunk.type):
            chunk = chunk.cast(pa.large_string())
        if not pa.types.is_large_string(chunk.type):
            chunk = chunk.cast(pa.large_string())
        if chunk.null_count:
            chunk = chunk.fill_null("")
        n = len(chunk)
        if n:
            offs = np.frombuffer(chunk.buffers()[1], dtype=np.int64)[chunk.offset : chunk.offset + n + 1]
            data = chunk.buffers()[2]
            raw = np.frombuffer(data, dtype=np.uint8) if data is not None else np.empty(0, dtype=np.uint8)
            lo = 0
            while lo < n:
                hi = int(np.searchsorted(offs, offs[lo] + SUB_BATCH_BYTES, side="right")) - 1
                hi = min(n, max(hi, lo + 1))
                yield base + lo, base + hi, raw[offs[lo] : offs[hi]], offs[lo : hi + 1] - offs[lo]
                lo = hi
        base += n


def find_words(raw: np.ndarray, offsets: np.ndarray) -> Words:
    word = ~_SPACE[raw]
    n = len(raw)
    if not n:
        none = np.empty(0, dtype=np.int64)
        return Words(raw, offsets, none, none, np.zeros(len(offsets), dtype=np.int64))
    opens = word.copy()
    opens[1:] &= ~word[:-1]
    closes = word.copy()
    closes[:-1] &= ~word[1:]
    inner = offsets[1:-1]
    inner = inner[(inner > 0) & (inner < n)]
    if len(inner):  # texts touch each other without a separator
        opens[inner] = word[inner]
        closes[inner - 1] = word[inner - 1]
    start = np.flatnonzero(opens)
    end = np.flatnonzero(closes) + 1
    return Words(raw, offsets, start, end, np.searchsorted(start, offsets))


def windows(hashes: np.ndarray, width: int, seed: int = 0) -> np.ndarray:
    """Hashes of all runs of ``width`` consecutive words, ignoring text borders."""
    n = len(hashes) - width + 1
    if n <= 0:
        return np.empty(0, dtype=np.uint64)
    total = np.full(n, np.uint64((width * 0x51_7C_C1B7_2722_0A95 + seed) & (2**64 - 1)), dtype=np.uint64)
    for k in range(width):
        total += hashes[k : k + n] * _SLOT[k % 64]
    return mix64(total)


def distinct_shingles(words: Words, width: int) -> Iterator[np.ndarray]:
    """Sorted distinct shingle hashes of each text.

    A text of fewer words than ``width`` has its whole sequence as its only
    shingle (marked by its length); a text without words has none.
    """
    hashes = words.hashes()
    grams = windows(hashes, width)
    none = np.empty(0, dtype=np.uint64)
    first = words.first.tolist()
    for lo, hi in zip(first[:-1], first[1:]):
        n = hi - lo
        if n >= width:
            yield np.unique(grams[lo : hi - width + 1])
        elif n:
            yield windows(hashes[lo:hi], n)
        else:
            yield none
