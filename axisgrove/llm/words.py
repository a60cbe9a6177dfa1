"""Vectorised word spans and hashes over Arrow string batches.

Everything works on the UTF-8 bytes of a whole batch at once. Separators are ASCII in
every word definition used here, so cutting bytes cuts code points correctly.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

#: Bytes of text that are expanded into 8-byte lanes at a time.
SLICE_BYTES = 1 << 21


def _table(is_word) -> np.ndarray:
    return np.array([bool(is_word(b)) for b in range(256)])


#: Words between the six ASCII white-space characters.
SPACED = _table(lambda b: not (b == 0x20 or 0x09 <= b <= 0x0D))
#: Words of digits, lower-case letters and everything beyond ASCII.
ALNUM = _table(lambda b: 0x30 <= b <= 0x39 or 0x61 <= b <= 0x7A or b >= 0x80)
#: A-Z to a-z, other bytes as they are.
LOWER = np.array([b + 32 if 0x41 <= b <= 0x5A else b for b in range(256)], dtype=np.uint8)


def mix64(x: np.ndarray) -> np.ndarray:
    """Bijective scrambling of unsigned 64-bit lanes (xor-shift and multiply)."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def multipliers(n: int, seed: int) -> np.ndarray:
    """``n`` fixed pseudo-random odd multipliers; a longer request extends a shorter one."""
    with np.errstate(over="ignore"):
        lanes = (np.arange(1, n + 1, dtype=np.uint64) + np.uint64(seed)) * np.uint64(0x9E3779B97F4A7C15)
    return mix64(lanes) | np.uint64(1)


_PLACES = multipliers(4096, 11)


def text_bytes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of all texts in a row, and n + 1 offsets; a null text is empty."""
    if isinstance(texts, pa.ChunkedArray):
        texts = texts.combine_chunks()
    texts = texts.cast(pa.large_binary()).fill_null(b"")
    _, offsets, data = texts.buffers()
    offsets = np.frombuffer(offsets, dtype=np.int64)[texts.offset : texts.offset + len(texts) + 1]
    if data is None or offsets[-1] == offsets[0]:
        return np.zeros(0, dtype=np.uint8), np.zeros(len(texts) + 1, dtype=np.int64)
    return np.frombuffer(data, dtype=np.uint8)[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(batch: pa.RecordBatch, column: str, most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """The batch in runs of rows of about ``most`` bytes of text (a longer text alone)."""
    if not batch.num_rows:
        return
    _, offsets = text_bytes(batch.column(column))
    start = 0
    while start < batch.num_rows:
        stop = int(np.searchsorted(offsets, offsets[start] + most, side="right")) - 1
        stop = min(max(stop, start + 1), batch.num_rows)
        yield batch.slice(start, stop - start)
        start = stop


class Words:
    """Word spans of a batch of texts.

    ``start`` and ``stop`` are byte positions in ``data``; the words of text i are
    ``first[i] .. first[i + 1]``.
    """

    def __init__(self, texts: pa.Array, kind: np.ndarray, lower: bool):
        data, self.offsets = text_bytes(texts)
        self.data = LOWER[data] if lower else data
        self.inside = kind[self.data]
        before = np.zeros_like(self.inside)
        before[1:] = self.inside[:-1]
        heads = self.offsets[:-1]
        before[heads[heads < len(data)]] = False
        self.start = np.flatnonzero(self.inside & ~before)
        after = np.zeros_like(self.inside)
        after[:-1] = self.inside[1:]
        tails = self.offsets[1:] - 1
        after[tails[tails >= 0]] = False
        self.stop = np.flatnonzero(self.inside & ~after) + 1
        self.first = np.searchsorted(self.start, self.offsets)

    def counts(self) -> np.ndarray:
        return np.diff(self.first)

    def packed(self) -> pa.LargeBinaryArray:
        """The words as one binary array."""
        ends = np.zeros(len(self.start) + 1, dtype=np.int64)
        np.cumsum(self.stop - self.start, out=ends[1:])
        data = np.ascontiguousarray(self.data[self.inside])
        return pa.LargeBinaryArray.from_buffers(pa.large_binary(), len(self.start), [None, pa.py_buffer(ends), pa.py_buffer(data)])

    def hashes(self) -> np.ndarray:
        """A 64-bit hash of each word."""
        if not len(self.start):
            return np.zeros(0, dtype=np.uint64)
        size = self.stop - self.start
        ends = np.cumsum(size)
        heads = ends - size
        place = np.arange(ends[-1]) - np.repeat(heads, size)
        longest = int(size.max())
        table = _PLACES if longest <= len(_PLACES) else multipliers(longest, 11)
        with np.errstate(over="ignore"):
            lanes = (self.data[self.inside].astype(np.uint64) + np.uint64(1)) * table[place]
            return mix64(np.add.reduceat(lanes, heads) + size.astype(np.uint64))


def shingle_hashes(words: Words, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of every run of ``width`` words, and the index of the text of each.

    A text of fewer words, but not none, has its whole sequence as one shingle.
    """
    h, first = words.hashes(), words.first
    counts = np.diff(first)
    text = np.repeat(np.arange(len(counts)), counts)
    weights = multipliers(width + 1, 77)
    n = len(h) - width + 1
    with np.errstate(over="ignore"):
        if n > 0:
            total = np.zeros(n, dtype=np.uint64)
            for j in range(width):
                total += h[j : j + n] * weights[j]
            whole = text[:n] == text[width - 1 :]
            found, owner = mix64(total[whole]), text[:n][whole]
        else:
            found, owner = np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64)
        short = np.flatnonzero((counts > 0) & (counts < width))
        if len(short):
            extra = np.array([np.sum(h[first[i] : first[i + 1]] * weights[: counts[i]]) + weights[width] * np.uint64(counts[i]) for i in short], dtype=np.uint64)
            found = np.concatenate([found, mix64(extra)])
            owner = np.concatenate([owner, short])
    return found, owner
