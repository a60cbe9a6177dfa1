"""Anchors: places of a text that depend only on the bytes near them.

The anchor of a window of ``length`` bytes is where its least hash of ``GRAM`` bytes
stands (the leftmost of equal ones), so equal windows have equal anchors. Consecutive
windows with one anchor are a run; every window of a text is in exactly one run.
"""

from __future__ import annotations

import numpy as np

from axisgrove.llm.words import mix64, multipliers

GRAM = 24
_PLACE = np.uint64((1 << 21) - 1)
_WEIGHTS = multipliers(GRAM // 8, 501)
#: An odd base and its inverse modulo 2^64, for sums over spans that do not depend on where they stand.
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)


_powers = [np.ones(1, np.uint64), np.ones(1, np.uint64)]


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """The first powers of the base and of its inverse; kept for the next call while small."""
    if len(_powers[0]) < n:
        size = max(n, 1 << 17)
        made = [np.multiply.accumulate(np.concatenate([np.ones(1, np.uint64), np.full(size - 1, b, dtype=np.uint64)])) for b in (_BASE, _INVERSE)]
        if size > 1 << 20:
            return made[0][:n], made[1][:n]
        _powers[:] = made
    return _powers[0][:n], _powers[1][:n]


def _lanes(data: np.ndarray) -> np.ndarray:
    """The 8 bytes from each place, as one number."""
    return np.ndarray(shape=(len(data) - 7,), dtype="<u8", buffer=np.ascontiguousarray(data), strides=(1,)).copy()


def gram_hashes(data: np.ndarray) -> np.ndarray:
    lanes = _lanes(data)
    n = len(data) - GRAM + 1
    with np.errstate(over="ignore"):
        total = np.zeros(n, dtype=np.uint64)
        for j in range(GRAM // 8):
            total += lanes[8 * j : 8 * j + n] * _WEIGHTS[j]
        return mix64(total)


def _sliding_min(x: np.ndarray, width: int) -> np.ndarray:
    step, out = 1, x
    while step * 2 <= width:
        out = np.minimum(out[:-step], out[step:])
        step *= 2
    if step < width:
        out = np.minimum(out[: len(out) - (width - step)], out[width - step :])
    return out


#: Bytes of short texts that are looked at together.
CHUNK = 1 << 16


def _runs_of_chunk(data: np.ndarray, offsets: np.ndarray, length: int, surroundings: bool):
    hashes = gram_hashes(data)
    reach = length - GRAM + 1
    total = len(data) - length + 1
    heads = np.zeros(total, dtype=bool)
    heads[0] = True
    anchored = np.empty(total, dtype=np.int64)
    block = int(_PLACE) - reach
    for at in range(0, total, block):  # places fit into the low bits of a key
        part = hashes[at : at + block + reach - 1]
        keys = (part & ~_PLACE) | np.arange(len(part), dtype=np.uint64)
        anchored[at : at + block] = (_sliding_min(keys, reach) & _PLACE).astype(np.int64) + at
    heads[1:] = anchored[1:] != anchored[:-1]
    # A run ends with the last window of its text; those that reach into the next text are left out.
    for edge in offsets[:-1], np.maximum(offsets[:-1], offsets[1:] - length + 1):
        heads[edge[edge < total]] = True
    start = np.flatnonzero(heads)
    count = np.diff(np.append(start, total))
    text = np.searchsorted(offsets, start, side="right") - 1
    inside = np.flatnonzero(start <= offsets[text + 1] - length)
    start, count, text = start[inside], count[inside], text[inside]
    place = anchored[start]
    whole = np.zeros(len(start), np.uint64)
    if surroundings and len(start):
        with np.errstate(over="ignore"):
            power, back = powers(len(hashes) + 1)
            sums = np.concatenate([np.zeros(1, np.uint64), np.cumsum(hashes * power[:-1])])
            span = (sums[start + count - 1 + reach] - sums[start]) * back[start]
            whole = mix64(span + mix64((place - start).astype(np.uint64) * np.uint64(1 << 32) + count.astype(np.uint64)))
    return text, start - offsets[text], count, hashes[place], whole, place - start


def runs_of_texts(data: np.ndarray, offsets: np.ndarray, length: int, surroundings: bool = True) -> tuple[np.ndarray, ...]:
    """(text, first window, windows, anchor hash, hash of all bytes of the run and the anchor's place in it, that place).

    ``data`` is the bytes of texts one after the other, text i being ``data[offsets[i] : offsets[i + 1]]``. Short texts are
    looked at many at a time. Without ``surroundings`` the hash of the bytes is left out (zeros).
    """
    found, at = [], 0
    while at < len(offsets) - 1:
        stop = max(at + 1, int(np.searchsorted(offsets, offsets[at] + CHUNK, side="right")) - 1)
        if offsets[stop] - offsets[at] >= length:
            text, *rest = _runs_of_chunk(data[offsets[at] : offsets[stop]], offsets[at : stop + 1] - offsets[at], length, surroundings)
            found.append((text + at, *rest))
        at = stop
    kinds = (np.int64, np.int64, np.int64, np.uint64, np.uint64, np.int64)
    return tuple(np.concatenate([*(f[k] for f in found), np.zeros(0, kind)]) for k, kind in enumerate(kinds))


def runs(data: np.ndarray, length: int, surroundings: bool = True) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(first window, windows, anchor hash, hash of the run's bytes) of one text, as of many (``runs_of_texts``)."""
    return runs_of_texts(data, np.array([0, len(data)]), length, surroundings)[1:5]
