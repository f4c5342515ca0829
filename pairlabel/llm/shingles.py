"""Hashes of words and of runs of words, for whole Arrow columns at once."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

_U = np.uint64
_BASE = _U(0x9E3779B97F4A7C15 | 1)
_STEP = _U(0xD6E8FEB86659FD93)
_powers: list[np.ndarray] = []


def _power_tables(n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of the odd base modulo 2**64, and of its inverse."""
    if not _powers or len(_powers[0]) < n:
        n = max(n, (1 << 20) + 1)
        inverse = _U(pow(int(_BASE), -1, 1 << 64))
        up, down = np.full(n, _BASE, dtype=_U), np.full(n, inverse, dtype=_U)
        up[0] = down[0] = 1
        with np.errstate(over="ignore"):
            _powers[:] = [np.cumprod(up, dtype=_U), np.cumprod(down, dtype=_U)]
    return _powers[0], _powers[1]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
        return x ^ (x >> _U(31))


def text_slices(column: pa.Array, most_bytes: int = 1 << 20) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """Of a string column: first row, bytes, and offsets (rows + 1), for runs of rows of about so many bytes; null counts as empty."""
    column = pa.concat_arrays([column]) if isinstance(column, pa.Array) else column.combine_chunks()
    column = column.cast(pa.large_string()).fill_null("")
    _, offsets, data = column.buffers()
    offs = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    at = 0
    while at < len(column):
        end = max(at + 1, int(np.searchsorted(offs, offs[at] + most_bytes, side="right")) - 1)
        end = min(end, len(column))
        yield at, raw[offs[at] : offs[end]], offs[at : end + 1] - offs[at]
        at = end


def word_hashes(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash of each word ([^\\x20\\x09-\\x0D]+ after lower-casing A-Z) of a run of texts, and offsets of each text's words (texts + 1)."""
    n = len(raw)
    if not n:
        return np.zeros(0, _U), np.zeros(len(offsets), np.int64)
    upper = (raw >= 65) & (raw <= 90)
    low = raw + (upper.view(np.uint8) << 5)
    inside = ~((raw == 32) | ((raw >= 9) & (raw <= 13)))
    edge = np.zeros(n + 1, dtype=bool)
    edge[offsets[offsets < n]] = True
    before = np.empty(n, dtype=bool)
    before[0], before[1:] = False, inside[:-1]
    starts = np.nonzero(inside & (~before | edge[:n]))[0]
    after = np.empty(n, dtype=bool)
    after[-1], after[:-1] = False, inside[1:]
    ends = np.nonzero(inside & (~after | edge[1:]))[0] + 1
    up, down = _power_tables(n + 1)
    with np.errstate(over="ignore"):
        total = np.empty(n + 1, dtype=_U)
        total[0] = 0
        np.cumsum((low.astype(_U) + _U(1)) * up[:n], dtype=_U, out=total[1:])
        h = (total[ends] - total[starts]) * down[starts]
        h = mix(h + (ends - starts).astype(_U) * _STEP)
    return h, np.searchsorted(starts, offsets, side="left")


def runs(words: np.ndarray, size: int) -> np.ndarray:
    """Hash of each run of so many words (one array, no regard to texts)."""
    m = len(words) - size + 1
    if m < 1:
        return np.zeros(0, _U)
    with np.errstate(over="ignore"):
        out = np.zeros(m, _U)
        factor = _STEP
        for k in range(size):
            out += words[k : k + m] * factor
            factor = factor * _BASE + _U(2 * k + 1)
        return mix(out + _U(size))


def shingle_sets(raw: np.ndarray, offsets: np.ndarray, size: int = 5) -> Iterator[np.ndarray]:
    """Of each text the sorted distinct hashes of its runs of ``size`` words; a shorter text is one run; without words, empty."""
    words, at = word_hashes(raw, offsets)
    whole = runs(words, size)
    for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
        if b - a >= size:
            own = np.sort(whole[a : b - size + 1])
            if len(own) > 1:
                new = np.empty(len(own), dtype=bool)
                new[0] = True
                np.not_equal(own[1:], own[:-1], out=new[1:])
                own = own[new]
            yield own
        else:
            yield runs(words[a:b], b - a) if b > a else np.zeros(0, _U)
