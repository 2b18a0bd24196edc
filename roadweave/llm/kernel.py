"""Vectorised word and shingle hashing over UTF-8 buffers.

Words are found on the bytes themselves and hashed through one running
polynomial sum, so no Python string is made for a word. Hashes depend on
nothing but the bytes: every process on every machine gives the same ones.
"""

from __future__ import annotations

import numpy as np

#: Fixed odd multipliers of the polynomial hashes and the mixing steps.
BASE = 0x9E3779B97F4A7C15
STEP = 0xC2B2AE3D27D4EB4F
MIX = (0xBF58476D1CE4E5B9, 0x94D049BB133111EB)

_powers: dict[int, np.ndarray] = {}

#: White space of the contracts: space and 0x09 to 0x0D.
WHITE = np.zeros(256, dtype=bool)
WHITE[[0x20, *range(0x09, 0x0E)]] = True

#: Everything in ASCII but letters and digits parts words; bytes from 0x80 on belong to them.
NOT_WORD = np.ones(256, dtype=bool)
NOT_WORD[[*range(0x30, 0x3A), *range(0x41, 0x5B), *range(0x61, 0x7B), *range(0x80, 0x100)]] = False


def powers(base: int, n: int) -> np.ndarray:
    """``base`` to the powers 0 to n - 1, modulo 2**64."""
    have = _powers.get(base)
    if have is None or len(have) < n:
        size = max(1 << 12, 1 << (n - 1).bit_length())
        row = np.full(size, base, dtype=np.uint64)
        row[0] = 1
        have = _powers[base] = np.cumprod(row, dtype=np.uint64)
    return have[:n]


def mix(h: np.ndarray) -> np.ndarray:
    """Bijective scrambling of 64-bit values."""
    h = h ^ (h >> np.uint64(30))
    h = h * np.uint64(MIX[0])
    h ^= h >> np.uint64(27)
    h *= np.uint64(MIX[1])
    h ^= h >> np.uint64(31)
    return h


def words(data: np.ndarray, offsets: np.ndarray, separator: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end byte of every word, and the number of words of each row.

    A word is a maximal run, inside one row, of bytes for which ``separator`` is false.
    """
    n = len(data)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets) - 1, np.int64)
    inside = ~separator[data]
    begin = inside.copy()
    begin[1:] &= ~inside[:-1]
    edges = offsets[:-1][offsets[:-1] < n]
    begin[edges] = inside[edges]
    close = inside.copy()
    close[:-1] &= ~inside[1:]
    lasts = offsets[1:][offsets[1:] > 0] - 1
    close[lasts] = inside[lasts]
    starts = np.flatnonzero(begin)
    ends = np.flatnonzero(close) + 1
    per_row = np.diff(np.searchsorted(starts, offsets))
    return starts, ends, per_row


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hash of the bytes of every word."""
    n = len(data)
    inverse = pow(BASE, -1, 1 << 64)
    total = np.zeros(n + 1, dtype=np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * powers(BASE, n), dtype=np.uint64, out=total[1:])
    return mix((total[ends] - total[starts]) * powers(inverse, n + 1)[starts] + (ends - starts).astype(np.uint64))


def windows(hashes: np.ndarray, per_row: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Hash of every run of ``width`` words inside a row, and how many each row has."""
    counts = np.maximum(per_row - width + 1, 0)
    if not counts.sum():
        return np.zeros(0, np.uint64), counts
    span = len(hashes) - width + 1
    out = np.zeros(span, dtype=np.uint64)
    for j in range(width):
        out += hashes[j : j + span] * np.uint64(pow(STEP, j + 1, 1 << 64))
    row_start = np.cumsum(per_row) - per_row
    first = np.repeat(row_start - (np.cumsum(counts) - counts), counts)
    return mix(out[first + np.arange(counts.sum())]), counts


def shingles(hashes: np.ndarray, per_row: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """As :func:`windows`, but a row with one to ``width`` - 1 words has one shingle of them all."""
    found, counts = windows(hashes, per_row, width)
    short = np.flatnonzero((per_row > 0) & (per_row < width))
    if not len(short):
        return found, counts
    row_start = np.cumsum(per_row) - per_row
    own = np.zeros(len(short), dtype=np.uint64)
    for j in range(width - 1):
        has = per_row[short] > j
        own[has] += hashes[row_start[short[has]] + j] * np.uint64(pow(STEP, j + 1, 1 << 64))
    at = np.cumsum(counts) - counts
    counts = counts.copy()
    counts[short] = 1
    return np.insert(found, at[short], mix(own + per_row[short].astype(np.uint64))), counts


def distinct(hashes: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct hashes of each row in ascending order, how often each occurs, and their number by row."""
    rows = np.repeat(np.arange(len(counts)), counts)
    order = np.lexsort((hashes, rows))
    h, r = hashes[order], rows[order]
    if not len(h):
        return h, np.zeros(0, np.int64), counts * 0
    new = np.ones(len(h), dtype=bool)
    new[1:] = (h[1:] != h[:-1]) | (r[1:] != r[:-1])
    at = np.flatnonzero(new)
    return h[at], np.diff(np.append(at, len(h))), np.bincount(r[at], minlength=len(counts))
