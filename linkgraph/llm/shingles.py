"""Word shingles of whole texts as 64-bit hashes, computed on UTF-8 bytes.

Words are the runs of bytes other than ASCII white space, A-Z lower-cased.
Everything is vectorised over many rows at once; no row-wise Python loop runs
over words.
"""

from __future__ import annotations

import numpy as np

from linkgraph.llm.common import mix, powers

WIDTH = 5
_SPACE = np.zeros(256, bool)
_SPACE[[0x20, *range(0x09, 0x0E)]] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[0x41:0x5B] += 32
_COEF = mix(np.arange(101, 101 + WIDTH, dtype=np.uint64)) | np.uint64(1)


def word_hashes(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash of every word of the rows, and how many words each row has."""
    lo, hi = int(offsets[0]), int(offsets[-1])
    block = _LOWER[data[lo:hi]]
    inside = ~_SPACE[block]
    starts_row = np.zeros(len(block) + 1, bool)
    starts_row[offsets - lo] = True
    begins = inside.copy()
    begins[1:] &= ~inside[:-1] | starts_row[1:-1]
    letters = block[inside].astype(np.uint64) + np.uint64(1)
    first = np.flatnonzero(begins)
    rows = np.diff(np.searchsorted(first, offsets - lo))
    if not len(first):
        return np.zeros(0, np.uint64), rows
    # places in the compacted letters
    at = np.cumsum(inside)[first] - 1
    length = np.diff(np.append(at, len(letters)))
    place = np.arange(len(letters)) - np.repeat(at, length)
    letters *= powers(int(length.max()))[place]
    return mix(np.add.reduceat(letters, at) + length.astype(np.uint64) * np.uint64(0xD6E8FEB86659FD93)), rows


def shingle_sets(data: np.ndarray, offsets: np.ndarray, width: int = WIDTH) -> tuple[np.ndarray, np.ndarray]:
    """Distinct shingles of each row, sorted within the row, and their number.

    A row of fewer than ``width`` words but at least one has its whole sequence
    as its single shingle; a row without words has none.
    """
    words, n_words = word_hashes(data, offsets)
    ends = np.cumsum(n_words)
    begins = ends - n_words
    per_row = np.where(n_words >= width, n_words - width + 1, (n_words > 0).astype(n_words.dtype))
    total = int(per_row.sum())
    if not total:
        return np.zeros(0, np.uint64), np.zeros(len(n_words), np.int64)
    row = np.repeat(np.arange(len(n_words)), per_row)
    first = np.cumsum(per_row) - per_row
    start = np.arange(total) - np.repeat(first, per_row) + np.repeat(begins, per_row)
    limit = np.repeat(ends, per_row)
    padded = np.append(words, np.zeros(width, np.uint64))
    value = np.zeros(total, np.uint64)
    for k in range(width):
        value += np.where(start + k < limit, padded[start + k], np.uint64(0)) * _COEF[k]
    value = mix(value)
    order = np.lexsort((value, row))
    value, row = value[order], row[order]
    fresh = np.ones(total, bool)
    fresh[1:] = (value[1:] != value[:-1]) | (row[1:] != row[:-1])
    return value[fresh], np.bincount(row[fresh], minlength=len(n_words))
