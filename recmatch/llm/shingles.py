"""Words and word shingles of whole Arrow columns as 64-bit hashes, in numpy, without a string a word.

A word's hash is a polynomial of its bytes modulo 2**64, mixed; a shingle's is a weighted sum of its
words' hashes, mixed. Both depend on the bytes only, so they agree between tasks, runs and machines.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

#: An odd base and its inverse modulo 2**64, and multipliers of a 64-bit finalizer.
BASE = 0x9E3779B97F4A7C15
INVERSE = pow(BASE, -1, 2**64)
MIX1, MIX2 = 0xBF58476D1CE4E5B9, 0x94D049BB133111EB
SLICE = 1 << 20


def mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(30))) * np.uint64(MIX1)
    h = (h ^ (h >> np.uint64(27))) * np.uint64(MIX2)
    return h ^ (h >> np.uint64(31))


def _tables(words: str) -> tuple[np.ndarray, np.ndarray]:
    """Lower-casing of bytes, and which bytes end a word: `blank` the six ASCII blanks, `plain` all ASCII but letters and digits."""
    lower = np.arange(256, dtype=np.uint8)
    lower[65:91] += 32
    ends = np.zeros(256, bool)
    if words == "blank":
        ends[[32, 9, 10, 11, 12, 13]] = True
    else:
        ends[:128] = True
        for a, b in ((48, 58), (65, 91), (97, 123)):
            ends[a:b] = False
    return lower, ends


def _powers(n: int, base: int) -> np.ndarray:
    p = np.full(n, base, np.uint64)
    p[0] = 1
    return np.cumprod(p)


def slices(column: pa.Array, size: int = SLICE):
    """(data, offsets, first row) for runs of rows of about `size` bytes; nulls count as empty."""
    column = column.fill_null("").cast(pa.large_string())
    off = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1] if len(column) else np.zeros(1, np.int64)
    data = np.frombuffer(column.buffers()[2], np.uint8) if column.buffers()[2] is not None else np.zeros(0, np.uint8)
    row = 0
    while row < len(column):
        end = max(row + 1, int(np.searchsorted(off, off[row] + size, "right")) - 1)
        yield data[off[row] : off[end]], off[row : end + 1] - off[row], row
        row = end


class Words:
    """Hashes of the words of some rows: `hashes`, and `first`, the place of each row's first word, one more at the end."""

    def __init__(self, words: str = "blank"):
        self.lower, self.ends = _tables(words)
        self.up = self.down = np.ones(1, np.uint64)

    def of(self, data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        n = len(data)
        if n >= len(self.up):
            self.up, self.down = _powers(max(n + 1, SLICE), BASE), _powers(max(n + 1, SLICE), INVERSE)
        blank = np.ones(n + 1, bool)
        blank[:n] = self.ends[data]
        edge = np.zeros(n + 1, bool)
        edge[off] = True
        inner = ~blank[:n]
        start = inner.copy()
        start[1:] &= blank[: n - 1] | edge[1:n]
        stop = inner & (blank[1:] | edge[1:])
        starts, stops = np.flatnonzero(start), np.flatnonzero(stop) + 1
        total = np.zeros(n + 1, np.uint64)
        np.cumsum((self.lower[data].astype(np.uint64) + np.uint64(1)) * self.up[:n], out=total[1:])
        h = (total[stops] - total[starts]) * self.down[starts]
        return mix(h + (stops - starts).astype(np.uint64)), np.searchsorted(starts, off)


def shingled(h: np.ndarray, first: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of each row's k-word shingles in order, and where each row's begin. A row of fewer words has one, of all; none without words."""
    n = len(h)
    count = np.diff(first)
    rolled = np.zeros(n, np.uint64)
    for j in range(k if n >= k else 0):
        rolled[: n - k + 1] += h[j : n - k + 1 + j] * np.uint64((2 * j + 3) * MIX2 % 2**64)
    keep = np.zeros(n + 1, np.int64)
    # A row's shingles start at its first words, all but the last k - 1.
    np.add.at(keep, first[:-1], 1)
    np.add.at(keep, np.maximum(first[1:] - (k - 1), first[:-1]), -1)
    places = np.flatnonzero(np.cumsum(keep)[:n] > 0)
    full = np.maximum(count - (k - 1), 0)
    short = np.flatnonzero((count > 0) & (count < k))
    out = mix(rolled[places])
    ptr = np.concatenate([[0], np.cumsum(full)])
    if not len(short):
        return out, ptr
    extra = []
    for r in short:
        w = h[first[r] : first[r + 1]]
        extra.append((sum(int(x) * (2 * j + 3) for j, x in enumerate(w)) + len(w)) % 2**64)
    out = np.insert(out, ptr[short], mix(np.array(extra, np.uint64)))
    full[short] = 1
    return out, np.concatenate([[0], np.cumsum(full)])
