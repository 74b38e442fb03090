"""Words and word shingles of Arrow text columns as NumPy arrays.

A word is a maximal run of bytes other than space and \\x09-\\x0D. Hashes are 64 bits wide
and depend only on a word's bytes, so every executor computes the same ones.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa

from gridchain.llm.shared import mix64, text_bytes

SEPARATOR = np.zeros(256, bool)
SEPARATOR[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32
_BASE = 0x9E3779B97F4A7C15
_INVERSE = pow(_BASE, -1, 1 << 64)
_tables: dict[str, np.ndarray] = {}


def _powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """base^i and base^-i modulo 2^64 for i up to n."""
    if len(_tables.get("up", ())) <= n:
        size = max(1 << 20, n + 1)
        for name, base in (("up", _BASE), ("down", _INVERSE)):
            steps = np.full(size, np.uint64(base))
            steps[0] = 1
            _tables[name] = np.cumprod(steps, dtype=np.uint64)
    return _tables["up"], _tables["down"]


class Words:
    """Word bounds (`starts`, `ends` into `data`) of a text column; `docs` is each word's row."""

    def __init__(self, column: pa.Array, lower: bool = False):
        raw, cuts = text_bytes(column)
        self._total = None
        self.raw, self.cuts = raw, cuts
        self.data = LOWER[raw] if lower else raw
        gap = SEPARATOR[raw]
        n = len(raw)
        first = np.ones(n + 1, bool)
        first[1:n] = gap[:-1]
        first[cuts[cuts < n]] = True
        last = np.ones(n + 1, bool)
        last[: n - 1] = gap[1:]
        ends = cuts[1:]
        last[ends[ends > 0] - 1] = True
        self.starts = np.flatnonzero(first[:n] & ~gap)
        self.ends = np.flatnonzero(last[:n] & ~gap) + 1
        self.docs = np.searchsorted(cuts, self.starts, side="right") - 1
        self.rows = len(cuts) - 1
        self.first_word = np.searchsorted(self.docs, np.arange(self.rows + 1))
        self.counts = np.diff(self.first_word)

    def hashes(self, most: int = 0) -> np.ndarray:
        """Hash of each word, or of its first `most` bytes."""
        n = len(self.data)
        up, down = _powers(n)
        if self._total is None:
            self._total = np.zeros(n + 1, np.uint64)
            np.cumsum((self.data.astype(np.uint64) + np.uint64(1)) * up[:n], out=self._total[1:])
            self._from, self._down = self._total[self.starts], down[self.starts]
        ends = np.minimum(self.ends, self.starts + most) if most else self.ends
        value = (self._total[ends] - self._from) * self._down
        return mix64(value ^ ((ends - self.starts).astype(np.uint64) << np.uint64(48)))


_STEPS = [np.uint64(x) for x in (0xA0761D6478BD642F, 0xE7037ED1A0B428DB, 0x8EBC6AF09C88C6E3, 0x589965CC75374CC3, 0x1D8E4E27C47D124F, 0xEB44ACCAB455D165, 0x9C6E6877736C46E3, 0x2D358DCCAA6C78A5)]


def sliding(take, values: np.ndarray, width: int) -> np.ndarray:
    """Least or largest (take) of each `width` successive values, by doubling."""
    n, have = len(values) - width + 1, 1
    while have * 2 <= width:
        values = take(values[:-have], values[have:])
        have *= 2
    return take(values[:n], values[width - have : width - have + n])


def join_hashes(hashes: np.ndarray, size: int) -> np.ndarray:
    """Hash of each run of `size` successive word hashes."""
    n = len(hashes) - size + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.full(n, np.uint64(size))
    for k in range(size):
        out = out * _STEPS[0] + (hashes[k : k + n] ^ _STEPS[k % 8]) * _STEPS[(k + 1) % 8]
    return mix64(out)


def group_shingles(hashes: np.ndarray, first: np.ndarray, size: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Shingles of consecutive word groups (group g has words first[g]..first[g+1]).

    Returns (hashes, groups). A group with 1..size-1 words has its whole sequence as one
    shingle; an empty group has none.
    """
    counts = np.diff(first)
    groups = np.repeat(np.arange(len(counts)), counts)
    runs = join_hashes(hashes, size)
    inside = groups[: len(runs)] == groups[size - 1 :] if len(runs) else np.zeros(0, bool)
    out, owner = [runs[inside]], [groups[: len(runs)][inside]]
    for k in range(1, size):
        short = np.flatnonzero(counts == k)
        if len(short):
            whole = np.full(len(short), np.uint64(0x5851F42D4C957F2D + k))
            for j in range(k):
                whole = mix64(whole * _STEPS[2] + hashes[first[short] + j])
            out.append(whole)
            owner.append(short)
    return np.concatenate(out), np.concatenate(owner)


def distinct_sets(hashes: np.ndarray, owners: np.ndarray, rows: int) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct hashes of each owner: (hashes, cuts)."""
    order = np.lexsort((hashes, owners)) if len(hashes) else np.zeros(0, np.int64)
    hashes, owners = hashes[order], owners[order]
    keep = np.ones(len(hashes), bool)
    keep[1:] = (hashes[1:] != hashes[:-1]) | (owners[1:] != owners[:-1])
    hashes, owners = hashes[keep], owners[keep]
    return hashes, np.searchsorted(owners, np.arange(rows + 1))


def shingle_sets(column: pa.Array, size: int = 5) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of each lower-cased text: (hashes, cuts)."""
    w = Words(column, lower=True)
    hashes, owners = group_shingles(w.hashes(), w.first_word, size)
    return distinct_sets(hashes, owners, w.rows)
