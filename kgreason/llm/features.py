"""Hashed word and character n-gram features of a text, and sparse rows of them.

Four blocks of hashed counts, all of the lower-cased text: words; pairs of neighbouring words; the first 3 to 7 code points
of each word; and the 2 and 3 code points that follow each word.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import xxhash

BITS = 17
SIZE = 1 << BITS
BLOCKS = 4
TOTAL = BLOCKS * SIZE

_PUNCTUATION = bytes(c if chr(c).isalnum() or c >= 128 else 32 for c in range(256))
#: Whether a code point below 384 ends a word; higher ones never do.
_BREAKS = np.array([not chr(c).isalnum() for c in range(0x180)])

_SAME = b"\0same"  # stands for a word that repeats the one before


def _folded(h: np.ndarray, block: int) -> np.ndarray:
    return (h >> np.uint32(32 - BITS)).astype(np.int64) + block * SIZE


def _grams(points: np.ndarray, at: np.ndarray, n: int) -> np.ndarray:
    """32-bit hashes of the n code points from each place on."""
    h = points[at]
    for j in range(1, n):
        h = (h * np.uint32(0x01000193)) ^ points[at + j]
    h = h * np.uint32(2 * n + 1)
    return (h ^ (h >> np.uint32(15))) * np.uint32(0x9E3779B1)


def hashed(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """(indexes, values): distinct features, ascending, and one plus the logarithm of their counts."""
    low = (text or "").lower()
    words = low.encode("utf-8", "surrogatepass").translate(_PUNCTUATION).split()
    found = []
    if words:
        h = np.fromiter(map(xxhash.xxh32_intdigest, words), np.uint32, len(words))
        found.append(_folded(h, 0))
        pairs = ((h[:-1] * np.uint32(0x85EBCA6B)) ^ h[1:]) * np.uint32(0x9E3779B1)
        found.append(_folded(pairs, 1))
        same = int((h[1:] == h[:-1]).sum())
        if same:
            found.append(np.full(same, xxhash.xxh32_intdigest(_SAME) >> (32 - BITS), np.int64))
    points = np.frombuffer(low.encode("utf-32-le", "surrogatepass"), np.uint32)
    if len(points):
        breaks = _BREAKS[np.minimum(points, len(_BREAKS) - 1)]
        at = np.flatnonzero(~breaks & np.concatenate(([True], breaks[:-1])))
        for n in range(2, 8):  # words of n code points at least
            at = at[at + n <= len(points)]
            at = at[~breaks[at + n - 1]]
            if n > 2:
                found.append(_folded(_grams(points, at, n), 2))
        ends = np.flatnonzero(breaks & np.concatenate(([False], ~breaks[:-1])))
        for n in (2, 3):
            found.append(_folded(_grams(points, ends[ends + n <= len(points)], n), 3))
    if not found:
        return np.zeros(0, np.int32), np.zeros(0, np.float32)
    index, count = np.unique(np.concatenate(found), return_counts=True)
    return index.astype(np.int32), (1 + np.log(count)).astype(np.float32)


#: A feature counts in training from so many rows on; rarer ones only let a row be learnt by heart.
MIN_ROWS = 5


@dataclass
class Rows:
    """Sparse rows, one behind the other."""

    index: np.ndarray
    value: np.ndarray
    ends: np.ndarray

    @classmethod
    def of(cls, rows: list[tuple[np.ndarray, np.ndarray]]) -> Rows:
        ends = np.cumsum([len(i) for i, _ in rows]).astype(np.int64)
        return cls(np.concatenate([i for i, _ in rows]) if rows else np.zeros(0, np.int32), np.concatenate([v for _, v in rows]) if rows else np.zeros(0, np.float32), ends)

    def __len__(self) -> int:
        return len(self.ends)

    def sizes(self) -> np.ndarray:
        return np.diff(np.concatenate(([0], self.ends)))

    def take(self, at: np.ndarray) -> Rows:
        starts = np.concatenate(([0], self.ends[:-1]))
        parts = [np.arange(starts[i], self.ends[i]) for i in at]
        flat = np.concatenate(parts) if parts else np.zeros(0, np.int64)
        return Rows(self.index[flat], self.value[flat], np.cumsum([len(p) for p in parts]).astype(np.int64))

    def dot(self, weights: np.ndarray) -> np.ndarray:
        sums = np.concatenate(([0.0], np.cumsum(self.value * weights[self.index], dtype=np.float64)))
        return np.diff(sums[np.concatenate(([0], self.ends))])

    def back(self, errors: np.ndarray, size: int) -> np.ndarray:
        """Sum of rows times errors."""
        return np.bincount(self.index, weights=self.value * np.repeat(errors, self.sizes()), minlength=size)


def learnable(rows: Rows, least: int = MIN_ROWS) -> bool:
    """Whether any feature stands in enough rows to count."""
    return len(rows.index) > 0 and int(np.bincount(rows.index).max()) >= least


def _chunks(rows: Rows, size: int = 512):
    """(first row, rows) by so many at a time, as views."""
    for i in range(0, len(rows), size):
        start, ends = rows.ends[i - 1] if i else 0, rows.ends[i : i + size]
        yield i, Rows(rows.index[start : ends[-1]], rows.value[start : ends[-1]], ends - start)


def evidence(rows: Rows, y: np.ndarray, classes: int, least: int = MIN_ROWS) -> np.ndarray:
    """For each feature how much its presence tells of a class: the largest log ratio of its shares inside and outside a class.

    0 for features of fewer than ``least`` rows.
    """
    held = np.zeros((classes, TOTAL), np.int32)
    for i, part in _chunks(rows):
        grade = np.repeat(y[i : i + len(part)], part.sizes())
        for k in range(classes):
            held[k] += np.bincount(part.index[grade == k], minlength=TOTAL).astype(np.int32)
    n, total = np.bincount(y, minlength=classes), held.sum(axis=0)
    out = np.zeros(TOTAL)
    for k in range(classes):
        inside, outside = (held[k] + 1) / (n[k] + 2), (total - held[k] + 1) / (n.sum() - n[k] + 2)
        out = np.maximum(out, np.abs(np.log(inside / outside)))
    out[total < least] = 0
    return out.astype(np.float32)


def scaled(rows: Rows, scale: np.ndarray) -> tuple[Rows, np.ndarray]:
    """(rows, features): values times scale with each row at length 1, without features of scale 0; indexes count those in ``features``."""
    features = np.flatnonzero(scale)
    number = np.zeros(TOTAL, np.int32)
    number[features] = np.arange(len(features))
    indexes, values, sizes = [np.zeros(0, np.int32)], [np.zeros(0, np.float32)], [np.zeros(0, np.int64)]
    for _, part in _chunks(rows):
        keep = scale[part.index] > 0
        owner, index = np.repeat(np.arange(len(part)), part.sizes())[keep], part.index[keep]
        value = part.value[keep] * scale[index]
        length = np.sqrt(np.bincount(owner, weights=value * value, minlength=len(part)))
        indexes.append(number[index])
        values.append((value / np.where(length > 0, length, 1)[owner]).astype(np.float32))
        sizes.append(np.bincount(owner, minlength=len(part)))
    return Rows(np.concatenate(indexes), np.concatenate(values), np.cumsum(np.concatenate(sizes)).astype(np.int64)), features


@dataclass
class Scorer:
    """Linear scores of texts: weights of scaled features, of rows at length 1."""

    weights: np.ndarray
    scale: np.ndarray

    @classmethod
    def of(cls, weights: np.ndarray, features: np.ndarray, scale: np.ndarray) -> Scorer:
        whole = np.zeros(TOTAL, np.float32)
        whole[features] = weights
        return cls(whole, scale)

    def score(self, text: str | None) -> float:
        """0 for a text without known features."""
        index, value = hashed(text)
        own = value * self.scale[index]
        length = float(np.sqrt(np.dot(own, own)))
        return float(np.dot(own, self.weights[index])) / length if length else 0.0

    def scores(self, texts: list[str | None]) -> np.ndarray:
        return np.array([self.score(t) for t in texts], dtype=np.float64)
