"""Weighted MinHash by darts.

An element of weight w is cut into regions of unit weight and one for the rest; darts fall on a
region along a rank axis as a Poisson process that depends on the region alone, and in the last
region only those below the rest hit. Each dart aims at one coordinate, and the earliest dart of a
coordinate is its signature value: two sides agree there with the probability of their weighted
Jaccard similarity (sum of lesser weights over sum of greater ones). A text is a multiset of word
shingles: the n-th occurrence of a shingle is its n-th region.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np

_U = np.uint64
SHINGLE = 5
#: Odd constants of the mixing functions.
_A, _B, _C = _U(0x9E3779B97F4A7C15), _U(0xC2B2AE3D27D4EB4F), _U(0x165667B19E3779F9)
_P = 0x2545F4914F6CDD1D
#: Length of the first cell of the rank axis; each further cell ends at twice the one before.
CELL = 1 / 16


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _U(30))) * _U(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> _U(27))) * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


class Darts:
    def __init__(self, coordinates: int, rows: int):
        self.k, self.rows = coordinates, rows
        low = np.arange(256, dtype=np.uint8)
        low[65:91] += 32
        self.low = low
        self.is_word = np.array([48 <= b <= 57 or 97 <= b <= 122 or b >= 128 for b in low.tolist()])
        self.power = self.inverse = np.ones(0, _U)
        self.cells: list[tuple[float, float, np.ndarray]] = []

    def _powers(self, n: int) -> None:
        if len(self.power) < n:
            n = 1 << (n - 1).bit_length()
            self.power = np.cumprod(np.concatenate([[_U(1)], np.full(n - 1, _U(_P))]), dtype=_U)
            self.inverse = np.cumprod(np.concatenate([[_U(1)], np.full(n - 1, _U(pow(_P, -1, 1 << 64)))]), dtype=_U)

    def words(self, text: str) -> np.ndarray:
        """A 64-bit hash of each word (A-Z lowered)."""
        raw = self.low[np.frombuffer(text.encode(), np.uint8)]
        if not len(raw):
            return np.zeros(0, _U)
        inside = np.concatenate([[False], self.is_word[raw], [False]])
        edge = np.flatnonzero(inside[1:] != inside[:-1])
        start, end = edge[::2], edge[1::2]
        self._powers(len(raw) + 1)
        sums = np.concatenate([[_U(0)], np.cumsum((raw.astype(_U) + _U(1)) * self.power[: len(raw)], dtype=_U)])
        return mix((sums[end] - sums[start]) * self.inverse[start] + (end - start).astype(_U) * _A)

    def elements(self, words: np.ndarray) -> np.ndarray:
        """One 64-bit value for each occurrence of each shingle, sorted; fewer than SHINGLE words
        make one shingle."""
        n = len(words)
        if not n:
            return words
        width = min(n, SHINGLE)
        sh = np.zeros(n - width + 1, _U)
        for j in range(width):
            sh = (sh + words[j : n - width + 1 + j]) * _B + _C
        sh = np.sort(mix(sh))
        first = np.concatenate([[True], sh[1:] != sh[:-1]])
        at = np.arange(len(sh))
        nth = at - np.maximum.accumulate(np.where(first, at, 0))
        return np.sort(mix(sh + nth.astype(_U) * _A))

    def _cell(self, c: int) -> tuple[float, float, np.ndarray]:
        while len(self.cells) <= c:
            j = len(self.cells)
            lo, hi = (0.0, CELL) if j == 0 else (CELL * 2 ** (j - 1), CELL * 2**j)
            area = hi - lo
            top = int(area + 12 * math.sqrt(area) + 30)
            logs = np.array([x * math.log(area) - area - math.lgamma(x + 1) for x in range(top)])
            self.cells.append((lo, hi, np.cumsum(np.exp(logs))))
        return self.cells[c]

    @staticmethod
    def regions(keys: np.ndarray, weights: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(regions, part of each that is hit) of distinct 64-bit keys with weights above zero."""
        count = np.ceil(weights).astype(np.int64)
        nth = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
        part = np.minimum(np.repeat(np.asarray(weights, np.float64), count) - nth, 1.0)
        return mix(np.repeat(keys, count) + nth.astype(_U) * _A), part

    def signature(self, elements: np.ndarray, part: np.ndarray | None = None) -> np.ndarray:
        """The values of the earliest darts, by coordinate. elements: regions; part: how much of
        each may be hit, all of it unless given."""
        k = self.k
        weight = len(elements) if part is None else float(part.sum())
        reach = k * (math.log(k) + 2) / weight  # enough darts that few coordinates stay free
        best, value = np.full(k, np.inf), np.zeros(k, _U)
        c = 0
        while True:
            lo, hi, cdf = self._cell(c)
            seed = _U((c * 0x9E3779B97F4A7C15 + 0x1234567) & (2**64 - 1))
            u = (mix(elements ^ seed) >> _U(11)).astype(np.float64) * 2.0**-53
            count = np.searchsorted(cdf, u, side="right")
            total = int(count.sum())
            if total:
                who = np.repeat(np.arange(len(elements)), count)
                nth = np.arange(total) - np.repeat(np.cumsum(count) - count, count)
                dart = mix(elements[who] * _B + nth.astype(_U) * _A + seed)
                if part is not None:
                    dart = dart[(mix(dart ^ _B) >> _U(11)).astype(np.float64) * 2.0**-53 < part[who]]
                rank = lo + (hi - lo) * ((dart >> _U(11)).astype(np.float64) * 2.0**-53)
                aim = (mix(dart ^ _C) % _U(k)).astype(np.int64)
                order = np.argsort(-rank)
                aim, rank, dart = aim[order], rank[order], dart[order]
                near = np.full(k, np.inf)
                near[aim] = rank  # the last, smallest one stays
                got = np.zeros(k, _U)
                got[aim] = dart
                better = near < best
                best[better], value[better] = near[better], got[better]
            c += 1
            if hi >= reach and np.isfinite(best).all():
                return value

    def describe(self, text: str) -> tuple[bytes | None, np.ndarray, np.ndarray]:
        """Digest of the word sequence (None without words), band keys, elements."""
        words = self.words(text)
        if not len(words):
            return None, np.zeros(0, np.int64), np.zeros(0, np.int64)
        elements = self.elements(words)
        value = self.signature(elements).reshape(-1, self.rows)
        keys = np.arange(len(value)).astype(_U)
        for j in range(self.rows):
            keys = mix(keys * _B + value[:, j])
        digest = hashlib.blake2b(words.tobytes(), digest_size=16).digest()
        return digest, keys.view(np.int64), np.unique(elements).view(np.int64)
