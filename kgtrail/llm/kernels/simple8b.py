"""Simple-8b: unsigned numbers packed into 64-bit words, coded and decoded with numpy."""

from __future__ import annotations

import numpy as np

#: Fixed values of the format: selector k + 1 packs COUNTS[k] numbers of 60 // COUNTS[k] bits.
COUNTS = (1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 15, 20, 30, 60)
#: Selector 0: an escape; the number itself, over 60 bits wide, is the next word.
ESCAPE = 0
_LOW = np.uint64((1 << 60) - 1)


def pack(values: np.ndarray) -> np.ndarray:
    """uint64 words for the values; the count must be kept beside them, as the tail is padded."""
    values = np.ascontiguousarray(values, np.uint64)
    n = len(values)
    if not n:
        return np.zeros(0, np.uint64)
    padded = np.concatenate([values, np.zeros(64, np.uint64)])
    width = np.zeros(n + 64, np.uint8)
    rest = padded.copy()
    for s in (32, 16, 8, 4, 2, 1):  # bits by halving
        big = rest >= np.uint64(1 << s)
        width[big] += s
        rest[big] >>= np.uint64(s)
    width += rest.astype(np.uint8)
    best = np.zeros(n, np.uint8)  # selector; 0 escapes
    widest, reach = width.copy(), 1  # the greatest width among the next `reach` numbers
    for k, count in enumerate(COUNTS):
        while reach < count:
            step = min(reach, count - reach)
            moved = widest.copy()
            np.maximum(widest[: len(widest) - step], widest[step:], out=moved[: len(widest) - step])
            widest, reach = moved, reach + step
        best[widest[:n] <= 60 // count] = k + 1
    # follow the greedy jumps; each step is one stored word
    jump = np.array((1, *COUNTS), np.int64)[best].tolist()
    at, places = 0, []
    while at < n:
        places.append(at)
        at += jump[at]
    places = np.array(places, np.int64)
    chosen = best[places]
    slots = np.cumsum(1 + (chosen == ESCAPE)) - (1 + (chosen == ESCAPE))
    words = np.zeros(slots[-1] + 1 + (chosen[-1] == ESCAPE), np.uint64)
    for k, count in enumerate(COUNTS):
        mine = np.flatnonzero(chosen == k + 1)
        if not len(mine):
            continue
        bits, word = 60 // count, np.full(len(mine), np.uint64((k + 1) << 60))
        for j in range(count):
            word |= padded[places[mine] + j] << np.uint64(bits * j)
        words[slots[mine]] = word
    wide = np.flatnonzero(chosen == ESCAPE)
    words[slots[wide] + 1] = padded[places[wide]]
    return words


def unpack(words: np.ndarray, n: int) -> np.ndarray:
    """The first n values, as uint64."""
    words = np.ascontiguousarray(words, np.uint64)
    if not n:
        return np.zeros(0, np.uint64)
    selector = (words >> np.uint64(60)).astype(np.int64)
    raw = np.zeros(len(words) + 1, bool)
    for k in np.flatnonzero(selector == ESCAPE).tolist():  # a raw word may look like an escape
        if not raw[k]:
            raw[k + 1] = True
    raw = raw[:-1]
    counts = np.array((1, *COUNTS, 0), np.int64)[np.minimum(selector, 15)]
    counts[raw] = 0
    at = np.cumsum(counts) - counts
    out = np.zeros(int(counts.sum()) + 64, np.uint64)
    for s, count in enumerate(COUNTS):
        mine = np.flatnonzero((selector == s + 1) & ~raw)
        if not len(mine):
            continue
        bits = 60 // count
        mask = np.uint64((1 << bits) - 1)
        for j in range(count):
            out[at[mine] + j] = (words[mine] >> np.uint64(bits * j)) & mask
    wide = np.flatnonzero((selector == ESCAPE) & ~raw)
    out[at[wide]] = words[wide + 1]
    return out[:n]
