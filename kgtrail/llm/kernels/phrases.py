"""Prefix-free parsing of texts for repeated strings of a fixed width.

Triggers are the places whose next GRAM bytes have a rolling hash divisible by MODULUS. They cut a
text into phrases that overlap by one trigger, so that no suffix of a phrase that is longer than a
trigger begins another one. The order of all suffixes of a corpus then follows from two smaller
ones: the suffix array of the dictionary of distinct phrases, and that of the parse, the sequence of
phrases. corpus_order() combines both.

To deal texts out over a cluster, each window of `width` bytes goes by its first trigger (in a window
without one by the 8 bytes with the least hash). Equal windows have equal triggers at equal
distance, so windows that may be equal meet under one key.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

_U = np.uint64
GRAM = 8
_P = 0x9E3779B97F4A7C15 | 1
#: A place in so many is a trigger.
MODULUS = 128
#: Windows of a text that are cut at once.
SEGMENT = 1 << 22
_LOW = _U((1 << 24) - 1)


def mix(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> _U(32))) * _U(0xD6E8FEB86659FD93)
    x = (x ^ (x >> _U(32))) * _U(0xD6E8FEB86659FD93)
    return x ^ (x >> _U(32))


class Hashes:
    """Hashes of stretches of one buffer, from sums of byte * P**place."""

    power = np.ones(1, _U)
    inverse = np.ones(1, _U)

    def __init__(self, raw: np.ndarray):
        n = len(raw) + 1
        if len(Hashes.power) < n:
            size = 1 << (n - 1).bit_length()
            Hashes.power = np.cumprod(np.concatenate([[_U(1)], np.full(size - 1, _U(_P))]), dtype=_U)
            Hashes.inverse = np.cumprod(np.concatenate([[_U(1)], np.full(size - 1, _U(pow(_P, -1, 1 << 64)))]), dtype=_U)
        self.sums = np.zeros(n, _U)
        np.cumsum((raw.astype(_U) + _U(1)) * Hashes.power[: n - 1], dtype=_U, out=self.sums[1:])

    def of(self, a: np.ndarray, b: np.ndarray) -> np.ndarray:
        return mix((self.sums[b] - self.sums[a]) * Hashes.inverse[a] + (b - a).astype(_U))


def rolled(raw: np.ndarray) -> np.ndarray:
    """The hash of the GRAM bytes from each place on."""
    return mix(np.ndarray(max(0, len(raw) - GRAM + 1), "<u8", np.ascontiguousarray(raw).tobytes(), strides=(1,)).astype(_U))


def triggers(raw: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(trigger, first window, last window): the windows lo..hi all have this trigger."""
    k = width - GRAM + 1
    found = []
    total = len(raw) - width + 1
    for at in range(0, total, SEGMENT):
        count = min(SEGMENT, total - at)
        part = rolled(raw[at : at + count + width - 1])
        # a trigger goes before all other places, the leftmost one first
        part = np.where(part % _U(MODULUS) == 0, _U(0), part & ~_LOW | _LOW + _U(1)) | np.arange(count + k - 1, dtype=_U)
        pad = -len(part) % k
        rows = np.concatenate([part, np.full(pad, ~_U(0))]).reshape(-1, k)
        ahead = np.minimum.accumulate(rows, axis=1).ravel()
        behind = np.minimum.accumulate(rows[:, ::-1], axis=1)[:, ::-1].ravel()
        least = (np.minimum(behind[:count], ahead[k - 1 : k - 1 + count]) & _LOW).astype(np.int64) + at
        start = np.flatnonzero(np.concatenate([[True], least[1:] != least[:-1]]))
        end = np.append(start[1:], count) - 1
        found.append((least[start], start + at, end + at))
    return tuple(np.concatenate(x) for x in zip(*found, strict=True))


def cut(text: bytes, width: int):
    """core, phrase, trigger, lo, hi: the halves of all phrases of a text.

    A window starts `left` bytes before its trigger. Windows with left >= half form the left half
    of the phrase, the others the right half; lo and hi are the least and the greatest left. All
    windows of a half share the bytes hashed in `core`; `phrase` hashes all bytes of all of them.
    """
    raw = np.frombuffer(text, np.uint8)
    half = (width - GRAM) // 2
    at, first, last = triggers(raw, width)
    lo, hi = at - last, at - first
    sides = []
    for left in (True, False):
        a, b = (np.maximum(lo, half), hi) if left else (lo, np.minimum(hi, half - 1))
        sides.append((np.flatnonzero(a <= b), a, b, left))
    h = Hashes(raw)
    out = []
    for mine, a, b, left in sides:
        t, a, b = at[mine], a[mine], b[mine]
        core = h.of(t - half, t + GRAM) if left else h.of(t, t + width - half + 1)
        phrase = mix(h.of(t - b, t - a + width) ^ (a * 512 + b).astype(_U) * _U(_P) + _U(left))
        out.append((mix(core + _U(left)), phrase, t, a, b))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def _ranked(key: np.ndarray) -> np.ndarray:
    return np.unique(key, return_inverse=True)[1].astype(_U)


def _doubled(rank: np.ndarray, depth: int, most: int, left: np.ndarray) -> np.ndarray:
    """Ranks of sequences of up to `most` items from ranks of `depth` items (from 1 on), by prefix
    doubling. left: how many items are left at each place; behind the last one all rank 0."""
    n = len(rank)
    while depth < most:
        step = min(depth, most - depth)
        later = np.concatenate([rank[step:], np.zeros(step, _U)])[:n] if step < n else np.zeros(n, _U)
        later[left <= step] = 0
        rank = _ranked(rank << _U(32) | later) + _U(1)
        depth += step
    return rank


@dataclass(frozen=True)
class Parse:
    """start, end: bytes of each phrase. word: its number in the dictionary. left: phrases of its
    text from it on. first: for each word a phrase that is it."""

    start: np.ndarray
    end: np.ndarray
    word: np.ndarray
    left: np.ndarray
    first: np.ndarray


def parse(raw: np.ndarray, begin: np.ndarray, end: np.ndarray, modulus: int = MODULUS) -> Parse:
    """Cuts the texts raw[begin:end], which lie one after another, at their triggers."""
    cut = np.flatnonzero(rolled(raw) % _U(modulus) == 0)
    text = np.searchsorted(begin, cut, side="right") - 1
    cut = cut[(cut > begin[text]) & (cut + GRAM <= end[text])]
    text = np.searchsorted(begin, cut, side="right") - 1
    start = np.sort(np.concatenate([begin, cut]))
    owner = np.searchsorted(begin, start, side="right") - 1
    last = np.append(owner[1:] != owner[:-1], True)
    stop = np.where(last, end[owner], np.append(start[1:], 0) + GRAM)
    left = np.searchsorted(owner, owner, side="right") - np.arange(len(start))
    # phrases by hash, then byte by byte against the first of their kind
    key = mix(Hashes(raw).of(start, stop) + last.astype(_U) * _U(_P))
    _, first, word = np.unique(key, return_index=True, return_inverse=True)
    size, model = stop - start, first[word]
    alike = bool((size == size[model]).all()) and bool((last == last[model]).all())
    if alike:
        step = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
        alike = bool((raw[np.repeat(start, size) + step] == raw[np.repeat(start[model], size) + step]).all())
    if not alike:  # two phrases of one hash: each is a word of its own, which costs room but no result
        first = word = np.arange(len(start))
    return Parse(start, stop, word, left, first)


#: Bytes in a first rank of the dictionary's suffixes, in 9 bits each, as an end ranks before all.
_PACKED = 7


def corpus_order(raw: np.ndarray, begin: np.ndarray, end: np.ndarray, depth: int, modulus: int = MODULUS) -> np.ndarray:
    """For each place of raw a number: their order is that of the suffixes of the texts
    raw[begin:end], to a depth of `depth` bytes at least; an end of a text comes before any byte."""
    cut = parse(raw, begin, end, modulus)
    # the dictionary: its words one after another, each with an end mark if it ends a text
    size = (cut.end - cut.start)[cut.first]
    closing = (cut.left == 1)[cut.first]
    room = size + closing + _PACKED
    at = np.cumsum(room) - room
    letters = np.zeros(int(room.sum()) + _PACKED, _U)
    step = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
    letters[np.repeat(at, size) + step] = raw[np.repeat(cut.start[cut.first], size) + step].astype(_U) + _U(2)
    letters[(at + size)[closing]] = 1
    n = len(letters) - _PACKED
    packed = np.zeros(n, _U)
    for j in range(_PACKED):
        packed = packed << _U(9) | letters[j : j + n]
    left = np.repeat(at + size + closing, room) - np.arange(n)
    suffix = _doubled(_ranked(packed) + _U(1), _PACKED, max(depth, _PACKED), left)
    # the parse: phrases by the rank of the whole word, then sequences of them
    later = _doubled(suffix[at[cut.word]], 1, depth, cut.left)
    after = np.append(later[1:], _U(0))
    after[cut.left == 1] = 0
    phrase = np.searchsorted(cut.start, np.arange(len(raw)), side="right") - 1
    inside = suffix[at[cut.word[phrase]] + np.arange(len(raw)) - cut.start[phrase]]
    return inside << _U(32) | after[phrase]


def equal_places(raw: np.ndarray, begin: np.ndarray, end: np.ndarray, places: np.ndarray, width: int, modulus: int = MODULUS) -> np.ndarray:
    """A number for each of the places, the same exactly for those with equal next `width` bytes:
    neighbours in corpus order are compared byte by byte. Each place has `width` bytes left."""
    order = np.argsort(corpus_order(raw, begin, end, width, modulus)[places], kind="stable")
    placed = places[order]
    words = np.ndarray(max(0, len(raw) - 7), "<u8", np.ascontiguousarray(raw).tobytes(), strides=(1,))
    same = np.ones(len(placed), bool)
    same[:1] = False
    alive = np.arange(1, len(placed))
    for at in [*range(0, width - 7, 8), width - 8]:
        alive = alive[words[placed[alive] + at] == words[placed[alive - 1] + at]]
    same[1:] = False
    same[alive] = True
    out = np.empty(len(places), np.int64)
    out[order] = np.cumsum(~same)
    return out


def ranks(raw: np.ndarray, width: int) -> np.ndarray:
    """equal_places of one text, for every place; those too near the end are like no other."""
    n = max(0, len(raw) - width + 1)
    bounds = np.array([0]), np.array([len(raw)])
    return np.concatenate([equal_places(raw, *bounds, np.arange(n), width), np.arange(n, len(raw)) + len(raw)])


def shared(texts: list[bytes], lo: np.ndarray, hi: np.ndarray, many: np.ndarray, width: int) -> list[list[tuple[int, int]]]:
    """For each dictionary phrase the runs (least left, greatest left) of windows that occur in
    another place. many: whether the phrase itself occurs more than once."""
    raw = np.frombuffer(b"".join(texts), np.uint8)
    sizes = np.array([len(t) for t in texts], np.int64)
    begin = np.cumsum(sizes) - sizes
    count = hi - lo + 1
    owner = np.repeat(np.arange(len(texts)), count)
    step = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)  # 0 is the greatest left
    left = hi[owner] - step
    place = begin[owner] + step
    key = equal_places(raw, begin, begin + sizes, place, width)
    _, inverse, times = np.unique(key, return_inverse=True, return_counts=True)
    often = times > 1
    np.logical_or.at(often, inverse[many[owner]], True)
    hit = often[inverse]
    out: list[list[tuple[int, int]]] = [[] for _ in texts]
    at = np.flatnonzero(hit)
    if len(at):
        new = np.concatenate([[True], (at[1:] != at[:-1] + 1) | (owner[at[1:]] != owner[at[:-1]])])
        starts = at[new]
        ends = at[np.append(np.flatnonzero(new)[1:], len(at)) - 1]
        for s, e in zip(starts.tolist(), ends.tolist(), strict=True):
            out[owner[s]].append((int(left[e]), int(left[s])))
    return out


def union(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    done: list[list[int]] = []
    for a, b in sorted(spans):
        if done and a <= done[-1][1]:
            done[-1][1] = max(done[-1][1], b)
        else:
            done.append([a, b])
    return [(a, b) for a, b in done]
