"""Exact BPE by backtracking over longest token matches.

A piece is written in an alphabet of base symbols, one character each. One Aho-Corasick pass gives,
for each place, the tokens that start there. The encoder takes the longest one whose pairing with
the token before it is stable under the merges, and steps back where none fits; a place found
hopeless is never tried again, so the work is linear in the piece.
"""

from __future__ import annotations

import json
import re
import unicodedata

import ahocorasick
import numpy as np
import regex

#: The byte-level alphabet prints these bytes as themselves, the others from U+0100 on.
PRINTED = [*range(33, 127), *range(161, 173), *range(174, 256)]


def byte_letters() -> list[str]:
    rest = iter(range(256, 512))
    shown = set(PRINTED)
    return [chr(b) if b in shown else chr(next(rest)) for b in range(256)]


#: Unicode white space, which Python's \\s exceeds by the separators U+001C to U+001F.
WHITE = "\t-\r \x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000"
SPACES = re.compile(f"[{WHITE}]+")


class WordBpe:
    """Encoder and decoder for a tokenizer file (JSON text) of the word-end BPE kind: NFC, blanks
    joined, lower case, no decoder. Files that normalise otherwise are refused."""

    MAX_CACHED = 400_000

    def __init__(self, text: str):
        spec = json.loads(text)
        model = spec["model"]
        kinds = [x["type"] for x in (spec["normalizer"] or {}).get("normalizers", [])]
        if kinds != ["NFC", "Replace", "Lowercase"] or spec["decoder"] or not model.get("end_of_word_suffix"):
            raise ValueError("not a word-end tokenizer file that composes, joins blanks and lowers")
        self.end = model.get("end_of_word_suffix") or ""
        vocab: dict[str, int] = model["vocab"]
        merges = [m if isinstance(m, list) else m.split(" ") for m in model["merges"]]
        letters = byte_letters()
        # base symbols: a byte inside a piece is chr(byte), the last byte of a piece chr(256 + byte)
        code = {x: chr(b) for b, x in enumerate(letters)}
        last = {x + self.end: chr(256 + b) for b, x in enumerate(letters)} if self.end else {}

        def spelled(token: str) -> str:
            if self.end and token.endswith(self.end):
                body = token[: -len(self.end)]
                return "".join(code[c] for c in body[:-1]) + last[body[-1] + self.end]
            return "".join(code[c] for c in token)

        self.rank: dict[int, int] = {}
        self.parts: dict[int, tuple[int, int]] = {}
        self.merged: dict[tuple[int, int], int] = {}
        for k, (a, b) in enumerate(merges):
            new = vocab[a + b]
            pair = (vocab[a], vocab[b])
            self.merged.setdefault(pair, k)
            if new not in self.parts:
                self.parts[new], self.rank[new] = pair, k
        self.machine = ahocorasick.Automaton()
        self.length: dict[int, int] = {}
        for token, i in vocab.items():
            if i in self.parts or token in code or token in last:
                s = spelled(token)
                self.length[i] = len(s)
                self.machine.add_word(s, i)
        self.machine.make_automaton()
        self.special = {x["content"]: x["id"] for x in spec["added_tokens"]}
        self.split = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        pattern = next(p["pattern"]["Regex"] for p in spec["pre_tokenizer"]["pretokenizers"] if p["type"] == "Split")
        self.pieces = regex.compile(pattern.replace(r"\s", r"\p{White_Space}")).findall
        self.stable: dict[int, bool] = {}
        self.cache: dict[str, bytes] = {}
        names = {i: t for t, i in [*vocab.items(), *self.special.items()]}
        top = max(names) + 1
        self.token_table = OffsetTable([names.get(i, "").encode() for i in range(top)], b" ")
        self.number_table = OffsetTable([str(i).encode() for i in range(top)], b" ")

    def fits(self, left: int, right: int) -> bool:
        """True if the merges, run over the two tokens' symbols, leave the border between them.
        The tokens facing each other across the border are followed back in time: the younger one
        is undone first, and a pair that would have merged before that moment breaks the border."""
        key = left << 32 | right
        known = self.stable.get(key)
        if known is not None:
            return known
        rank, parts, merged = self.rank.get, self.parts, self.merged.get
        before, fine = len(self.merged), True
        before += 1
        while True:
            at = merged((left, right))
            if at is not None and at < before:
                fine = False
                break
            l_age, r_age = rank(left, -1), rank(right, -1)
            if l_age < 0 and r_age < 0:
                break
            if l_age > r_age:
                before, left = l_age, parts[left][1]
            else:  # of equal merges the one further left goes first
                before, right = r_age + 1, parts[right][0]
        if len(self.stable) > 800_000:
            self.stable.clear()
        self.stable[key] = fine
        return fine

    def encode_piece(self, piece: str) -> list[int]:
        raw = piece.encode()
        word = raw.decode("latin-1")
        if self.end:
            word = word[:-1] + chr(256 + raw[-1])
        n = len(word)
        starts: list[list[int]] = [[] for _ in range(n)]
        length, fits = self.length, self.fits
        for end, i in self.machine.iter(word):
            starts[end + 1 - length[i]].append(i)  # ends ascend, so lengths do
        out: list[int] = []
        tried = [len(x) for x in starts]
        dead = bytearray(n + 1)
        at = 0
        while at < n:
            here, k = starts[at], tried[at]
            placed = False
            while k:
                k -= 1
                i = here[k]
                to = at + length[i]
                if not dead[to] and (not out or fits(out[-1], i)):
                    tried[at] = k
                    out.append(i)
                    at = to
                    placed = True
                    break
            if not placed:
                dead[at] = 1
                if not out:
                    raise ValueError("the vocabulary lacks a base symbol")
                tried[at] = len(here)
                at -= length[out.pop()]
            elif at < n:
                tried[at] = len(starts[at])
        return out

    def encode(self, text: str) -> np.ndarray:
        cache, chunks = self.cache, []
        for k, part in enumerate(self.split.split(text) if self.split else [text]):
            if k % 2:
                chunks.append(np.uint32(self.special[part]).tobytes())
                continue
            if not part:
                continue
            # the library lowers character by character, so no final sigma
            part = SPACES.sub(" ", unicodedata.normalize("NFC", part)).replace("Σ", "σ").lower()
            for piece in self.pieces(part):
                got = cache.get(piece)
                if got is None:
                    got = np.array(self.encode_piece(piece), np.uint32).tobytes()
                    if len(piece) <= 64:
                        if len(cache) >= self.MAX_CACHED:
                            cache.clear()
                        cache[piece] = got
                chunks.append(got)
        return np.frombuffer(b"".join(chunks), np.uint32)

    def decode(self, ids: np.ndarray) -> bytes:
        """Token texts joined by a space, as the library does for a file without a decoder."""
        return self.token_table.joined(ids)


class OffsetTable:
    """Texts in one buffer with their offsets; joined() copies many at once without a loop."""

    def __init__(self, texts: list[bytes], glue: bytes):
        self.glue = len(glue)
        self.buffer = np.frombuffer(b"".join(t + glue for t in texts), np.uint8)
        self.size = np.array([len(t) + len(glue) for t in texts], np.int64)
        self.start = np.cumsum(self.size) - self.size

    def joined(self, ids: np.ndarray) -> bytes:
        out = []
        for lo in range(0, len(ids), 1 << 18):  # bounded memory for very long texts
            part = ids[lo : lo + (1 << 18)]
            size = self.size[part]
            to = np.cumsum(size)
            index = np.arange(to[-1]) + np.repeat(self.start[part] - (to - size), size)
            out.append(self.buffer[index].tobytes())
        got = b"".join(out)
        return got[: len(got) - self.glue] if len(ids) else b""
