"""A Levenshtein automaton run against a lexicon trie, determinised as texts are read."""

from __future__ import annotations

import re

import numpy as np

WORDS = re.compile(r"[^\W_]+").finditer
#: Signs of quotation, and words that report what somebody else said.
QUOTES = frozenset("\"“”„«»‘’")
REPORTS = frozenset("said says wrote writes quoted quote called reported dit écrit sagte schrieb dijo escribió".split())
#: Words on either side of a hit that its context is read from.
REACH = 6
#: Terms this long may have one letter wrong.
LONG = 5


class Lexicon:
    """terms: {text: weight}; a text that ends in * stands for all words with that beginning.
    innocent: words that are near a term but known to misspell none."""

    def __init__(self, terms: dict[str, float], innocent: list[str] | tuple[str, ...] = ()):
        self.terms, self.innocent = terms, frozenset(innocent)
        self.child: list[dict[str, int]] = [{}]
        self.whole: dict[int, str] = {}
        self.begin: dict[int, str] = {}
        self.deep = [0]
        for term in sorted(terms):
            node = 0
            for c in term.rstrip("*"):
                if c not in self.child[node]:
                    self.child[node][c] = len(self.child)
                    self.child.append({})
                    self.deep.append(self.deep[node] + 1)
                node = self.child[node][c]
            (self.begin if term.endswith("*") else self.whole)[node] = term
        self.ids: dict[frozenset, int] = {}
        self.sets: list[frozenset] = []
        self.next: list[dict[str, int]] = []
        self.start = self._state({(0, 0)})
        self.cache: dict[str, tuple[str, int] | None] = {}

    def _state(self, pairs: set[tuple[int, int]]) -> int:
        todo = [n for n, e in pairs if e == 0]
        for n in todo:  # a letter of the term left out
            pairs.update((m, 1) for m in self.child[n].values())
        pairs = frozenset((n, e) for n, e in pairs if e == 0 or (n, 0) not in pairs)
        if pairs not in self.ids:
            self.ids[pairs] = len(self.sets)
            self.sets.append(pairs)
            self.next.append({})
        return self.ids[pairs]

    def _step(self, state: int, c: str) -> int:
        to: set[tuple[int, int]] = set()
        for n, e in self.sets[state]:
            m = self.child[n].get(c)
            if m is not None:
                to.add((m, e))
            if e == 0:
                to.add((n, 1))  # a letter too many
                to.update((x, 1) for x in self.child[n].values())  # a wrong letter
        got = self.next[state][c] = self._state(to) if to else -1
        return got

    def match(self, word: str) -> tuple[str, int] | None:
        """(term, errors) of the best term that the word is or misspells."""
        state, best = self.start, None
        for c in word:
            state = self.next[state][c] if c in self.next[state] else self._step(state, c)
            if state < 0:
                return best
            if self.begin:
                for n, e in self.sets[state]:
                    if e == 0 and n in self.begin:
                        best = (self.begin[n], 0)
        known = word in self.innocent
        for n, e in sorted(self.sets[state], key=lambda x: (x[1], x[0])):
            if n in self.whole and (e == 0 or not known and (self.deep[n] >= LONG and len(word) >= LONG - 1)):
                return best if best and e else (self.whole[n], e)
        return best

    def features(self, text: str) -> list[float]:
        """Weights of the different words that hit outright, misspelled, or in reported speech only;
        then the length of the text."""
        low = text.lower()
        words = [(m.group(), m.start(), m.end()) for m in WORDS(low)]
        cache, hits = self.cache, {}
        for w in {x[0] for x in words}:
            got = cache.get(w, 0)
            if got == 0:
                if len(cache) > 100_000:
                    cache.clear()
                got = cache[w] = self.match(w)
            if got:
                hits[w] = got
        seen: dict[str, int] = {}  # the plainest use of each word counts
        if hits:
            for k, (w, a, b) in enumerate(words):
                if w not in hits:
                    continue
                lo, hi = words[max(0, k - REACH)][1], words[min(len(words) - 1, k + REACH)][2]
                told = any(x[0] in REPORTS for x in words[max(0, k - REACH) : k])
                quoted = told and QUOTES.intersection(low[lo:a]) and QUOTES.intersection(low[b:hi])
                kind = 2 if quoted else 1 if hits[w][1] else 0
                seen[w] = min(kind, seen.get(w, 2))
        sums = [0.0, 0.0, 0.0]
        for w, kind in seen.items():
            sums[kind] += self.terms[hits[w][0]] / 4
        return [*sums, float(np.log1p(len(words))) / 4]


#: Before any evidence a misspelled hit counts this part of a plain one, and a hit in reported speech this.
MISSPELLED, TOLD = 0.6, 0.3


def fit(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Bias and weights of features() by logistic regression.

    Misspelled and told hits share the weight of plain ones by the parts above, and the labels move
    them away from these only against a penalty. Where that breaks the order told <= misspelled <=
    plain, or makes one of them negative, the fit is repeated with the parts as they are."""
    tied = x[:, 0] + MISSPELLED * x[:, 1] + TOLD * x[:, 2]
    w = _logistic(np.column_stack([tied, x[:, 1], x[:, 2], x[:, 3]]), y, np.array([0.05, 20.0, 20.0, 0.05]))
    plain, wrong, told = w[1], MISSPELLED * w[1] + w[2], TOLD * w[1] + w[3]
    if not 0 < told <= wrong <= plain:
        w = _logistic(np.column_stack([tied, x[:, 3]]), y, np.array([0.05, 0.05]))
        plain = max(w[1], 0.0)
        return np.array([w[0], plain, MISSPELLED * plain, TOLD * plain, w[2]])
    return np.array([w[0], plain, wrong, told, w[4]])


def _logistic(x: np.ndarray, y: np.ndarray, ridge: np.ndarray, rounds: int = 50) -> np.ndarray:
    """Logistic regression with a bias in front, by Newton steps."""
    a = np.hstack([np.ones((len(x), 1)), x])
    w = np.zeros(a.shape[1])
    if not len(x):
        return w
    keep = np.concatenate([[1e-3], ridge])
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(a @ w, -30, 30)))
        step = np.linalg.solve((a * (p * (1 - p))[:, None]).T @ a + np.diag(keep), a.T @ (p - y) + keep * w)
        w -= np.clip(step, -4, 4)
        if np.abs(step).max() < 1e-8:
            break
    return w
