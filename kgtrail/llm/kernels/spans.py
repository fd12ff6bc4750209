"""Personal data in a text: patterns propose, checksums confirm, nearby words adjust the score."""

from __future__ import annotations

import re

#: Kinds in the order of the digest, with their score before context.
KINDS = {"email": 0.9, "ip": 0.6, "card": 0.9, "phone": 0.6, "iban": 0.9, "ssn": 0.3, "secret": 0.8}
#: Words that, shortly before a span, speak for its kind.
HINTS = {
    "email": ("mail", "contact", "write to"),
    "ip": ("ip", "host", "server", "address"),
    "card": ("card", "credit", "visa", "pay"),
    "phone": ("phone", "call", "tel", "fax", "mobile"),
    "iban": ("iban", "account", "bank", "konto"),
    "ssn": ("ssn", "social security"),
    "secret": ("key", "secret", "token", "password", "credential", "login"),
}
#: Words that speak against any kind.
DOUBTS = ("version", "order", "isbn", "example only", "figure")
#: Characters before a span in which such words are looked for, as whole words.
REACH = 40
#: Added kinds are kept from this score on; the base kinds always are.
LEAST = 0.5

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
# a match can only begin where a run of digits does, so no run is walked twice
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_IBAN = re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?:\x20?[A-Z0-9]){11,30}(?![A-Za-z0-9])")
_SSN = re.compile(r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])")
#: Access keys by their fixed prefix, and long values given to a name that says secret.
_KEY = re.compile(r"(?<![A-Za-z0-9])(?:AKIA|ASIA)[A-Z0-9]{16}(?![A-Za-z0-9])")
_GIVEN = re.compile(r"(?<![A-Za-z0-9])(?:password|passwd|pwd|secret|token|api[_-]?key|access[_-]?key)\s{0,3}[=:]\s{0,3}[\"']?([A-Za-z0-9+/_-]{12,200})(?![A-Za-z0-9+/_-])", re.IGNORECASE)
_NOT_DIGIT = re.compile(r"[^0-9]")


def _any_of(words: tuple[str, ...]) -> re.Pattern:
    return re.compile(r"(?<![^\W_])(?:" + "|".join(map(re.escape, words)) + r")(?![^\W_])")


_HINTED = {kind: _any_of(words) for kind, words in HINTS.items()}
_DOUBTED = _any_of(DOUBTS)


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        d = int(c) * (1 + k % 2)
        total += d - 9 * (d > 9)
    return total % 10 == 0


def mod97(iban: str) -> bool:
    plain = iban.replace(" ", "")
    return int("".join(str(int(c, 36)) for c in plain[4:] + plain[:4])) % 97 == 1


def emails(text: str):
    """The leftmost matches of local@domain: each @ is tried with the run of local characters
    before it, so a long run without @ costs nothing."""
    at, free = text.find("@"), 0
    while at >= 0:
        start = at
        while start > free and text[start - 1] in _LOCAL:
            start -= 1
        found = _DOMAIN.match(text, at + 1) if start < at else None
        if found:
            yield start, found.end()
            free = found.end()
            at = text.find("@", free)
        else:
            at = text.find("@", at + 1)


def base_spans(text: str) -> list[tuple[str, int, int]]:
    found = [("email", a, b) for a, b in emails(text)]
    found += [("ip", *m.span()) for m in _IP.finditer(text) if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m[0].split("."))]
    for m in _CARD.finditer(text):
        if m.end() - m.start() >= 13:
            digits = _NOT_DIGIT.sub("", m[0])
            if 13 <= len(digits) <= 19 and luhn(digits):
                found.append(("card", *m.span()))
    if "+" in text:
        found += [("phone", *m.span()) for m in _PHONE.finditer(text) if 9 <= len(_NOT_DIGIT.sub("", m[0])) <= 15]
    return found


def context(text: str, kind: str, start: int) -> float:
    # one character more than REACH shows whether the first word is whole
    before = text[max(0, start - REACH - 1) : start].lower()
    first = int(start > REACH)
    return 0.3 * bool(_HINTED[kind].search(before, first)) - 0.3 * bool(_DOUBTED.search(before, first))


def secret_like(value: str) -> bool:
    """Letters and at least three digits: no word of a language, no plain number."""
    digits = sum(c.isdigit() for c in value)
    return digits >= 3 and digits < len(value)


def spans(text: str) -> list[tuple[str, int, int, float]]:
    """(kind, start, end, score) by kind in the order of KINDS, then by start. Base kinds are never
    dropped by their score; the added kinds need a checksum, a hint or the shape of a secret."""
    rows = [(k, a, b, min(1.0, max(0.0, KINDS[k] + context(text, k, a)))) for k, a, b in base_spans(text)]
    added = [("iban", *m.span()) for m in _IBAN.finditer(text) if mod97(m[0])]
    added += [("ssn", *m.span()) for m in _SSN.finditer(text)]
    given = {m.span(1) for m in _GIVEN.finditer(text) if secret_like(m[1])} if "=" in text or ":" in text else set()
    added += [("secret", a, b) for a, b in sorted(given | {m.span() for m in _KEY.finditer(text)})]
    for k, a, b in added:
        score = min(1.0, max(0.0, KINDS[k] + context(text, k, a)))
        if score >= LEAST:
            rows.append((k, a, b, score))
    return rows


def redacted(text: str, found: list[tuple[str, int, int, float]]) -> str:
    """The text with each span, overlapping ones joined, replaced by its kind in brackets."""
    out, at = [], 0
    for kind, a, b, _ in sorted(found, key=lambda x: (x[1], -x[2])):
        if a >= at:
            out += [text[at:a], f"[{kind.upper()}]"]
        at = max(at, b)
    return "".join(out) + text[at:]
