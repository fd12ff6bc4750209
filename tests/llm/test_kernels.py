import random
import re

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from kgtrail.llm.kernels import phrases, simple8b, spans
from kgtrail.llm.kernels.backtrack import WordBpe
from kgtrail.llm.kernels.darts import Darts
from kgtrail.llm.kernels.flow import Flow
from kgtrail.llm.kernels.lexicon import Lexicon
from kgtrail.llm.op3_token_files import byte_encoder

ODD = ["", " ", "a" * 3000, "ab" * 2000, "<|startoftext|>x<|endoftext|>y", "don't we'll I'M", "ΑΣ ς İ ß é é 中文 🙂 ½ Ⅷ ٣", "\x00\x1f\x7f\t\n", "'s's''s"]


def texts(n=1500):
    rng = random.Random(4)
    letters = "aab  'sΣΑİßé́ñ中文0123½Ⅷ٣!?.\n\t  <|endoftext|>🙂_-"
    return ODD + ["".join(rng.choice(letters) for _ in range(rng.randint(1, 80))) for _ in range(n)]


def test_word_bpe_is_the_library():
    path = public_tokenizers.path("word_bpe_49k.json")
    ours, theirs = WordBpe(open(path, encoding="utf-8").read()), Tokenizer.from_file(path)
    for text in texts():
        want = theirs.encode(text, add_special_tokens=False).ids
        got = ours.encode(text)
        assert got.tolist() == want, text
        assert ours.decode(got).decode() == theirs.decode(want, skip_special_tokens=False)


def test_byte_bpe_is_the_library():
    path = public_tokenizers.path("byte_bpe_50k.json")
    ours, theirs = byte_encoder(open(path, encoding="utf-8").read()), Tokenizer.from_file(path)
    for text in texts():
        assert ours.encode(text, allowed_special="all") == theirs.encode(text, add_special_tokens=False).ids, text


@pytest.mark.parametrize("n", [0, 1, 2, 59, 60, 61, 1000])
@pytest.mark.parametrize("top", [1, 2, 50257, 2**32 - 1, 2**61, 2**64 - 1])
def test_simple8b_round_trip(n, top):
    v = np.random.default_rng(n).integers(0, top, n, dtype=np.uint64)
    assert (simple8b.unpack(simple8b.pack(v), n) == v).all()


def test_spans_against_plain_patterns():
    rng = random.Random(2)
    for _ in range(5000):
        t = "".join(rng.choice("ab@@..1 2-+34()é") for _ in range(rng.randint(0, 40)))
        want = [("email", *m.span()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
        want += [("ip", *m.span()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(x) <= 255 for x in m[0].split("."))]
        for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
            d = re.sub("[^0-9]", "", m[0])
            if 13 <= len(d) <= 19 and spans.luhn(d):
                want.append(("card", *m.span()))
        want += [("phone", *m.span()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 9 <= len(re.sub("[^0-9]", "", m[0])) <= 15]
        assert spans.base_spans(t) == want, t


def test_checksums_context_and_redaction():
    assert spans.luhn("4111111111111111") and not spans.luhn("4111111111111112")
    assert spans.mod97("GB82 WEST 1234 5698 7654 32") and not spans.mod97("GB82WEST12345698765433")
    assert [s[0] for s in spans.spans("IBAN GB82 WEST 1234 5698 7654 32.")] == ["iban"]
    assert spans.spans("nr 123-45-6789") == [] and spans.spans("ssn 123-45-6789")[0][0] == "ssn"
    low, high = spans.spans("1.2.3.4")[0][3], spans.spans("server 1.2.3.4")[0][3]
    assert high > low
    text = "mail a@b.co, call +1 (988) 555-2485"
    assert spans.redacted(text, spans.spans(text)) == "mail [EMAIL], call [PHONE]"
    long = "9" * 300 + ".1.1.1"
    assert all(k != "ip" for k, *_ in spans.base_spans(long))


def test_automaton():
    lex = Lexicon({"idiot": 1.0, "vequ*": 1.0, "scum": 1.0})
    assert lex.match("idiot") == ("idiot", 0) and lex.match("idi0t") == ("idiot", 1)
    assert lex.match("idiiot") == ("idiot", 1) and lex.match("idit") == ("idiot", 1)
    assert lex.match("vequxyz") == ("vequ*", 0) and lex.match("scam") is None and lex.match("idxxt") is None
    plain, wrong, told, _ = lex.features("You idiot.")
    assert plain > 0 and wrong == told == 0
    plain, wrong, told, _ = lex.features('He said "you idiot" and left')
    assert told > 0 and plain == 0


def test_automaton_against_distances():
    def lev(a, b):
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            old, row = row, [i]
            for j, y in enumerate(b, 1):
                row.append(min(old[j] + 1, row[-1] + 1, old[j - 1] + (x != y)))
        return row[-1]

    rng = random.Random(5)
    terms = ["abcab", "bcabc", "aabbcc"]
    lex = Lexicon(dict.fromkeys(terms, 1.0))
    for _ in range(4000):
        w = "".join(rng.choice("abc") for _ in range(rng.randint(1, 8)))
        best = min(lev(w, t) for t in terms)
        got = lex.match(w)
        assert (got is not None) == (best <= 1), w
        if got:
            assert got[1] == best == lev(w, got[0])


def test_darts_estimate_similarity():
    d = Darts(512, 4)
    rng = np.random.default_rng(1)
    for share in (0.2, 0.5, 0.8):
        agree = []
        for _ in range(15):
            both = rng.integers(0, 2**63, 400).astype(np.uint64)
            k = int(400 * share)
            rest = rng.integers(0, 2**63, 2 * (400 - k)).astype(np.uint64)
            a, b = np.concatenate([both[:k], rest[: 400 - k]]), np.concatenate([both[:k], rest[400 - k :]])
            agree.append((d.signature(np.sort(a)) == d.signature(np.sort(b))).mean())
        assert abs(np.mean(agree) - k / (800 - k)) < 0.03
    assert (d.signature(np.array([7], np.uint64)) == d.signature(np.array([7], np.uint64))).all()


def test_triggers_and_ranks():
    rng = random.Random(1)
    text = "".join(rng.choice("ab") for _ in range(700)).encode()
    raw = np.frombuffer(text, np.uint8)
    at, first, last = phrases.triggers(raw, 40)
    assert first[0] == 0 and last[-1] == len(raw) - 40 and (first[1:] == last[:-1] + 1).all()
    assert (at >= last).all() and (at + 8 <= first + 40).all()
    rank = phrases.ranks(raw, 40)
    seen = {}
    for k in range(len(raw) - 39):
        assert seen.setdefault(text[k : k + 40], rank[k]) == rank[k]
    assert len(set(rank[: len(raw) - 39].tolist())) == len(seen)


def test_flow_finds_the_cheapest_way():
    f = Flow(4)
    cheap, dear = f.arc(0, 1, 5, 1), f.arc(0, 2, 5, 3)
    f.arc(1, 3, 3, 1)
    f.arc(2, 3, 5, 1)
    back = f.arc(1, 2, 9, 1)
    assert f.run(0, 3, 6) == 6
    assert (f.used(cheap), f.used(dear), f.used(back)) == (5, 1, 2)
    assert f.run(0, 3, 99) == 2
