"""Corpus order from dictionary and parse against a plain suffix array; windows against counting."""

import random

import numpy as np
import pytest

from kgtrail.llm.kernels import phrases


def corpus(alphabet, n, seed):
    rng = random.Random(seed)
    base = ["".join(rng.choice(alphabet) for _ in range(rng.randint(9, 300))) for _ in range(6)]
    texts = ["".join(rng.choice(base)[rng.randint(0, 9) :] for _ in range(rng.randint(1, 4))).encode() for _ in range(n)]
    texts += [texts[0], b"x", texts[1][5:]]
    size = np.array([len(t) for t in texts])
    end = np.cumsum(size)
    return texts, np.frombuffer(b"".join(texts), np.uint8), end - size, end


@pytest.mark.parametrize(("alphabet", "n", "modulus"), [("ab", 12, 4), ("abcdefgh ", 20, 16), ("a", 4, 4), ("abc", 8, 1), ("xyz", 9, 10**9)])
def test_combined_order_is_the_suffix_array(alphabet, n, modulus):
    texts, raw, begin, end = corpus(alphabet, n, modulus)
    key = phrases.corpus_order(raw, begin, end, int(max(end - begin)) + 1, modulus)
    order = np.argsort(key, kind="stable")
    owner = np.searchsorted(begin, order, side="right") - 1
    suffixes = [texts[o][p - begin[o] :] for p, o in zip(order.tolist(), owner.tolist(), strict=True)]
    assert suffixes == sorted(suffixes)
    got = key[order]
    assert [bool(a == b) for a, b in zip(got, got[1:])] == [a == b for a, b in zip(suffixes, suffixes[1:])]


@pytest.mark.parametrize("modulus", [1, 4, 128])
def test_equal_places_are_equal_windows(modulus):
    texts, raw, begin, end = corpus("abcd", 15, modulus)
    width = 40
    places = np.concatenate([np.arange(b, max(b, e - width + 1)) for b, e in zip(begin, end, strict=True)])
    number, seen = phrases.equal_places(raw, begin, end, places, width, modulus), {}
    for p, k in zip(places.tolist(), number.tolist(), strict=True):
        assert seen.setdefault(raw[p : p + width].tobytes(), k) == k
    assert len(seen) == len(set(number.tolist()))


def test_phrases_overlap_by_a_trigger_and_no_suffix_begins_another():
    texts, raw, begin, end = corpus("abc", 10, 3)
    cut = phrases.parse(raw, begin, end, 8)
    words = {raw[a:b].tobytes() + (b"$" if left == 1 else b"") for a, b, left in zip(cut.start, cut.end, cut.left, strict=True)}
    assert len(words) == len(cut.first) < len(cut.start)
    tails = {w[k:] for w in words for k in range(len(w) - phrases.GRAM) if not w.endswith(b"$")}
    assert not [(x, y) for x in tails for y in tails if x != y and y.startswith(x)]


def test_phrases_of_a_corpus_are_joined_without_sorting_them(spark, monkeypatch):
    from kgtrail.llm import op7_repeats as op

    plans, keep = {}, op.stored

    def seen(df, name):
        plans[name] = df._jdf.queryExecution().executedPlan().toString()
        return keep(df, name)

    monkeypatch.setattr(op, "stored", seen)
    same = "".join(f"{i % 97} word " for i in range(80))
    texts = spark.createDataFrame([(1, "first " + same), (2, "second one " + same), (3, "alone " * 9)], "row long, text string")
    threshold = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", -1)
    try:
        spans = op.repeated_spans(texts).collect()
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", threshold)
    assert {r["row"] for r in spans} == {1, 2}
    assert not [n for n in ("repeated-cores", "dictionary") if "Sort" in plans[n]]
