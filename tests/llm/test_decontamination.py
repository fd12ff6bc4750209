"""The positional index: shuffled windows, several scans, repeated terms, brute force."""

import collections
import random

from kgtrail.llm import op2_decontaminate as op


def frame(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string")


def items(spark, texts):
    return spark.createDataFrame(list(enumerate(texts)), "item_id long, text string")


def close(text, window, slop):
    """Starts of the first stretch for every place of a word of the window, by plain counting."""
    words, want = text.split(), collections.Counter(window)
    return any(not want - collections.Counter(words[s : s + len(window) + slop]) for s in range(len(words)))


def test_proximity_in_any_order_against_brute_force(spark):
    rng = random.Random(3)
    window = [f"t{i}" for i in range(11)] + ["the", "the"]
    docs = [(0, " ".join(reversed(window))), (1, " ".join(window)), (2, " ".join(window[:-1]))]
    for i in range(3, 80):
        words = window[:]
        rng.shuffle(words)
        for _ in range(rng.randint(0, 6)):
            words.insert(rng.randrange(len(words)), "the" if rng.random() < 0.3 else f"x{rng.randrange(9)}")
        docs.append((i, " ".join([f"x{rng.randrange(9)}" for _ in range(rng.randint(0, 40))] + words)))
    got = {r["doc_id"] for r in op.proximity_matches(frame(spark, docs), items(spark, [" ".join(window)])).collect()}
    assert got == {i for i, t in docs if close(t, window, 3)} and {0, 1} <= got and 2 not in got
    none = {r["doc_id"] for r in op.proximity_matches(frame(spark, docs), items(spark, [" ".join(window)]), slop=0).collect()}
    assert none == {i for i, t in docs if close(t, window, 0)} != got


def test_many_terms_take_several_scans(spark, monkeypatch):
    rng = random.Random(5)
    vocab = [f"w{i}" for i in range(60)]
    tests = [" ".join(rng.choice(vocab) for _ in range(rng.randint(3, 20))) for _ in range(12)]
    docs = [(i, " ".join(rng.choice(vocab) for _ in range(30)) + " " + (tests[i % 12] if i % 4 == 0 else "end")) for i in range(60)] + [(60, None), (None, tests[0]), (1, "w1 " * 500)]
    run = lambda: sorted(map(str, op.decontaminate(frame(spark, docs), items(spark, tests)).collect()))
    want = run()
    assert sum("contaminated=True" in r for r in want) >= 15
    monkeypatch.setattr(op, "BROADCAST_ROWS", 7)
    assert run() == want
    monkeypatch.setattr(op, "BROADCAST_ROWS", 0)
    assert run() == want


def test_a_window_of_one_word_and_of_equal_words(spark):
    docs = frame(spark, [(1, "b a a a"), (2, "a b a"), (3, "c"), (4, "")])
    got = {r["doc_id"]: (r["n_hit"], r["n_items"]) for r in op.decontaminate(docs, items(spark, ["a a", "c", "zzz"])).collect()}
    assert got == {1: (3, 1), 2: (0, 0), 3: (1, 1), 4: (0, 0)}
    near = sorted((r["doc_id"], r["phrase"]) for r in op.proximity_matches(docs, items(spark, ["a a", "c"]), slop=1).select("doc_id", "phrase").distinct().collect())
    assert near == [(1, "a a"), (2, "a a"), (3, "c")]


def test_words_are_split_and_not_matched_one_by_one(spark):
    import re

    from pyspark.sql import functions as F

    from kgtrail.llm.common import WORD_ANY_CASE

    texts = ["", " ", "one", " lead and trail. ", "..a..B", "a\n\tb\r\n c\x00d\x7fe", "İstanbul ÄÖ 東京,x 😀y_z", "A" * 50 + " 1-2", None]
    df = frame(spark, list(enumerate(texts))).withColumn("ws", op.words(F.col("text")))
    assert {r["doc_id"]: r["ws"] for r in df.collect()} == {i: re.findall(WORD_ANY_CASE, t or "") for i, t in enumerate(texts)}
    assert "regexp_extract_all" not in df._jdf.queryExecution().toString()
