"""Rows that an operator must keep, or copies that it must find, in cases that earlier tests left out."""

import random
import zlib

from kgtrail.llm import op8_near_copies, op10_toxicity


def test_rows_without_words_stay_rows_of_their_own(spark):
    rows = [(None, None), (None, None), (1, None), (1, None), (2, "?!"), (2, "?!"), (3, "one two three four five six seven"), (3, "one two three four five six seven")]
    left = op8_near_copies.without_near_copies(spark.createDataFrame(rows, "doc_id long, text string"))
    assert sorted(((r["doc_id"], r["text"]) for r in left.collect()), key=str) == sorted(rows[:-1], key=str)


def test_edited_copies_leave_one_row_in_the_sample(spark):
    rng = random.Random(5)
    base = [f"w{rng.randrange(900)}" for _ in range(80)]
    ids = [i for i in range(300) if zlib.crc32(str(i).encode()) % 5]
    group, others = ids[:60], ids[60:70]
    rows = [(i, " ".join([f"early{i}", *base])) for i in group] + [(i, " ".join(f"x{rng.randrange(9_000)}" for _ in range(80))) for i in others]
    classes = [(i, 1 if i in group[:40] else 0) for i in group + others]
    sample = op10_toxicity.sample_of(spark.createDataFrame(rows, "doc_id long, text string"), spark.createDataFrame(classes, "doc_id long, toxic int"))
    want = [(1, dict(rows)[group[0]]), (0, dict(rows)[group[40]]), *[(0, dict(rows)[i]) for i in others]]
    assert sorted((r["toxic"], r["text"]) for r in sample.collect()) == sorted(want)
