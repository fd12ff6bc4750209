"""Resharding: least bytes against the optimum, and which files it touches."""

import itertools
import os
import random
import zlib

import pytest
from pyspark.sql import functions as F

from kgtrail.llm import op5_reshard
from kgtrail.llm.common import new_path


def old_of(i, shards):
    return zlib.crc32(str(i).encode()) % shards


def optimum(sizes, new):
    """Fewest bytes over all choices of which shards keep one row more. sizes: those of each shard."""
    total = sum(map(len, sizes))
    low, more = divmod(total, new)
    best = None
    for extra in itertools.combinations(range(new), more):
        moved = 0
        for j, mine in enumerate(sizes):
            room = low + (j in extra) if j < new else 0
            moved += sum(sorted(mine)[: max(0, len(mine) - room)])
        best = moved if best is None else min(best, moved)
    return best


@pytest.mark.parametrize(("n", "old", "new", "top"), [(157, 3, 5, 400), (160, 5, 3, 12), (211, 4, 4, 3000), (3, 2, 5, 50)])
def test_fewest_bytes(spark, n, old, new, top):
    rng = random.Random(n)
    rows = [(i, "x" * rng.randint(0, top)) for i in range(n)]
    shards, plan = op5_reshard.reshard(spark.createDataFrame(rows, "doc_id long, text string").repartition(3), old_shards=old, new_shards=new)
    got = shards.collect()
    assert sorted((r["doc_id"], r["text"]) for r in got) == rows
    counts = [sum(r["shard"] == j for r in got) for j in range(new)]
    assert sum(counts) == n and max(counts) - min(counts) <= 1
    for j in range(new):
        assert sorted(r["slot"] for r in got if r["shard"] == j) == list(range(counts[j]))
    moved = sum(r["size"] for r in got if old_of(r["doc_id"], old) != r["shard"])
    assert moved == plan.bytes == optimum([[len(t) + 8 for i, t in rows if old_of(i, old) == j] for j in range(old)], new)
    assert sum(t[2] for t in plan.transfers) == sum(old_of(r["doc_id"], old) != r["shard"] for r in got)


def test_equal_rows_are_cut_exactly(spark):
    rows = [(7, "same text")] * 500 + [(None, None)] * 400
    shards, _ = op5_reshard.reshard(spark.createDataFrame(rows, "doc_id long, text string").repartition(4), old_shards=3, new_shards=7)
    got = shards.collect()
    assert sorted(map(str, ((r["doc_id"], r["text"]) for r in got))) == sorted(map(str, rows))
    assert {r["n"] for r in shards.groupBy("shard").agg(F.count("*").alias("n")).collect()} == {128, 129}
    assert len({(r["shard"], r["slot"]) for r in got}) == 900


def test_only_affected_files_change(spark):
    path = new_path(spark, "shards-test")
    ids = {j: [i for i in range(900) if old_of(i, 3) == j][:k] for j, k in ((0, 60), (1, 50), (2, 40))}
    docs = spark.createDataFrame([(i, "t" * (i % 90)) for j in ids for i in ids[j]], "doc_id long, text string").repartition(2)
    op5_reshard.lay_out(docs, f"{path}/old", 3)
    here = path.removeprefix("file://")
    files = lambda top: {j: sorted((f, os.path.getmtime(f"{here}/{top}/shard={j}/{f}")) for f in os.listdir(f"{here}/{top}/shard={j}")) for j in range(3) if os.path.isdir(f"{here}/{top}/shard={j}")}
    before = files("old")
    plan = op5_reshard.solve(op5_reshard.measure(spark, f"{path}/old", 3), 3)
    assert (plan.losing, plan.affected) == ({0}, {0, 2}) and plan.transfers == [(0, 2, 10)]
    op5_reshard.rewrite(spark, f"{path}/old", plan, f"{path}/new")
    after = files("old")
    assert 0 not in after and after[1] == before[1] and after[2] == before[2]
    assert sorted(files("new")) == [0, 2]
    got = op5_reshard.read_shards(spark, [f"{path}/old", f"{path}/new"])
    assert sorted(r["doc_id"] for r in got.collect()) == sorted(i for j in ids for i in ids[j])
