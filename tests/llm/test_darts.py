"""Weighted signatures, and recall of near copies on a given table."""

import collections
import re

import numpy as np

from kgtrail.llm import op8_near_copies
from kgtrail.llm.kernels.darts import Darts


def test_signatures_agree_as_often_as_weights_overlap():
    d = Darts(512, 4)
    rng = np.random.default_rng(6)
    for spread in (0.1, 0.6, 2.0):
        want, got = [], []
        for _ in range(20):
            keys = rng.integers(0, 2**63, 150).astype(np.uint64)
            a = rng.exponential(1.5, 150) + 0.01
            b = a * np.exp(spread * rng.standard_normal(150))
            want.append(np.minimum(a, b).sum() / np.maximum(a, b).sum())
            got.append((d.signature(*d.regions(keys, a)) == d.signature(*d.regions(keys, b))).mean())
        assert abs(np.mean(got) - np.mean(want)) < 0.02
    keys = np.array([3, 9], np.uint64)
    whole, part = d.regions(keys, np.array([2.0, 0.5]))
    assert len(whole) == 3 and part.tolist() == [1.0, 1.0, 0.5]


def test_every_similar_pair_of_a_given_table_is_in_one_class(spark, sf):
    docs = spark.read.parquet(f"{sf.replace('0.001', '0.01')}/documents.parquet")
    classes = {r["doc_id"]: r["class_id"] for r in op8_near_copies.near_copies(docs).collect()}
    sets, where = {}, collections.defaultdict(list)
    for r in docs.collect():
        low = (r["text"] or "").translate(str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))
        words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)
        k = min(5, len(words))
        if words:
            sets[r["doc_id"]] = collections.Counter(tuple(words[i : i + k]) for i in range(len(words) - k + 1))
            for gram in sets[r["doc_id"]]:
                where[gram].append(r["doc_id"])
    pairs = {(a, b) for ids in where.values() for a in ids for b in ids if a < b}
    similar = [(a, b) for a, b in pairs if (c := sum((sets[a] & sets[b]).values())) >= 0.8 * (sum(sets[a].values()) + sum(sets[b].values()) - c)]
    assert len(similar) > 20
    assert [p for p in similar if classes[p[0]] != classes[p[1]]] == []
