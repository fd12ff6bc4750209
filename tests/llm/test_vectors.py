"""Vectors: rows that share a vec_id, extreme numbers, borders of tasks, and recall on large labels."""

import collections
import math

import numpy as np

from kgtrail.llm import op9_embeddings


def brute(rows, least=0.98):
    """n_links and component of each row, all rows being nodes of their own."""
    x = np.array([np.array(v, float) / np.abs(v).max() for _, v, _ in rows])
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    label = np.array([c for *_, c in rows])
    alike = (x @ x.T >= least) & (label[:, None] == label[None, :])
    np.fill_diagonal(alike, False)
    comp = list(range(len(rows)))
    for start in range(len(rows)):
        todo = [start] if comp[start] == start else []
        while todo:
            k = todo.pop()
            for j in np.flatnonzero(alike[k]).tolist():
                if comp[j] > start:
                    comp[j] = start
                    todo.append(j)
    name = collections.defaultdict(lambda: math.inf)
    for k, (i, *_) in enumerate(rows):
        name[comp[k]] = min(name[comp[k]], i)
    return sorted((i, int(alike[k].sum()), name[comp[k]], i == name[comp[k]]) for k, (i, *_) in enumerate(rows))


def got(spark, rows, **options):
    df = spark.createDataFrame([(*r, "q") for r in rows], "vec_id long, embedding array<double>, label int, node string")
    return sorted((r["vec_id"], r["n_links"], r["component_id"], r["kept"]) for r in op9_embeddings.near_vectors(df, **options).collect())


def test_vectors_that_share_a_vec_id_and_huge_numbers(spark):
    rows = [(5, [1.0, 0.0], 0), (5, [0.0, 1.0], 0), (7, [1.0, 0.001], 0), (8, [0.001, 1.0], 0), (9, [1e200, 0.0], 1), (10, [1e200, 1e190], 1), (11, [1e-300, 0.0], 1), (12, [-1.0, 0.0], 1)]
    want = brute(rows)
    assert [r[1] for r in want] == [1, 1, 1, 1, 2, 2, 2, 0]
    assert got(spark, rows) == want


def test_links_counts_and_components_against_brute_force(spark):
    rng = np.random.default_rng(3)
    base = rng.standard_normal((12, 16))
    rows = [(i, (base[i % 12] + 0.12 * rng.standard_normal(16)).tolist(), i % 3 // 2) for i in range(240)]
    rows += [(300 + i, rows[i][1], rows[i][2]) for i in range(20)] + [rows[0], rows[0]]
    assert got(spark, rows, block=16, count_block=8) == brute(rows)


def test_passes_rise_and_recall_holds(spark):
    assert op9_embeddings.passes_for(100) == op9_embeddings.PASSES < op9_embeddings.passes_for(10**7) < op9_embeddings.passes_for(10**9) < 60
    rng = np.random.default_rng(4)
    n, d = 20_000, 32
    x = rng.standard_normal((n, d)) + 0.5
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    turn = rng.standard_normal((n // 2, d))
    turn -= (turn * x[: n // 2]).sum(1, keepdims=True) * x[: n // 2]
    turn /= np.linalg.norm(turn, axis=1, keepdims=True)
    x[n // 2 :] = 0.982 * x[: n // 2] + math.sqrt(1 - 0.982**2) * turn  # pairs just over the threshold
    df = spark.createDataFrame([(i, v.tolist(), 0) for i, v in enumerate(x)], "vec_id long, embedding array<double>, label int")
    small = 64  # as many blocks as a label of 160,000 has at the usual size
    rows = op9_embeddings.near_vectors(df, block=small).collect()
    found = sum(r["n_links"] for r in rows) / 2
    alike = sum(int((x[k : k + 1000] @ x.T >= 0.98).sum()) for k in range(0, n, 1000))
    assert found / ((alike - n) / 2) >= 0.97
