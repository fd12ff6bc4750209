"""Queries over all rows, held against their DuckDB twins with the twins' own thinning taken out here."""

import os

import duckdb
import pytest

from kgtrail.operators import workload
from kgtrail.registry import load, oracle_sql, queries

load()
TENTHS = [(f"(select greatest(1, count(*) // 10) from {t})", "1") for t in ("customer", "part")]


SEVENTHS = [(f"{t} where {k} % 7 = 0", t) for t, k in (("customer", "c_custkey"), ("part", "p_partkey"))]


def norm(v):
    return f"{v:.9g}" if isinstance(v, float) or type(v).__name__ == "Decimal" else str(v)


def against(spark, sf, key, cuts):
    con = duckdb.connect()
    for f in os.listdir(sf):
        con.execute(f"create view {f.split('.')[0]} as select * from '{sf}/{f}'")
    sql = oracle_sql()[key]
    for old, new in cuts:
        sql = sql.replace(old, new)
    df = queries()[key](spark, sf)
    cols = sorted(df.columns)
    res = con.execute(sql)
    names = [x[0] for x in res.description]
    assert sorted(names) == cols
    want = sorted(tuple(norm(r[names.index(c)]) for c in cols) for r in res.fetchall())
    assert sorted(tuple(norm(r[c]) for c in cols) for r in df.collect()) == want
    return want


@pytest.mark.parametrize("name", [t.name for t in workload.TEMPLATES])
def test_templates_ask_about_all_topics(spark, sf, name):
    against(spark, sf, name, TENTHS)


@pytest.mark.parametrize("key", ["dataset_stats", "oneshot_sample", "type_top_m", "type_chain_logp", "type_accuracy", "type_cross_entropy", "type_knn_predict"])
def test_statistics_and_predictors_take_all_questions(spark, sf, key):
    against(spark, sf, key, SEVENTHS)


@pytest.mark.parametrize("key", ["br_oneshot", "backbone_grid"])
def test_predictors_are_trained_on_all_questions(spark, sf, key, monkeypatch):
    made, ask = [], workload.questions
    monkeypatch.setattr(workload, "questions", lambda *a, **b: made.append(ask(*a, **b)) or made[-1])
    queries()[key](spark, sf)
    assert max(q.filter("template = 'w_customer_nation'").count() for q in made) == 150


def test_text_similarity_of_all_turns_and_items(spark, sf):
    against(spark, sf, "w_text_similarity", [(" and conv_id % 10 = 0", ""), (" where item_id < 20", "")])


LINEAR = {"w_light_1hop": [("doc_id % 100 in (0, 1, 2) and ", "")], "topic_lookup": [(" where c_custkey % 5 = 0", "")], "join_full": [(" where doc_id % 2 = 0", ""), (" where doc_id % 3 = 0", "")]}


@pytest.mark.parametrize("key", LINEAR)
def test_linear_joins_take_all_rows(spark, sf, key):
    against(spark, sf, key, LINEAR[key])
