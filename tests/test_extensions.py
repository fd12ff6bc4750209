"""Extension points, sinks, the planner's fall-backs, and rows that come too late."""

import datetime

import pytest
from pyspark.sql import functions as F

from kgtrail.functions import external
from kgtrail.operators import metrics, refine, workload
from kgtrail.registry import queries
from kgtrail.sources import files
from kgtrail.sources.star import table
from kgtrail.streaming import events as stream
from tests.test_surface import test_against_duckdb as against_duckdb

KEYS = ["udf_path_f1", "udf_path_support", "udf_grouped_verdict", "udtf_expand_paths", "udf_replies", "udf_encoder", "agg_sketch_merge", "x_overall", "x_retrieval_only", "x_ablation", "x_by_hops", "br_oneshot"]


@pytest.mark.parametrize("key", KEYS)
def test_queries(spark, sf, key):
    against_duckdb(spark, sf, key)


def test_table_function_refuses_a_large_graph(spark, monkeypatch):
    monkeypatch.setattr(external, "MOST_EDGES", 1)
    with pytest.raises(ValueError, match="edges"):
        external.register_expand_paths(spark, spark.createDataFrame([("a", "r", "b"), ("b", "r", "c")], "head string, rel string, tail string"))


def test_planner_falls_back_to_sort_and_object_aggregates(spark, sf):
    orders = table(spark, sf, "orders")
    assert "ObjectHashAggregate" in metrics.plan_text(orders.groupBy("o_custkey").agg(F.collect_set("o_orderpriority")))
    assert "SortAggregate" in metrics.plan_text(orders.groupBy("o_custkey").agg(F.max("o_orderpriority")))
    plain = metrics.plan_text(orders.groupBy("o_custkey").agg(F.sum("o_totalprice")))
    assert "HashAggregate" in plain and "SortAggregate" not in plain and "ObjectHashAggregate" not in plain


@pytest.mark.parametrize("kind", ["parquet", "orc"])
def test_columnar_sinks(spark, tmp_path, kind):
    df = spark.createDataFrame([("a", "r", "b"), ("b", "s", "c")], "head string, rel string, tail string")
    files.write_columnar(df, str(tmp_path / kind), kind, "rel")
    assert sorted(map(tuple, spark.read.format(kind).load(str(tmp_path / kind)).select("head", "rel", "tail").collect())) == sorted(map(tuple, df.collect()))


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    at = lambda h: datetime.datetime(2024, 1, 2, h)
    src, seen = str(tmp_path / "in"), []
    rows = lambda hs, k: spark.createDataFrame([(k + i, at(h), 1, "view", 0.0, "{}") for i, h in enumerate(hs)], stream.SCHEMA.replace("timestamp_ntz", "timestamp")).withColumn("ts", F.col("ts").cast("timestamp_ntz")).coalesce(1)

    def run():
        s = stream.counts(stream.read_events(spark, src, late="1 hour"), "1 hour")
        q = s.writeStream.foreachBatch(lambda batch, _: seen.extend(r["n"] for r in batch.collect())).outputMode("update").option("checkpointLocation", str(tmp_path / "cp")).trigger(availableNow=True).start()
        q.awaitTermination(120)
        return stream.dropped_rows(q)

    rows([1, 10, 10, 12], 0).write.mode("append").parquet(src)
    assert run() == 0
    rows([2, 3, 12], 10).write.mode("append").parquet(src)  # the watermark stands at 11:00
    assert run() == 2
    assert sorted(seen) == [1, 1, 2, 2]  # the update mode gives a window again when it changes


def test_rate_source_has_the_shape_of_events(spark):
    feed = stream.rate_events(spark)
    assert feed.isStreaming and feed.columns == [x.split()[0] for x in stream.SCHEMA.split(", ")]


def test_second_round_brings_supported_answers_that_the_first_left_out(spark):
    """Fixed and adaptive rounds: one round ends on an unsupported answer, two mend it, three cost more."""
    from pyspark.sql.types import StructType

    q = spark.createDataFrame([(1, "which parts", "t", [("answer", "size", ">", "5")]), (2, "which parts", "t", [("answer", "size", ">", "5")])], "qid long, text string, topic string, constraints array<struct<target:string,rel:string,op:string,value:string>>")
    rows = [(1, 1, ["r"], ["t", "a"], "a", "t|r|a", 0.9, 1), (1, 1, ["s"], ["t", "b"], "b", "t|s|b", 0.4, 2), (2, 1, ["r"], ["t", "b"], "b", "t|r|b", 0.9, 1)]
    p0 = spark.createDataFrame(rows, "qid long, len int, rels array<string>, nodes array<string>, tail string, path_key string, score double, rank int")
    facts = spark.createDataFrame([("a", "size", "3"), ("b", "size", "9")], "entity string, attr string, value string")
    assert isinstance(p0.schema, StructType)
    run = lambda **o: {r["qid"]: (r["y_ref"], r["rounds"]) for r in refine.run(q, p0, refine.RuleGenerator(0.05), refine.RuleRefiner(facts), **o).collect()}
    assert run(max_rounds=1) == {1: (["a"], 1), 2: (["b"], 1)}
    assert run() == {1: (["b"], 2), 2: (["b"], 1)}
    assert run(adaptive=False) == {1: (["b"], 3), 2: (["b"], 3)}


def test_typed_search_looks_up_no_entity_types(spark, sf):
    from kgtrail.plans import retrieve
    from kgtrail.queries.common import asked, gold_type, graph

    q, g = asked(spark, sf, "w_customer_brands"), graph(spark, sf)
    assert "/types]" in metrics.plan_text(g.entity_types)
    for mask in (False, True):
        paths = retrieve.bidirectional(q, gold_type(q), g.triples, g.entity_types, g.signatures, retrieve.Config(depth=3, use_mask=mask))
        assert "/types]" not in metrics.plan_text(paths)


def test_all_limits_of_rounds_come_from_one_trace(spark):
    """What is cut from one trace is what a run to each limit gives."""
    path = lambda q, key, tail, score, rank: (q, 1, ["r"], ["s", tail], tail, f"{q}{key}", score, rank)
    rows = [path(1, "p1", "a", 0.9, 1), path(1, "p2", "b", 0.5, 2), path(2, "p1", "b", 0.9, 1), path(3, "p1", "a", 0.9, 1), path(3, "p2", "b", 0.9, 2)]
    p0 = spark.createDataFrame(rows, "qid long, len int, rels array<string>, nodes array<string>, tail string, path_key string, score double, rank int")
    held = [("answer", "kind", "=", "good")]
    q = spark.createDataFrame([(i, held) for i in (1, 2, 3, 4)], "qid long, constraints array<struct<target:string,rel:string,op:string,value:string>>")
    facts = spark.createDataFrame([("a", "kind", "bad"), ("b", "kind", "good"), ("c", "kind", "good")], "entity string, attr string, value string")
    made = q, p0, refine.RuleGenerator(0.05), refine.RuleRefiner(facts)
    found = refine.trace(*made)
    for options in ({}, {"max_rounds": 1}, {"max_rounds": 2}, {"max_rounds": 2, "adaptive": False}, {"adaptive": False}):
        assert sorted(map(str, refine.cut(found, **options).collect())) == sorted(map(str, refine.run(*made, **options).collect()))
    assert {r["qid"]: r["rounds"] for r in refine.cut(found).collect()} == {1: 2, 2: 1, 3: 2, 4: 0}


@pytest.mark.parametrize("key, most", [("pick_rounds", 2), ("tradeoff_rounds", 3), ("tradeoff_rounds_narrow", 3)])
def test_rounds_and_gold_are_made_once(spark, sf, key, most, monkeypatch):
    """No mode repeats the rounds of another, nor the answers from the raw tables."""
    written, golds, write, gold = [], [], refine.stored, workload.gold
    monkeypatch.setattr(refine, "stored", lambda df, name: written.append(name) or write(df, name))
    monkeypatch.setattr(workload, "gold", lambda *a, **b: golds.append(1) or gold(*a, **b))
    rows = queries()[key](spark, sf).collect()
    assert written.count("round") <= most and len(golds) == 1 and len(rows) in (1, 3)


def test_few_questions_leave_the_answers_as_they_are(spark, sf):
    names = sorted(workload.BOUGHT) + ["w_suppliers_in_nation"]
    q = workload.questions(spark, sf, names, step=5)
    assert sorted(map(str, workload.gold(spark, sf, q, few=True).collect())) == sorted(map(str, workload.gold(spark, sf, q).collect()))
