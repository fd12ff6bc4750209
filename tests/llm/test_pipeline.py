import os
import re
import sys
import time

import duckdb
import pyarrow as pa
import pytest

import corpus_pipeline
from kgtrail.llm import op10_toxicity, queries
from kgtrail.llm.common import table, worker_state
from kgtrail.llm.kernels import spans
from kgtrail.llm.kernels.backtrack import WordBpe
from kgtrail.llm.op1_bpe import tokenizer_file

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def con():
    con = duckdb.connect()
    for f in os.listdir(SF):
        con.execute(f"create view {f.split('.')[0]} as select * from '{SF}/{f}'")
    return con


@pytest.mark.parametrize("key", sorted(queries.SQL))
def test_queries_against_duckdb(spark, con, key):
    df = queries.QUERIES[key](spark, SF)
    cols = sorted(df.columns)
    res = con.execute(queries.SQL[key])
    names = [x[0] for x in res.description]
    want = sorted(tuple(str(r[names.index(c)]) for c in cols) for r in res.fetchall())
    assert sorted(tuple(str(r[c]) for c in cols) for r in df.collect()) == want


def test_pipeline_stage_by_stage(spark, con):
    """Each stage against plain Python on the rows that reached it."""
    docs = table(spark, SF, "documents")
    model = op10_toxicity.learn(docs, table(spark, SF, "labels"))
    bad = {r["doc_id"] for r in op10_toxicity.score(docs, model).collect() if r["predicted"]}
    kept = {r["doc_id"]: r["text"] for r in docs.collect() if r["doc_id"] not in bad}
    stage = {n: f for n, f in corpus_pipeline.STAGES}
    one = stage["toxicity"](spark, docs, SF)
    assert {r["doc_id"] for r in one.collect()} == set(kept) and one.columns == docs.columns
    two = stage["near_copies"](spark, one, SF)
    ids = {r["doc_id"] for r in two.collect()}
    assert ids <= set(kept) and len({kept[i] for i in ids}) == len(ids) and two.columns == docs.columns
    three = stage["decontamination"](spark, two, SF)
    dirty = {r[0] for r in con.execute(f"select doc_id from ({queries.SQL['op2_decontaminate']}) where contaminated").fetchall()}
    assert {r["doc_id"] for r in three.collect()} == ids - dirty
    four = stage["personal_data"](spark, three, SF)
    texts = {r["doc_id"]: r["text"] for r in four.collect()}
    assert texts == {i: spans.redacted(kept[i], spans.spans(kept[i])) for i in ids - dirty}
    coder = WordBpe(open(tokenizer_file(), encoding="utf-8").read())
    assert {r["doc_id"]: r["ids"] for r in corpus_pipeline.run(spark, SF).collect()} == {i: coder.encode(t).tolist() for i, t in texts.items()}


def test_workers_hold_nothing_of_the_stage_before(spark):
    """What an operator kept in the workers is gone when the next stage begins."""

    def hold(batches):
        worker_state("held", lambda: "tables")
        time.sleep(0.5)  # so that each task has a worker of its own
        yield from batches

    def look(batches):
        time.sleep(0.5)
        for b in batches:
            yield pa.RecordBatch.from_pydict({"key": [str(getattr(sys.modules.get("_kgtrail_worker_state"), "key", None))] * b.num_rows})

    cores = spark.range(0, 4, 1, 4)
    keys = lambda: {r["key"] for r in cores.mapInArrow(look, "key string").collect()}
    cores.mapInArrow(hold, "id long").collect()
    assert "held" in keys()
    corpus_pipeline.personal_data(spark, table(spark, SF, "documents"), SF)
    assert "held" not in keys()


def test_decontamination_runs_no_python_on_executors(spark):
    """Nor does what near copies leave to it: the workers have given back before its plan is written."""
    docs = table(spark, SF, "documents")
    held = corpus_pipeline.near_copies(spark, docs, SF)
    ran, bus = spark._jsparkSession.sharedState().statusStore(), spark.sparkContext._jsc.sc().listenerBus()
    bus.waitUntilEmpty(30_000)
    before = ran.executionsCount()
    held.write.format("noop").mode("overwrite").save()
    corpus_pipeline.decontamination(spark, docs, SF).write.format("noop").mode("overwrite").save()
    bus.waitUntilEmpty(30_000)
    plans = [x.physicalPlanDescription() for x in spark._jvm.scala.jdk.javaapi.CollectionConverters.asJava(ran.executionsList(before, 1_000))]
    assert len(plans) > 5 and not [p for p in plans if re.search("Python|Pandas|Arrow", p)]
