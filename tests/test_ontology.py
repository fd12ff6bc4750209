from pyspark.sql import functions as F

from kgtrail.operators import ontology as o
from kgtrail.sources import star


def sigs(df):
    return sorted((r["head_type"], r["rel"], r["tail_type"]) for r in df.collect())


def test_completion(spark):
    holes = spark.createDataFrame([("r9", "tail")], "rel string, missing string")
    types = spark.createDataFrame([("a1", "A"), ("a2", "A"), ("a3", "A"), ("a4", "A"), ("b1", "B"), ("b2", "B"), ("c1", "C"), ("c2", "C")], "entity string, etype string")
    train = spark.createDataFrame([("a1", "r9", "b1"), ("a2", "r9", "b2"), ("a3", "r9", "c1")], "head string, rel string, tail string")
    assert sigs(o.complete_from_training(holes, train, types)) == [("A", "r9", "B")]
    more = train.union(spark.createDataFrame([("a4", "r9", "c2")], train.schema))
    assert sigs(o.complete_from_training(holes, more, types)) == []


def test_blocklist_and_completeness(spark):
    s = spark.createDataFrame([("topic_admin", "r1", "B"), ("A", "r1", "B"), ("A", "r2", None)], "head_type string, rel string, tail_type string")
    assert sigs(o.complete_only(o.drop_types(s, ["topic_admin"]))) == [("A", "r1", "B")]
    assert sigs(o.complete_only(o.drop_types(s, [], patterns=("_admin$",)))) == [("A", "r1", "B")]
    rels = spark.createDataFrame([("r1",), ("r2",), ("r3",)], "rel string")
    assert {(r["rel"], r["missing"]) for r in o.incomplete(s, rels).collect()} == {("r2", "tail"), ("r3", "both")}


def test_main_type(spark):
    obs = [("x", "y", ["film", "genre"])] + [("x", "z", ["film", "k"])] * 2 + [("x", "w", ["person", "k"]), ("v", "y", ["k", "film"])]
    t = spark.createDataFrame(obs, "topic string, answer string, type_path array<string>")
    got = {r["entity"]: r["etype"] for r in o.induce_entity_types(t).collect()}
    assert got["x"] == "film" and got["y"] == "film"  # the tie goes to the first name


def test_dominant_pair(spark):
    kg = spark.createDataFrame([(f"f{i}", "r", f"p{i}") for i in range(5)] + [(f"f{i}", "r", f"g{i}") for i in range(2)], "head string, rel string, tail string")
    types = spark.createDataFrame([(f"f{i}", "film") for i in range(5)] + [(f"p{i}", "person") for i in range(5)] + [(f"g{i}", "genre") for i in range(2)], "entity string, etype string")
    assert sigs(o.induce_signatures(kg, types)) == [("film", "r", "person")]
    assert {(r["tail_type"], r["support"]) for r in o.induce_signatures(kg, types, keep="all").collect()} == {("person", 5), ("genre", 2)}


def test_hierarchy_merges_leaves(spark):
    kg = spark.createDataFrame([("a", "r", "x"), ("b", "r", "x")], "head string, rel string, tail string")
    inst = spark.createDataFrame([("a", "leaf1"), ("b", "leaf2"), ("x", "thing")], "entity string, etype string")
    sub = spark.createDataFrame([("leaf1", "mid"), ("leaf2", "mid"), ("mid", "top")], "child string, parent string")
    assert [(r["head_type"], r["support"]) for r in o.induce_with_hierarchy(kg, inst, sub).collect()] == [("mid", 2)]
    assert {r["head_type"] for r in o.induce_with_hierarchy(kg, inst, sub, levels=2, closure=True).collect()} == {"leaf1", "leaf2", "mid", "top"}


def test_merge_prefers_declared(spark):
    row = lambda src, n: spark.createDataFrame([("A", "r", "B", n, src)], "head_type string, rel string, tail_type string, support long, source string")
    assert [r["source"] for r in o.merge(row("induced", 5), row("declared", 0), row("completed", 2)).collect()] == ["declared"]


def test_induced_equals_declared_on_the_star_graph(spark, sf):
    kg = star.triples(spark, sf)
    assert sigs(o.induce_signatures(kg, star.entity_types(kg))) == sorted((d, r, t) for r, d, t in star.declared())


def test_completion_reads_training_rows_only(spark):
    holes = spark.createDataFrame([("r9", "tail")], "rel string, missing string")
    types = spark.createDataFrame([("a1", "A"), ("b1", "B"), ("c1", "C")], "entity string, etype string")
    all_ = spark.createDataFrame([("a1", "r9", "b1", "train")] + [("a1", "r9", "c1", "test")] * 9, "head string, rel string, tail string, split string")
    assert sigs(o.complete_from_training(holes, all_.filter(F.col("split") == "train").drop("split"), types)) == [("A", "r9", "B")]
