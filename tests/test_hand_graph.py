import pytest
from pyspark.sql import functions as F

from kgtrail.operators import baselines, metrics, rank, refine, supervision
from kgtrail.plans import expand, retrieve
from kgtrail.plans.retrieve import Config
from tests import hand


@pytest.fixture(scope="module")
def g(spark):
    return [x.cache() for x in hand.frames(spark)]


def pred(q):
    return q.select("qid", "etype")


def two(g, **config):
    kg, types, sigs, q, _ = g
    return retrieve.bidirectional(q, pred(q), kg, types, sigs, Config(**config))


def test_supervision(g):
    kg, _, sigs, q, gold = g
    short = supervision.shortest_paths(q, gold, kg, max_len=4)
    assert [(r["len"], r["rels"]) for r in short.collect()] == [(3, ["born_in", "city_of", "official_language"])]
    last = supervision.last_relation(short)
    assert [r["rel"] for r in last.collect()] == ["official_language"]
    assert [(r["etype"], r["q"]) for r in supervision.soft_target(supervision.valid_types(last, sigs)).collect()] == [("language", 1.0)]


def test_last_hop_and_meeting(g):
    kg, types, sigs, q, _ = g
    last = retrieve.last_hop(pred(q), sigs)
    assert {(r["rel"], r["head_type"]) for r in last.collect()} == {("official_language", "country"), ("speaks", "person")}
    met = retrieve.meet(expand.union(expand.prefixes(q, kg, depth=2)), types, last)
    assert {(r["v"], r["rel"]) for r in met.collect()} == {("ann", "speaks"), ("norway", "official_language"), ("uk", "official_language")}


def test_path_counts(g):
    kg, types, sigs, q, _ = g
    forward = {r["hop"]: int(r["n_paths"]) for r in expand.count_paths(q, kg, depth=4).collect()}
    assert forward == {1: 4, 2: 2, 3: 3, 4: 1}
    last = retrieve.last_hop(pred(q), sigs)
    assert {r["hop"]: int(r["n_paths"]) for r in expand.count_paths(q, kg, depth=4, last=last).collect()} == {1: 1, 3: 2, 4: 1}
    for depth in (1, 2, 3, 4):
        found = {(tuple(r["rels"]), tuple(r["nodes"])) for r in retrieve.fallback(q, kg, depth=depth, length_mode="exact").collect()}
        assert found == set(hand.walks("ann", depth))


def test_bidirectional(g):
    kg, types, sigs, q, gold = g
    rows = two(g, depth=3).collect()
    assert sorted(r["tail"] for r in rows) == ["english", "english", "norwegian"]
    assert {r["path_key"] for r in two(g, depth=3, use_mask=True).collect()} == {r["path_key"] for r in rows}
    assert [r["len"] for r in two(g, depth=3, length_mode="exact").collect()] == [3, 3]
    assert two(g, depth=3, head_check="edge").count() == 3
    assert two(g, depth=3, path_mode="simple").count() == 3
    forward = baselines.forward_only(q, kg, depth=3)
    assert (forward.count(), forward.select("tail").distinct().count()) == (9, 8)
    assert retrieve.check_tail_type(two(g, depth=3), types, pred(q)).count() == 0
    red = {r["measure"]: round(r["pct"], 2) for r in metrics.reduction(metrics.n_paths(q, two(g, depth=3)), metrics.n_paths(q, forward)).collect()}
    assert red == {"paths": 66.67, "answers": 75.0}


def test_constrained_is_forward_filtered(g):
    kg, types, sigs, q, _ = g
    last = {(r["rel"], r["head_type"]) for r in retrieve.last_hop(pred(q), sigs).collect()}
    forward = retrieve.fallback(q, kg, depth=4).collect()
    want = {r["path_key"] for r in forward if (r["rels"][-1], hand.TYPES[r["nodes"][-2]]) in last}
    assert {r["path_key"] for r in two(g, depth=4).collect()} == want


def test_reach_mask(g):
    _, _, sigs, q, _ = g
    got = {}
    for r in retrieve.reach_mask(sigs, pred(q), depth=3).collect():
        got.setdefault(r["hops_left"], set()).add(r["etype"])
    assert got == {1: {"country", "person"}, 2: {"city", "company", "country"}, 3: {"city", "company", "person"}}


def test_measures(g):
    kg, types, _, q, gold = g
    f = lambda paths: metrics.per_question(q, paths.select("qid", F.col("tail").alias("answer"), F.lit(None).cast("int").alias("rank")).distinct(), gold).first()
    a = f(two(g, depth=3))
    assert (a["precision"], a["recall"], round(a["f1"], 6), a["any_hit"]) == (0.5, 1.0, 0.666667, 1.0)
    b = f(baselines.forward_only(q, kg, depth=3))
    assert (b["precision"], b["recall"], round(b["f1"], 6)) == (0.125, 1.0, 0.222222)
    none = metrics.per_question(q, gold.limit(0).withColumn("rank", F.lit(1)), gold).first()
    assert (none["f1"], none["n_gold"], none["hit1"]) == (0.0, 1, 0.0)


@pytest.fixture(scope="module")
def pool(g):
    kg, types, sigs, q, _ = g
    return rank.top_k(two(g, depth=3), q).cache()


def facts(g):
    return g[0].select(F.col("head").alias("entity"), F.col("rel").alias("attr"), F.col("tail").alias("value"))


def test_refinement_rounds(g, pool):
    kg, types, sigs, q, gold = g
    refiner = refine.RuleRefiner(facts(g))
    one = refine.run(q, pool, refine.RuleGenerator(), refiner, max_rounds=1).first()
    assert sorted(one["y_gen"]) == ["english", "norwegian"] and one["y_ref"] == ["norwegian"]
    assert (one["confidence"], one["issue"]) == (2, "answer_noise")
    full = refine.run(q, pool, refine.RuleGenerator(), refiner).first()
    assert (full["y_ref"], full["confidence"], full["rounds"]) == (["norwegian"], 3, 2)
    fixed = refine.run(q, pool, refine.RuleGenerator(), refiner, adaptive=False).first()
    assert (fixed["y_ref"], fixed["rounds"]) == (["norwegian"], 3)
    single = refine.run(q, pool, refine.RuleGenerator(), refiner, max_rounds=0).first()
    assert sorted(single["y_ref"]) == ["english", "norwegian"]
    f1 = metrics.per_question(q, metrics.ranked(refine.run(q, pool, refine.RuleGenerator(), refiner)), gold).first()
    assert f1["f1"] == 1.0


def test_refiner_that_finds_no_support(g, pool, spark):
    q = g[3].withColumn("constraints", F.expr("array(named_struct('target', 'path', 'rel', 'nowhere', 'op', 'via', 'value', ''))"))
    r = refine.run(q, pool, refine.RuleGenerator(), refine.RuleRefiner(facts(g))).first()
    assert sorted(r["y_ref"]) == ["english", "norwegian"] and (r["confidence"], r["rounds"], r["issue"]) == (1, 2, "no_support")


def test_question_without_paths(g, pool, spark):
    kg, types, sigs, q, _ = g
    lost = q.withColumn("topic", F.lit("nobody")).withColumn("qid", F.lit(9).cast("long"))
    both = q.unionByName(lost)
    rows = {r["qid"]: r for r in refine.run(both, pool, refine.RuleGenerator(), refine.RuleRefiner(facts(g))).collect()}
    assert rows[9]["y_ref"] == [] and rows[9]["rounds"] == 0


def test_replay_refiner_is_neutral_without_replies(g, pool, spark):
    replies = spark.createDataFrame([], "prompt_hash string, reply string")
    r = refine.run(g[3], pool, refine.RuleGenerator(), refine.ReplayRefiner(replies, facts(g))).first()
    assert sorted(r["y_ref"]) == ["english", "norwegian"] and r["rounds"] == 2


@pytest.mark.parametrize("etype", [None, "planet"])
def test_fallback(g, etype):
    kg, types, sigs, q, _ = g
    p = pred(q).filter(F.lit(False)) if etype is None else q.select("qid", F.lit(etype).alias("etype"))
    rows = retrieve.route(q, p, kg, types, sigs, Config(depth=3)).collect()
    assert len(rows) == 9 and {r["mode"] for r in rows} == {"fallback"}


def test_edge_cases(g, spark):
    kg, types, sigs, q, _ = g
    c = Config(depth=3)
    assert retrieve.bidirectional(q.filter("false"), pred(q), kg, types, sigs, c).count() == 0
    assert retrieve.fallback(q.withColumn("topic", F.lit("nobody")), kg, depth=2).count() == 0
    assert rank.top_k(two(g, depth=3), q, k=0).count() == 0
    assert rank.top_k(two(g, depth=3), q.withColumn("text", F.lit(None).cast("string")), k=500).count() == 3
    loop = spark.createDataFrame([("a", "r", "a"), ("a", "s", "b"), ("a", "t", "b"), ("b", "r", "a")], kg.schema)
    one = q.withColumn("topic", F.lit("a"))
    assert retrieve.fallback(one, loop, depth=2, length_mode="exact", path_mode="walk").count() == 5
    assert retrieve.fallback(one, loop, depth=2, path_mode="simple").count() == 2


def test_budget_before_filter_loses_answers(g):
    """A filter after a tight beam loses what a search under constraint finds."""
    kg, types, sigs, q, _ = g
    post = baselines.post_filter(q, pred(q), kg, types, sigs, k=1, depth=3)
    ours = {r["tail"] for r in two(g, depth=3).collect()}
    assert {r["tail"] for r in post.collect()} < ours


def test_top_k_is_stable_under_repartitioning(g):
    paths, q = two(g, depth=4), g[3]
    a = [tuple(r) for r in rank.top_k(paths, q).select("path_key", "rank").orderBy("rank").collect()]
    assert a == [tuple(r) for r in rank.top_k(paths.repartition(7), q).select("path_key", "rank").orderBy("rank").collect()]
