"""What may not grow with a hub: the tables that searches write, and what they join with."""

import pytest
from pyspark.sql import functions as F

from kgtrail.operators import baselines, metrics, rank, supervision, workload
from kgtrail.plans import expand, retrieve
from kgtrail.queries.common import asked, every, gold_type, graph, typed
from kgtrail.registry import load, queries
from kgtrail.sources import star

load()
BRANDS = "w_customer_brands"


def kinds(df, col="v"):
    return {r[0].split(":")[0] for r in df.select(col).distinct().collect()}


@pytest.fixture
def written(monkeypatch):
    """(name, table) of everything that a module writes."""
    made = []

    def spy(module):
        put = module.stored
        monkeypatch.setattr(module, "stored", lambda df, name: made.append((name, put(df, name))) or made[-1][1])
        return made

    return spy


def test_shortest_paths_enter_only_types_that_lead_on(spark, sf, written):
    made, q, g = written(supervision), asked(spark, sf, BRANDS), graph(spark, sf)
    gold = workload.gold(spark, sf, q)
    short = supervision.shortest_paths(q, typed(gold), g.triples, max_len=3, sigs=g.signatures)
    wrote = len(made)
    plain = supervision.shortest_paths(q, gold, g.triples, max_len=3)
    rows = lambda df: {(r["qid"], r["answer"], r["len"], tuple(r["rels"])) for r in df.collect()}
    assert rows(short) == rows(plain) and rows(short)
    assert [kinds(df) for name, df in made[:wrote] if name == "level"] == [{"customer"}, {"order"}, {"part"}]


def test_shortest_paths_to_answers_of_several_types(spark, sf):
    q, g = asked(spark, sf, BRANDS, "w_customer_nation", "w_customer_region"), graph(spark, sf)
    gold = workload.gold(spark, sf, q)
    rows = lambda df: {(r["qid"], r["answer"], r["len"], tuple(r["rels"])) for r in df.collect()}
    assert rows(supervision.shortest_paths(q, typed(gold), g.triples, max_len=3, sigs=g.signatures)) == rows(supervision.shortest_paths(q, gold, g.triples, max_len=3))


def test_typed_search_spells_no_hub_out_before_the_result(spark, sf, written):
    made, q, g = written(retrieve), asked(spark, sf, BRANDS), graph(spark, sf)
    two = lambda **c: {r["path_key"] for r in retrieve.bidirectional(q, gold_type(q), g.triples, g.entity_types, g.signatures, retrieve.Config(depth=3, **c)).select("path_key").collect()}
    assert two(covered=True) == two()
    assert [kinds(df) for name, df in made if name == "front"] == [{"order"}]


def test_meeting_nodes_joins_only_prefixes_that_can_meet(spark, sf):
    q, g = asked(spark, sf, BRANDS), graph(spark, sf)
    fronts = retrieve.typed_prefixes(q, gold_type(q), g.triples, g.signatures, depth=2)
    assert [kinds(f) for f in fronts] == [{"customer"}, {"order"}, {"part"}]


def test_two_sides_meet_at_types_between_them(spark, sf, written):
    made, q, g = written(baselines), asked(spark, sf, BRANDS), graph(spark, sf)
    gold = workload.gold(spark, sf, q)
    rows = lambda df: {(r["qid"], r["answer"], r["n_paths"]) for r in df.collect()}
    assert rows(baselines.two_sided(q, typed(gold), g.triples, depth=3, sigs=g.signatures)) == rows(baselines.two_sided(q, gold, g.triples, depth=3))
    assert kinds(dict(made[:2])["near"]) == {"part"}


@pytest.mark.parametrize("key", ["ablation_no_type_space", "baseline_explore"])
def test_beams_join_no_more_of_a_hub_than_they_keep(spark, sf, monkeypatch, key):
    step, most = expand.step, []

    def counted(front, kg, **options):
        most.append(kg.groupBy("head", "rel").count().agg({"count": "max"}).first()[0])
        return step(front, kg, **options)

    monkeypatch.setattr(expand, "step", counted)
    queries()[key](spark, sf)
    assert most and max(most) <= (24 if key == "ablation_no_type_space" else 3)


@pytest.mark.parametrize("key", ["ontology_schema", "ontology_blocklist", "ontology_complete", "ontology_incomplete", "ontology_domain_range", "ontology_coverage", "ontology_by_tail", "type_soft_target"])
def test_schema_queries_read_the_tables(spark, sf, key):
    assert any("parquet" in f for f in queries()[key](spark, sf).inputFiles())


@pytest.mark.parametrize("key", ["path_counts_constrained", "bound_check"])
def test_counts_never_pair_questions_with_what_they_reach(spark, sf, written, key):
    made = written(expand)
    queries()[key](spark, sf)
    assert made and all("qid" not in df.columns for name, df in made if name in ("near", "back"))


def test_counting_back_equals_counting_forward(spark, sf):
    q, g = asked(spark, sf, BRANDS, "w_customer_nation"), graph(spark, sf)
    hops = retrieve.typed_hops(g.signatures, gold_type(q), depth=3, starts=retrieve.topic_types(q))
    last = retrieve.last_hop(gold_type(q), g.signatures)
    rows = lambda df: {tuple(r) for r in df.collect()}
    assert rows(expand.count_back(q, g.triples, hops, last=last)) == rows(expand.count_paths(q, g.triples, depth=3, last=last))


def counted(df):
    return {(r["qid"], r["hop"]): r["n_answers"] for r in df.collect()}


@pytest.mark.parametrize("wide", [1, 8])
def test_reached_nodes_keep_questions_as_bits(spark, sf, written, monkeypatch, wide):
    """no hop writes a row for each pair of question and node."""
    monkeypatch.setattr(expand, "WIDE", wide)
    made, q, g = written(expand), every(spark, sf, BRANDS), graph(spark, sf)
    assert q.count() == 150  # three longs: one row for each node, or three
    got = counted(expand.reached(q, g.triples, depth=3))
    assert got == counted(expand.count_paths(q, g.triples, depth=3))
    nodes = g.entity_types.count()
    fronts = [df for name, df in made if name == "reached"]
    assert len(fronts) == 3 and all(df.count() <= nodes * (3 if wide == 1 else 1) < sum(got.values()) / 10 for df in fronts)


def test_reached_without_questions_or_edges(spark, sf):
    q, g = asked(spark, sf, BRANDS), graph(spark, sf)
    assert expand.reached(q.limit(0), g.triples, depth=2).collect() == []
    assert expand.reached(q, g.triples.limit(0), depth=2).collect() == []
    none = baselines.forward_counts(q, g.triples.limit(0), g.signatures, depth=2).collect()
    assert {(r["n_paths"], r["n_answers"]) for r in none} == {(0, 0)} and len(none) == q.count()


def test_forward_counts_list_no_paths(spark, sf):
    """the counts of forward search without its paths."""
    q, g = asked(spark, sf, BRANDS), graph(spark, sf)
    rows = lambda df: {(r["qid"], r["n_paths"], r["n_answers"]) for r in df.collect()}
    counts = baselines.forward_counts(q, g.triples, g.signatures, depth=3)
    assert rows(counts) == rows(metrics.n_paths(q, baselines.forward_only(q, g.triples, depth=3)))
    assert "concat_ws" not in metrics.plan_text(counts)
    assert "n_answers" not in baselines.forward_counts(q, g.triples, g.signatures, depth=3, answers=False).columns


def test_fallback_writes_the_first_hop_only(spark, sf, written):
    """the size of the first hop is known when it meets all edges, which then need no shuffle."""
    made, q, g = written(retrieve), asked(spark, sf, "w_customer_region"), graph(spark, sf)
    paths = retrieve.fallback(q, g.triples, depth=2)
    assert [name for name, _ in made] == ["front"] and {r["len"] for r in made[0][1].select("len").distinct().collect()} == {1}
    assert {r["len"] for r in paths.select("len").distinct().collect()} == {1, 2}


@pytest.mark.parametrize("crowd", [1, 64])
def test_four_hops_make_paths_of_questions_in_the_result_only(spark, sf, written, monkeypatch, crowd):
    """past the first hop, what is written has a row for each node and way on, not for each question."""
    monkeypatch.setattr(retrieve, "CROWD", crowd)
    made, q, g = written(retrieve), asked(spark, sf, "w_customer_supplier_regions"), graph(spark, sf)
    rows = lambda **c: sorted(map(tuple, retrieve.bidirectional(q, gold_type(q), g.triples, g.entity_types, g.signatures, retrieve.Config(depth=4, **c)).select("qid", "len", F.concat_ws(">", "rels"), F.concat_ws(">", "nodes"), "tail", "path_key").collect()))
    found = rows(covered=True)
    assert found == rows() and {r[1] for r in found} == {2, 4}
    assert [{r["len"] for r in df.select("len").distinct().collect()} for _, df in made if "qid" in df.columns] == [{0}, {1}]
    assert [name for name, df in made if "qid" not in df.columns] == ["walks", "walks"]


def test_texts_of_relations_are_those_of_the_lists(spark, sf):
    q, g = asked(spark, sf, "w_customer_supplier_regions"), graph(spark, sf)
    two = retrieve.bidirectional(q, gold_type(q), g.triples, g.entity_types, g.signatures, retrieve.Config(depth=4, covered=True, texts=True))
    for paths in (two, retrieve.fallback(q, g.triples, depth=3, texts=True)):
        assert paths.filter(F.concat_ws(">", "rels") != F.col("rel_text")).isEmpty() and not paths.isEmpty()


@pytest.mark.parametrize("how", ["edges", "walk"])
def test_store_sorts_and_looks_up_nothing(spark, sf, how):
    """Entity types are no table of the store, and its session keeps its settings."""
    g = graph(spark, sf)
    if how == "edges":
        assert all("/triples/" in f for f in g.entity_types.inputFiles()) and spark.conf.get(star.WRITERS) == "0"
    else:
        ends = g.triples.select("head").union(g.triples.select("tail")).distinct()
        assert g.entity_types.count() == ends.count() == g.entity_types.select("entity").distinct().count()


@pytest.mark.parametrize("hashes", [1, 1 << 21])
def test_edges_of_other_heads_are_left_out_before_the_join(spark, sf, monkeypatch, hashes):
    """what meets the first hop is a small part of all edges, and every edge it needs."""
    monkeypatch.setattr(retrieve, "HASHES", hashes)
    q, g = asked(spark, sf, "w_customer_region"), graph(spark, sf)
    met = retrieve.likely(g.triples, q, "topic")
    mine = g.triples.join(q.select(F.col("topic").alias("head")), "head", "left_semi")
    assert met.columns == g.triples.columns and met.join(mine, ["head", "rel", "tail"], "left_semi").count() == mine.count() > 0
    assert met.count() == (g.triples.count() if hashes == 1 else mine.count())
    plain = expand.union(expand.prefixes(q, g.triples, depth=2)[1:])
    keys = lambda df: sorted(r["path_key"] for r in df.select("path_key").collect())
    assert keys(retrieve.fallback(q, g.triples, depth=2)) == keys(plain)


@pytest.mark.parametrize("k", [1, 3, 256])
def test_ways_beyond_the_last_rank_are_not_joined(spark, sf, written, k):
    """of the ways on from a hub by the same relations the first k are joined, and the ranked paths are the same."""
    made, q, g = written(retrieve), asked(spark, sf, "w_customer_nation", "w_customer_region", BRANDS), graph(spark, sf)
    two = lambda **c: retrieve.bidirectional(q, gold_type(q), g.triples, g.entity_types, g.signatures, retrieve.Config(covered=True, depth=3, **c))
    some, every_one = two(first=k), two()
    best = lambda paths: sorted((r["qid"], r["rank"], r["path_key"], r["score"]) for r in rank.top_k(paths, q, k=k).select("qid", "rank", "path_key", "score").collect())
    assert best(some) == best(every_one)
    ways = dict(made)["ways"]
    assert ways.groupBy("v", "ends", "text2").count().agg({"count": "max"}).first()[0] <= k
    assert k == 256 or some.count() < every_one.count()
