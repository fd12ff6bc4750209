"""The experiment tables: all methods side by side on one workload (X-1 to X-4)."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import functions as F

from kgtrail.operators import baselines, metrics, rank, refine, supervision, typepredict, workload
from kgtrail.plans import pipeline, retrieve
from kgtrail.plans.retrieve import Config
from kgtrail.queries.common import KG, SIGS, asked, every, gold_type, graph, sql_by_method, sql_forward, sql_gold, sql_oneshot_types, sql_pool, sql_questions, sql_two, typed, with_
from kgtrail.queries.experiments import BR, sql_beam, sql_explored
from kgtrail.registry import query
from kgtrail.sources.shared import stored

DEPTH, BEAM = 2, dict(k=24, depth=2, min_degree=4)
#: Relations that may come last before a part, the answer of this workload.
LAST = "('order.parts', 'supplier.parts', 'brand.parts', 'category.parts')"

# ---- SQL: one pool of paths per method ----

_PATHS = {
    "typed": sql_two(DEPTH),
    "beam": sql_beam(DEPTH, BEAM["k"], BEAM["min_degree"]) + ", beam as (select qid, len, rels, tail, path_key from b1 union all select qid, len, rels, tail, path_key from b2)",
    "post_filter": "filtered as (select * from beam where string_split(rels, '>')[-1] in " + LAST + ")",
    "relation_plans": """best as (select f.qid, f.tail, min(len) len from fwd f join gold g on g.qid = f.qid and g.answer = f.tail group by 1, 2), seqs as (select distinct qid, rels from fwd join best using (qid, tail, len)),
 plans as (select template, rels from (select template, rels, row_number() over (partition by template order by count(*) desc, rels) k from seqs join q using (qid) group by 1, 2) where k <= 2), planned as (select f.* from fwd f join q using (qid) join plans p on p.template = q.template and p.rels = f.rels)""",
    "grounded_plans": "near as (select qid, rels from (select distinct qid, rels, score, dense_rank() over (partition by qid order by score desc, rels) k from p_forward_s) where k <= 2), grounded as (select f.* from fwd f join near using (qid, rels))",
    "explore": "e0 as (select qid, 0 len, '' rels, topic v, topic path_key from q), " + sql_explored(1) + ", " + sql_explored(2) + ", explored as (select qid, len, rels, v tail, path_key from e1 union all select qid, len, rels, v, path_key from e2)",
    "memory": "facts as (select qid, len, rels, tail, path_key from (select *, row_number() over (partition by qid order by score desc, path_key) k from p_forward_s where len = 1) where k <= 5)",
}
_NAMES = {"typed": "two", "beam": "beam", "post_filter": "filtered", "relation_plans": "planned", "grounded_plans": "grounded", "explore": "explored", "memory": "facts"}


def _answers(method: str) -> str:
    return f"select '{method}' method, qid, tail answer, min(rank) rank from p_{method} group by 2, 3"


def sql_refined(pool: str) -> str:
    """{pool}_ref and {pool}_one: answers of the refinement loop and of the single pass."""
    return f"""{pool}_ans as (select qid, tail answer, bool_or(ok) sup, round(max(score) + 0.01 * ln(1 + count(*)), 6) s1, round(max(case when ok then score end) + 0.01 * ln(1 + count(case when ok then 1 end)), 6) s2 from (
 select p.*, case template when 'w_parts_in_year' then string_split(path_key, '|')[3] in (select 'order:' || o_orderkey from orders where year(o_orderdate) = 1997) when 'w_parts_over_size' then tail in (select 'part:' || p_partkey from part where p_size > 40) else true end ok
 from {pool} p join q using (qid)) group by 1, 2), {pool}_sum as (select qid, count(*) n, count(case when sup then 1 end) n_sup from {pool}_ans group by 1),
{pool}_ref as (select qid, answer, row_number() over (partition by qid order by case when n_sup in (0, n) then s1 else s2 end desc, answer) rank from {pool}_ans join {pool}_sum using (qid) where sup or n_sup = 0),
{pool}_one as (select qid, answer, row_number() over (partition by qid order by s1 desc, answer) rank from {pool}_ans)"""


def _pools(*methods: str) -> list[str]:
    """p_<method>: the ranked pool of each method; forward search always, as others build on it."""
    out = [sql_forward(DEPTH), sql_pool("fwd", "p_forward")]
    for m in methods:
        if m != "forward":
            out += [_PATHS[m], sql_pool(_NAMES[m], f"p_{m}")]
    return out


_BASE = (KG, SIGS, sql_questions(*BR), sql_gold(*BR))
_PRIOR = "often as (select template, arg_min(answer, (-n, answer)) answer from (select template, answer, count(*) n from q join gold using (qid) group by 1, 2) group by 1)"

# ---- DataFrames ----


def _setup(spark, d):
    q, g = asked(spark, d, *BR), graph(spark, d)
    return q, g, workload.gold(spark, d, q)


def _pool(method, q, g, gold):
    """The ranked pool of a method; what several tables read is written by them."""
    kg, pred = g.triples, gold_type(q)
    if method == "typed":
        return pipeline.pool(q, pred, g, Config(covered=True, depth=DEPTH))
    if method == "forward":
        paths = baselines.forward_only(q, kg, depth=DEPTH)
    elif method == "beam":
        paths = baselines.beam_paths(q, kg, **BEAM)
    elif method == "post_filter":
        paths = baselines.post_filter(q, pred, kg, g.entity_types, g.signatures, **BEAM)
    elif method == "relation_plans":
        paths = baselines.relation_plans(q, baselines.train_plans(q, supervision.shortest_paths(q, typed(gold), kg, max_len=DEPTH, sigs=g.signatures)), kg, depth=DEPTH)
    elif method == "grounded_plans":
        paths = baselines.grounded_plans(q, kg, depth=DEPTH)
    elif method == "explore":
        paths = baselines.explore(q, kg, width=3, depth=DEPTH)
    else:
        paths = baselines.memory(q, kg)
    return rank.top_k(paths.select("qid", "len", "rels", "nodes", "tail", "path_key"), q)


def _table(q, gold, answers):
    """A row for each method: questions, hit1, f1, precision, recall."""
    out = None
    for method, rows in answers.items():
        one = metrics.summary(metrics.per_question(q, rows.select("qid", "answer", "rank"), gold)).select(F.lit(method).alias("method"), "questions", "hit1", "f1", "precision", "recall")
        out = one if out is None else out.unionByName(one)
    return out


def _refined(q, g, p0, **options):
    p0 = stored(p0, "pool")
    return metrics.ranked(refine.run(q, p0, refine.RuleGenerator(), refine.RuleRefiner(g.facts), **options))


OVERALL = ("typed", "forward", "beam", "relation_plans", "grounded_plans", "explore", "memory")


@query("x_overall", with_(*_BASE, *_pools(*OVERALL), sql_refined("p_typed"), _PRIOR, "preds as (" + " union all ".join(map(_answers, OVERALL)) + " union all select 'full', qid, answer, rank from p_typed_ref union all select 'prior', q.qid, o.answer, 1 from q join often o using (template))", then=sql_by_method("preds")))
def _(spark, d):
    """The whole procedure against its parts and all baselines, on questions with and without constraints."""
    q, g, gold = _setup(spark, d)
    pools = {m: _pool(m, q, g, gold) for m in OVERALL}
    pools["typed"] = stored(pools["typed"], "pool")
    answers = {m: pipeline.retrieval_only(p) for m, p in pools.items()}
    answers["full"] = _refined(q, g, pools["typed"])
    answers["prior"] = baselines.prior_only(q, gold, q)
    return _table(q, gold, answers)


PLANS = ("typed", "relation_plans", "grounded_plans")


@query("x_retrieval_only", with_(*_BASE, *_pools(*PLANS), "preds as (" + " union all ".join(map(_answers, PLANS)) + ")", then=sql_by_method("preds")))
def _(spark, d):
    """Answers read off the evidence alone: typed search against both ways of planning relations."""
    q, g, gold = _setup(spark, d)
    return _table(q, gold, {m: pipeline.retrieval_only(_pool(m, q, g, gold)) for m in PLANS})


_ABLATION = {"full": "p_typed_ref", "no_type_space": "p_beam_ref", "post_filter": "p_post_filter_ref", "no_refine": "p_typed_one"}


@query("x_ablation", with_(*_BASE, *_pools("typed", "beam", "post_filter"), *map(sql_refined, ("p_typed", "p_beam", "p_post_filter")), "preds as (" + " union all ".join(f"select '{m}' method, qid, answer, rank from {t}" for m, t in _ABLATION.items()) + ")", then=sql_by_method("preds")))
def _(spark, d):
    """The whole procedure, without types in the search, with types only after it, and without refinement."""
    q, g, gold = _setup(spark, d)
    typed = stored(_pool("typed", q, g, gold), "pool")
    answers = {"full": _refined(q, g, typed), "no_type_space": _refined(q, g, _pool("beam", q, g, gold)), "post_filter": _refined(q, g, _pool("post_filter", q, g, gold)), "no_refine": _refined(q, g, typed, max_rounds=0)}
    return _table(q, gold, answers)


HOPS = ("w_customer_nation", "w_customer_region", "w_customer_brands")
SHOTS = (*HOPS, "w_customer_orders", "w_part_brand")


def one_shot_types(spark, d, q, names):
    """qid, etype predicted by naive Bayes from one training question of each named template."""
    train = workload.one_shot(every(spark, d, *names).filter("split = 'train'"))
    model = typepredict.NaiveBayes().fit(train, train.select("qid", "etype", F.lit(1.0).alias("q")))
    return stored(typepredict.predict(model.scores(q)).select("qid", "etype"), "types")


@query("x_by_hops", with_(KG, SIGS, sql_questions(*HOPS), sql_questions(*SHOTS, step=1, name="shots"), sql_gold(*HOPS), sql_oneshot_types("shots"), sql_two(3, "ga"), sql_two(3, "gb", "typed"), sql_pool("ga", "pa"), sql_pool("gb", "pb"), "preds as (select 'gold' method, qid, tail answer, min(rank) rank from pa group by 2, 3 union all select 'one_shot', qid, tail, min(rank) from pb group by 2, 3)", then=sql_by_method("preds", "method, hops")))
def _(spark, d):
    """Retrieval only by the question's hops at one depth for all, with gold types and with types
    learned from one example of each template."""
    q, g = asked(spark, d, *HOPS), graph(spark, d)
    gold, out = workload.gold(spark, d, q), None
    for method, pred in (("gold", gold_type(q)), ("one_shot", one_shot_types(spark, d, q, SHOTS))):
        config = Config(covered=True, depth=3)
        paths = retrieve.bidirectional(q, pred, g.triples, g.entity_types, g.signatures, replace(config, first=config.k))
        rows = metrics.per_question(q, pipeline.retrieval_only(rank.top_k(paths, q, k=config.k)), gold).join(q.select("qid", "hops"), "qid")
        one = metrics.summary(rows, "hops").select(F.lit(method).alias("method"), "hops", "questions", "hit1", "f1", "precision", "recall")
        out = one if out is None else out.unionByName(one)
    return out


ONE = (*BR, "w_customer_orders", "w_customer_nation")


@query("br_oneshot", with_(*_BASE, sql_questions(*ONE, step=1, name="shots"), sql_oneshot_types("shots"), sql_two(DEPTH, "two", "typed"), sql_pool("two", "p_one"), "preds as (select 'one_shot' method, qid, tail answer, min(rank) rank from p_one group by 2, 3)", then=sql_by_method("preds")))
def _(spark, d):
    """Retrieval only under types learned from one training question of each template."""
    q, g, gold = _setup(spark, d)
    p0 = pipeline.pool(q, one_shot_types(spark, d, q, ONE), g, Config(covered=True, depth=DEPTH))
    return _table(q, gold, {"one_shot": pipeline.retrieval_only(p0)})
