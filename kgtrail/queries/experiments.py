"""Queries on baselines, measures, workloads and experiments (B, A, W and X rows)."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from kgtrail.functions.text import tokens
from kgtrail.operators import baselines, metrics, ontology, rank, refine, supervision, typepredict, workload
from kgtrail.plans import expand, pipeline, retrieve
from kgtrail.plans.retrieve import Config
from kgtrail.queries.common import KG, SIGS, asked, every, gold_type, graph, path_rows, sql_chain, sql_cosine, sql_forward, sql_gold, sql_metrics, sql_questions, sql_scored, sql_summary, sql_tokens, sql_two, sql_walks, typed, with_
from kgtrail.queries.refinement import ANSWERS, FINAL, MEASURED, NAMES, POOL, loop, measured, pool, tradeoff
from kgtrail.registry import query
from kgtrail.sources import light
from kgtrail.sources.shared import stored
from kgtrail.sources.star import table

B3 = "w_customer_brands"
REGION = "w_customer_region"
_Q3 = (KG, SIGS, sql_questions(B3))


def _forward(spark, d, name, depth):
    q, g = asked(spark, d, name), graph(spark, d)
    return q, baselines.forward_only(q, g.triples, depth=depth)


# ---- baselines ----


@query("baseline_forward", with_(KG, sql_questions(B3), sql_forward(3), then="select qid, len, split_part(tail, ':', 1) etype, count(*) n_paths, count(distinct tail) n_answers from fwd group by all"))
def _(spark, d):
    _, paths = _forward(spark, d, B3, 3)
    return paths.groupBy("qid", "len", F.substring_index("tail", ":", 1).alias("etype")).agg(F.count("*").alias("n_paths"), F.countDistinct("tail").alias("n_answers"))


def sql_beam(depth: int, k: int, least: int) -> str:
    """b1..b<depth>: the beam after each hop, one scored chain on the other."""
    out = ["deg as (select head, count(*) degree from kg group by 1)", f"b0 as (select qid, topic v, '' rels, topic path_key, 0 len from q)"]
    for i in range(1, depth + 1):
        rels = "t.rel" if i == 1 else "b.rels || '>' || t.rel"
        out.append(f"h{i} as (select b.qid, {i} len, {rels} rels, t.tail v, t.tail, b.path_key || '|' || t.rel || '|' || t.tail path_key, deg.degree degree from b{i - 1} b join kg t on t.head = b.v join deg on deg.head = b.v)")
        out.append(sql_scored(f"h{i}", f"sc{i}"))
        out.append(f"b{i} as (select * from (select *, row_number() over (partition by qid, degree > {least} order by score desc, path_key) n from sc{i}) where degree <= {least} or n <= {k})")
    return ", ".join(out)


BEAM = dict(k=24, depth=3, min_degree=4)
_BEAM = sql_beam(3, 24, 4)
_ALL = " union all ".join(f"select qid, len, rels, tail, path_key from b{i}" for i in (1, 2, 3))


@query("ablation_no_type_space", with_(*_Q3, _BEAM, then=_ALL))
def _(spark, d):
    return path_rows(baselines.beam_paths(asked(spark, d, B3), graph(spark, d).triples, **BEAM))


@query("ablation_post_filter", with_(*_Q3, _BEAM, then=f"select * from ({_ALL}) where string_split(rels, '>')[-1] = 'part.brand'"))
def _(spark, d):
    q, g = asked(spark, d, B3), graph(spark, d)
    return path_rows(baselines.post_filter(q, gold_type(q), g.triples, g.entity_types, g.signatures, **BEAM))


@query("ablation_no_refine", with_(MEASURED, then=sql_summary("per_one")))
def _(spark, d):
    return metrics.summary(measured(spark, d, *loop(spark, d, max_rounds=0)))


def _br(spark, d, names, depth):
    q, g = asked(spark, d, *names), graph(spark, d)
    return q, pipeline.pool(q, gold_type(q), g, Config(covered=True, depth=depth))


BR = ("w_parts_in_year", "w_parts_over_size", "w_customer_parts")
_BR = (KG, SIGS, sql_questions(*BR), sql_gold(*BR), sql_two(2), sql_scored("two"), "br as (select qid, tail answer, min(rank) rank from (select *, row_number() over (partition by qid order by score desc, len, path_key) rank from scored) where rank <= 256 group by 1, 2)")


def _br_rows(spark, d):
    q, p0 = _br(spark, d, BR, 2)
    return q, metrics.per_question(q, pipeline.retrieval_only(p0), workload.gold(spark, d, q))


@query("br_only", with_(*_BR, sql_metrics("br"), then=sql_summary("per")))
def _(spark, d):
    return metrics.summary(_br_rows(spark, d)[1])


_TRAIN = (REGION, "w_customer_parts")
_REACHED = "reached as (" + " union all ".join(f"select qid, len, rels, tail from ({sql_chain(i)})" for i in (1, 2)) + "), best as (select r.qid, r.tail, min(len) len from reached r join gold g on g.qid = r.qid and g.answer = r.tail group by 1, 2), seqs as (select distinct qid, rels from reached join best using (qid, tail, len))"


@query("baseline_relation_plans", with_(KG, sql_questions(*_TRAIN), sql_gold(*_TRAIN), _REACHED, "plans as (select template, rels from (select template, rels, row_number() over (partition by template order by count(*) desc, rels) k from seqs join q using (qid) group by 1, 2) where k <= 2)", sql_forward(2), then="select f.qid, f.len, f.rels, f.tail, f.path_key from fwd f join q using (qid) join plans p on p.template = q.template and p.rels = f.rels"))
def _(spark, d):
    q, g = asked(spark, d, *_TRAIN), graph(spark, d)
    short = supervision.shortest_paths(q, typed(workload.gold(spark, d, q)), g.triples, max_len=2, sigs=g.signatures)
    return path_rows(baselines.relation_plans(q, baselines.train_plans(q, short), g.triples, depth=2))


@query("baseline_grounded_plans", with_(KG, sql_questions(REGION), sql_forward(2), sql_scored("fwd"), "best as (select qid, rels from (select distinct qid, rels, score, dense_rank() over (partition by qid order by score desc, rels) k from scored) where k <= 2)", then="select f.qid, f.len, f.rels, f.tail, f.path_key from fwd f join best using (qid, rels)"))
def _(spark, d):
    return path_rows(baselines.grounded_plans(asked(spark, d, REGION), graph(spark, d).triples, depth=2))


@query("baseline_two_sided", with_(KG, sql_questions(B3), sql_gold(B3), sql_walks(3, "w"), then="select w.qid, w.tail answer, cast(count(*) as double) n_paths from w_3 w join gold g on g.qid = w.qid and g.answer = w.tail group by 1, 2"))
def _(spark, d):
    q = asked(spark, d, B3)
    g = graph(spark, d)
    return baselines.two_sided(q, typed(workload.gold(spark, d, q)), g.triples, depth=3, sigs=g.signatures)


def _ppr(i: int) -> str:
    return f"m{i} as (select qid, v, sum(mass) mass from (select qid, tail v, mass * w * 0.8 mass from m{i - 1} join out on head = v union all select qid, topic, 0.2 from q) group by 1, 2)"


@query("baseline_ppr", with_(KG, sql_questions(REGION), "out as (select head, tail, 1.0::double / d w from kg join (select head, count(*) d from kg group by 1) using (head))", "m0 as (select qid, topic v, 1.0::double mass from q)", _ppr(1), _ppr(2), _ppr(3), then="select qid, v node, round(mass, 7) mass from (select *, row_number() over (partition by qid order by round(mass, 9) desc, v) rank from m3) where rank <= 10"))
def _(spark, d):
    return baselines.ppr(asked(spark, d, REGION), graph(spark, d).triples, n=10).select("qid", "node", F.round("mass", 7).alias("mass"))


@query("baseline_memory", with_(KG, sql_questions(REGION), sql_forward(1), sql_scored("fwd"), then="select qid, path_key, score from (select *, row_number() over (partition by qid order by score desc, path_key) rank from scored) where rank <= 5"))
def _(spark, d):
    return baselines.memory(asked(spark, d, REGION), graph(spark, d).triples).select("qid", "path_key", "score")


@query("baseline_prior", with_(sql_questions(REGION, "w_part_brand"), sql_gold(REGION, "w_part_brand"), "best as (select template, arg_min(answer, (-n, answer)) answer from (select template, answer, count(*) n from q join gold using (qid) group by 1, 2) group by 1)", then="select qid, b.answer from q join best b using (template)"))
def _(spark, d):
    q = asked(spark, d, REGION, "w_part_brand")
    return baselines.prior_only(q, workload.gold(spark, d, q), q).select("qid", "answer")


def sql_explored(i: int) -> str:
    return (
        f"k{i} as (select distinct e.qid, t.rel rels from e{i - 1} e join kg t on t.head = e.v), {sql_scored(f'k{i}', f'ks{i}')}, c{i} as (select qid, rels rel from (select *, row_number() over (partition by qid order by score desc, rels) k from ks{i}) where k <= 3), "
        f"e{i} as (select qid, {i} len, rels, v, path_key from (select e.qid, case when e.rels = '' then t.rel else e.rels || '>' || t.rel end rels, t.tail v, e.path_key || '|' || t.rel || '|' || t.tail path_key, row_number() over (partition by e.qid, t.rel order by e.path_key || '|' || t.rel || '|' || t.tail) k from e{i - 1} e join kg t on t.head = e.v join c{i} c on c.qid = e.qid and c.rel = t.rel) where k <= 3)"
    )


@query("baseline_explore", with_(KG, sql_questions(REGION), "e0 as (select qid, 0 len, '' rels, topic v, topic path_key from q)", sql_explored(1), sql_explored(2), then="select qid, len, rels, v tail, path_key from e1 union all select qid, len, rels, v, path_key from e2"))
def _(spark, d):
    return path_rows(baselines.explore(asked(spark, d, REGION), graph(spark, d).triples, width=3, depth=2))


@query("backbone_grid")
def _(spark, d):
    """Predictors by generator margins: hit1, f1 of the refined answers."""
    q, g = asked(spark, d, *BR), graph(spark, d)
    gold = workload.gold(spark, d, q)
    train = workload.questions(spark, d, [*BR, "w_customer_orders", "w_customer_nation", B3], step=1).filter("split = 'train'")
    target = train.select("qid", "etype", F.lit(1.0).alias("q"))
    models = {"bayes": typepredict.NaiveBayes().fit(train, target), "nearest": typepredict.Nearest(3).fit(train, target), "oracle": typepredict.Oracle(q.select("qid", "etype", F.lit(1.0).alias("q")))}
    out = None
    for name, model in models.items():
        pred = stored(typepredict.predict(model.scores(q)).select("qid", "etype"), "types")  # read several times by a search
        p0 = stored(pipeline.pool(q, pred, g, Config(covered=True, depth=2)), "pool")
        p0 = stored(p0.join(refine.satisfied(p0, q, g.facts), ["qid", "path_key"]), "pool")
        typed = q.drop("etype").join(pred, "qid", "left")
        for margin in (0.005, 1.0):
            runs = refine.run(typed, p0, refine.RuleGenerator(margin), refine.RuleRefiner(g.facts))
            one = metrics.summary(metrics.per_question(q, metrics.ranked(runs), gold)).select(F.lit(name).alias("predictor"), F.lit(margin).alias("margin"), "hit1", "f1")
            out = one if out is None else out.unionByName(one)
    return out


# ---- measures ----

for _key, _col in (("metric_hit1", "hit1"), ("metric_precision", "precision"), ("metric_recall", "recall"), ("metric_f1", "f1"), ("metric_gold_hit", "any_hit")):

    @query(_key, with_(*_BR, sql_metrics("br"), then=f"select qid, round({_col}, 6) as value from per"))
    def _(spark, d, col=_col):
        return _br_rows(spark, d)[1].select("qid", F.round(col, 6).alias("value"))


@query("metric_micro", with_(*_BR, sql_metrics("br"), then="select round(sum(n_both) / sum(n_pred), 6) as precision, round(sum(n_both) / sum(n_gold), 6) recall, round(2.0 * sum(n_both) / (sum(n_pred) + sum(n_gold)), 6) f1 from per"))
def _(spark, d):
    return metrics.micro(_br_rows(spark, d)[1])


@query("metric_top1_hit", with_(*_BR, sql_metrics("br"), then="select round(avg(hit1), 6) top1_hit, round(avg(any_hit), 6) gold_hit from per"))
def _(spark, d):
    return metrics.summary(_br_rows(spark, d)[1]).select(F.col("hit1").alias("top1_hit"), "gold_hit")


_PAIR = (*_Q3, sql_two(3), sql_forward(3))


def _both(spark, d, answers=True):
    q, g = asked(spark, d, B3), graph(spark, d)
    ours = retrieve.bidirectional(q, gold_type(q), g.triples, g.entity_types, g.signatures, Config(covered=True, depth=3))
    return metrics.n_paths(q, ours), baselines.forward_counts(q, g.triples, g.signatures, depth=3, answers=answers)


_N = "select q.qid, count(path_key) n_paths, count(distinct tail) n_answers from q left join {0} on {0}.qid = q.qid group by 1"


@query("cost_paths", with_(*_PAIR, then="select 'ours' method, qid, n_paths from (" + _N.format("two") + ") union all select 'forward', qid, n_paths from (" + _N.format("fwd") + ")"))
def _(spark, d):
    a, b = _both(spark, d, answers=False)
    return a.select(F.lit("ours").alias("method"), "qid", "n_paths").unionByName(b.select(F.lit("forward").alias("method"), "qid", "n_paths"))


@query("cost_answers", with_(*_PAIR, then="select 'ours' method, qid, n_answers from (" + _N.format("two") + ") union all select 'forward', qid, n_answers from (" + _N.format("fwd") + ")"))
def _(spark, d):
    a, b = _both(spark, d)
    return a.select(F.lit("ours").alias("method"), "qid", "n_answers").unionByName(b.select(F.lit("forward").alias("method"), "qid", "n_answers"))


_AVG = "a as (select avg(n_paths) p, avg(n_answers) x from (" + _N.format("two") + ")), b as (select avg(n_paths) fp, avg(n_answers) fx from (" + _N.format("fwd") + "))"
_RED = "select 'paths' measure, round(p, 6) ours, round(fp, 6) forward, round(100 * (1 - p / fp), 6) pct from a, b union all select 'answers', round(x, 6), round(fx, 6), round(100 * (1 - x / fx), 6) from a, b"


@query("cost_reduction", with_(*_PAIR, _AVG, then=_RED))
def _(spark, d):
    return metrics.reduction(*_both(spark, d))


@query("cost_rounds", with_(POOL, ANSWERS, FINAL, then="select round(avg(coalesce(rounds, 0)), 6) mean_rounds, round(100 * (1 - avg(coalesce(rounds, 0)) / 3), 6) saved_pct from q left join fin using (qid)"))
def _(spark, d):
    return metrics.rounds(loop(spark, d)[1])


@query("tradeoff_rounds", with_(MEASURED, then="""select mode, round(avg(case mode when 'adaptive' then coalesce(rounds, 0) when 'fixed1' then case when rounds is null then 0 else 1 end else case when rounds is null then 0 else 3 end end), 6) mean_rounds, round(avg(f1), 6) f1
 from (select unnest(['adaptive', 'fixed1', 'fixed3']) as mode) cross join q join per_ref using (qid) left join fin using (qid) group by mode"""))  # fmt: skip
def _(spark, d):
    return tradeoff(spark, d)


@query("tradeoff_rounds_narrow")
def _(spark, d):
    """The same for a generator that says only answers close to the best one: a first round may then
    end on unsupported answers, which the second mends. Its scores have no short SQL; tests hold the
    loop against rounds worked out by hand."""
    return tradeoff(spark, d, 0.02)


@query("gain_by_category", with_(MEASURED, then="select category, round(avg(a.f1), 6) f1_first, round(avg(b.f1), 6) f1_last, round(100 * (avg(b.f1) - avg(a.f1)), 4) gain from q join per_one a using (qid) join per_ref b using (qid) group by category"))
def _(spark, d):
    made = pool(spark, d)
    q, first = loop(spark, d, made, max_rounds=0)
    _, last = loop(spark, d, made)
    return metrics.gain_by_category(q, measured(spark, d, q, first), measured(spark, d, q, last))


@query("bound_check", with_(*_Q3, """bm as (select max(d) b from (select count(*) d from kg group by head)), f as (""" + " union all ".join(f"select {i} hop, count(*) n, count(case when rel = 'part.brand' then 1 end) c from ({sql_chain(i)})" for i in (1, 2, 3)) + ")", then="select hop, cast(n as double) forward, cast(c as double) constrained, (select count(*) from q) * power(b::double, hop) as limit, c <= n and n <= (select count(*) from q) * power(b::double, hop) holds from f, bm".replace(" as limit,", ' as "limit",')))
def _(spark, d):
    q, g = asked(spark, d, B3), graph(spark, d)
    last = retrieve.last_hop(gold_type(q), g.signatures)
    starts, any_type = retrieve.topic_types(q), g.signatures.select(F.col("tail_type").alias("etype"))
    hops, some = (retrieve.typed_hops(g.signatures, ends, depth=3, starts=starts) for ends in (any_type, gold_type(q)))
    return metrics.bounds(expand.count_back(q, g.triples, hops, answers=False), expand.count_back(q, g.triples, some, last=last, answers=False), g.triples)


@query("tail_type_histogram", with_(KG, sql_questions(B3), sql_forward(3), then="select len, split_part(tail, ':', 1) etype, count(*) n from fwd group by all"))
def _(spark, d):
    return metrics.tail_types(_forward(spark, d, B3, 3)[1])


_MANY = ("w_customer_nation", "w_customer_region", B3, "w_part_brand")


@query("dataset_stats", with_(sql_questions(*_MANY, step=1), then="select template, hops, count(case when split = 'train' then 1 end) train, count(case when split = 'dev' then 1 end) dev, count(case when split = 'test' then 1 end) test from q group by 1, 2"))
def _(spark, d):
    return workload.dataset_stats(every(spark, d, *_MANY))


@query("gold_reachable", with_(KG, sql_questions(REGION), sql_gold(REGION), sql_forward(2), then="select qid, answer from gold where (qid, answer) not in (select qid, tail from fwd)"))
def _(spark, d):
    q, paths = _forward(spark, d, REGION, 2)
    return metrics.unreachable(workload.gold(spark, d, q), paths)


# ---- workloads ----

for _t in workload.TEMPLATES:

    @query(_t.name, with_(sql_questions(_t.name, step=1), sql_gold(_t.name), then="select qid, text, split, answer from q join gold using (qid)"))
    def _(spark, d, n=_t.name):
        q = every(spark, d, n)
        return q.select("qid", "text", "split").join(workload.gold(spark, d, q), "qid")


for _key, _etype in (("w_fallback_null", None), ("w_fallback_unmapped", "planet")):

    @query(_key, with_(KG, sql_questions(REGION), sql_forward(2), then="select qid, 'fallback' mode, count(*) n_paths from fwd group by 1"))
    def _(spark, d, etype=_etype):
        q, g = asked(spark, d, REGION), graph(spark, d)
        pred = typepredict.Null().scores(q) if etype is None else q.select("qid", F.lit(etype).alias("etype"))
        return retrieve.route(q, pred, g.triples, g.entity_types, g.signatures, Config(covered=True, depth=2)).groupBy("qid", "mode").agg(F.count("*").alias("n_paths"))


def _light(spark, d):
    kg = light.triples(spark, d, inverses=True)
    types = ontology.induce_entity_types(light.training(light.triples(spark, d)))
    return kg, types, ontology.induce_signatures(kg, types)


def _docs_of(spark, d, m, etype):
    docs = table(spark, d, "documents").filter(f"doc_id % {m} = 0")
    return docs.select(F.col("doc_id").cast("long").alias("qid"), F.col("doc_id").cast("string").alias("topic"), F.lit(etype).alias("etype"))


@query("w_light_1hop", "select cast(doc_id as bigint) qid, 1 len, lang tail, count(*) n from documents where doc_id % 10 < 8 group by 1, 3")
def _(spark, d):
    kg, types, sigs = _light(spark, d)
    docs = table(spark, d, "documents")
    q = docs.select(F.col("doc_id").cast("long").alias("qid"), F.col("doc_id").cast("string").alias("topic"), F.lit("language").alias("etype"))
    # a head typed by training questions only: other documents have no type and no path
    found = retrieve.bidirectional(q, gold_type(q), kg, types, sigs, Config(depth=1))
    return found.groupBy("qid", "len", "tail").agg(F.count("*").alias("n"))


@query("w_light_2hop", "select cast(a.doc_id as bigint) qid, cast(b.doc_id as varchar) tail from documents a join documents b on a.source = b.source where a.doc_id % 100 = 0")
def _(spark, d):
    kg, types, sigs = _light(spark, d)
    q = _docs_of(spark, d, 100, "document")
    paths = retrieve.ground(q, q.select("qid", F.array(F.lit("document.source"), F.lit("~document.source")).alias("rels")), kg, depth=2)
    return paths.select("qid", "tail")


@query("w_light_3hop", "select cast(a.doc_id as bigint) qid, b.lang tail, count(*) n from documents a join documents b on a.source = b.source where a.doc_id % 100 = 0 group by 1, 2")
def _(spark, d):
    kg, _, _ = _light(spark, d)
    q = _docs_of(spark, d, 100, "language")
    plan = F.array(F.lit("document.source"), F.lit("~document.source"), F.lit("document.lang"))
    return retrieve.ground(q, q.select("qid", plan.alias("rels")), kg, depth=3).groupBy("qid", "tail").agg(F.count("*").alias("n"))


@query("w_hub_paths", with_(KG, "n1 as (select t.head topic, u.tail v, count(*) n from kg t join kg u on u.head = t.tail where t.rel = 'supplier.parts' and u.rel = 'part.orders' group by 1, 2)", then="select topic, cast(sum(n) as double) n_paths, count(*) n_answers from n1 group by 1"))
def _(spark, d):
    g = graph(spark, d)
    sup = table(spark, d, "supplier").select(F.col("s_suppkey").cast("long").alias("qid"), F.concat(F.lit("supplier:"), F.col("s_suppkey").cast("string")).alias("topic"))
    kg = g.triples.filter(F.col("rel").isin("supplier.parts", "part.orders"))
    rows = expand.count_paths(sup, kg, depth=2).filter("hop = 2").join(sup, "qid")
    return rows.select("topic", F.col("n_paths").cast("double").alias("n_paths"), "n_answers")


@query("w_text_similarity", f"select a.conv_id, a.turn, b.item_id, sim from (select conv_id, turn, {sql_tokens('text')} x from conversations where role = 'user') a, (select item_id, {sql_tokens('text')} y from benchmark) b, lateral (select {sql_cosine('x', 'y')} sim) where sim >= 0.3")
def _(spark, d):
    """All user turns against all benchmark items that share a word with them."""
    a = _term_index(table(spark, d, "conversations").filter("role = 'user'"), "conv_id", "turn")
    b = _term_index(table(spark, d, "benchmark"), "item_id")
    met = a.join(b.withColumnsRenamed({"row": "row_b", "size": "size_b", "n": "n_b"}), "w")
    dots = met.groupBy("row", "row_b", "conv_id", "turn", "item_id", "size", "size_b").agg(F.sum(F.col("n") * F.col("n_b")).alias("dot"))
    return dots.select("conv_id", "turn", "item_id", F.round(F.col("dot") / (F.col("size") * F.col("size_b")), 6).alias("sim")).filter("sim >= 0.3")


def _term_index(texts, *ids):
    """row, ids, size, w, n: the distinct words of each text with their counts, and its norm."""
    counted = F.transform(F.array_distinct("x"), lambda w: F.struct(w.alias("w"), F.size(F.filter("x", lambda y: y == w)).alias("n")))
    rows = texts.select(F.monotonically_increasing_id().alias("row"), *ids, tokens(F.col("text")).alias("x")).select("row", *ids, counted.alias("ws"))
    size = F.sqrt(F.aggregate("ws", F.lit(0), lambda acc, w: acc + w["n"] * w["n"]).cast("double"))
    return rows.select("row", *ids, size.alias("size"), F.explode("ws").alias("v")).select("row", *ids, "size", "v.*")


@query("w_vector_rank", """
with s as (select a.vec_id qid, b.vec_id id, a.label la, b.label lb, round(list_dot_product(a.embedding::double[], b.embedding::double[]) / (sqrt(list_dot_product(a.embedding::double[], a.embedding::double[])) * sqrt(list_dot_product(b.embedding::double[], b.embedding::double[]))), 6) score
 from embeddings a, embeddings b where a.vec_id % 100 = 0 and a.vec_id <> b.vec_id)
select qid, round(avg(case when la = lb then 1.0 else 0.0 end), 6) precision_at_10 from (select *, row_number() over (partition by qid order by score desc, id) rank from s) where rank <= 10 group by qid""")  # fmt: skip
def _(spark, d):
    e = table(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"), "label")
    q = e.filter("id % 100 = 0").select(F.col("id").alias("qid"), "vec")
    top = rank.vector_top_k(q, e.select("id", "vec"), k=10)
    labels = e.select("id", "label")
    rows = top.join(labels, "id").join(labels.select(F.col("id").alias("qid"), F.col("label").alias("mine")), "qid")
    return rows.groupBy("qid").agg(F.round(F.avg((F.col("label") == F.col("mine")).cast("double")), 6).alias("precision_at_10"))


# ---- experiment tables ----


@query("x_methods", with_(*_Q3, sql_gold(B3), _BEAM, sql_two(3), "preds as (select 'bidirectional' method, qid, tail answer from two union select 'beam', qid, tail from (" + _ALL + ") union select 'post_filter', qid, tail from (" + _ALL + ") where string_split(rels, '>')[-1] = 'part.brand')", then="""
select method, round(avg(coalesce(b / nullif(p, 0), 0)), 6) as precision, round(avg(coalesce(b / g, 0)), 6) recall, round(avg(coalesce(2.0 * b / (p + g), 0)), 6) f1 from (
 select m.method, q.qid, (select count(*) from gold where gold.qid = q.qid) g, count(x.answer) p, count(y.answer) b from (select unnest(['bidirectional', 'beam', 'post_filter']) as method) m cross join q left join preds x on x.method = m.method and x.qid = q.qid left join gold y on y.qid = x.qid and y.answer = x.answer group by 1, 2) group by method"""))  # fmt: skip
def _(spark, d):
    """The ablation's order on one workload: typed search, beam filtered afterwards, beam alone."""
    q, g = asked(spark, d, B3), graph(spark, d)
    gold = workload.gold(spark, d, q)
    pred = gold_type(q)
    ways = {
        "bidirectional": retrieve.bidirectional(q, pred, g.triples, g.entity_types, g.signatures, Config(covered=True, depth=3)),
        "beam": baselines.beam_paths(q, g.triples, **BEAM),
        "post_filter": baselines.post_filter(q, pred, g.triples, g.entity_types, g.signatures, **BEAM),
    }
    out = None
    for name, paths in ways.items():
        answers = paths.select("qid", F.col("tail").alias("answer"), F.lit(None).cast("int").alias("rank")).distinct()
        one = metrics.summary(metrics.per_question(q, answers, gold)).select(F.lit(name).alias("method"), "precision", "recall", "f1")
        out = one if out is None else out.unionByName(one)
    return out


@query("x_evidence", with_(*_BR, sql_metrics("br"), sql_forward(2), "fw as (select qid, tail answer, null::int rank from fwd)", sql_metrics("fw", "perf"), then="select 'bidirectional' method, * from (" + sql_summary("per") + ") union all select 'forward', questions, 0.0, f1, precision, recall, gold_hit from (" + sql_summary("perf") + ")"))
def _(spark, d):
    """Evidence before generation: typed search against forward search."""
    q, rows = _br_rows(spark, d)
    fwd = baselines.forward_only(q, graph(spark, d).triples, depth=2).select("qid", F.col("tail").alias("answer"), F.lit(None).cast("int").alias("rank")).distinct()
    other = metrics.per_question(q, fwd, workload.gold(spark, d, q))
    return metrics.summary(rows).select(F.lit("bidirectional").alias("method"), "*").unionByName(metrics.summary(other).select(F.lit("forward").alias("method"), "*"))
