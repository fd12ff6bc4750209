"""Queries on answer-type supervision and prediction (P-01 to P-12)."""

from __future__ import annotations

from pyspark.sql import functions as F

from kgtrail.operators import supervision, typepredict, workload
from kgtrail.queries.common import KG, SIGS, asked, every, graph, gold_type, sql_chain, sql_cosine, sql_gold, sql_questions, sql_tokens, typed, with_
from kgtrail.registry import query
from kgtrail.sources.star import table

SHORT = ("w_customer_nation", "w_customer_region", "w_customer_orders", "w_part_supplier_nations", "w_customer_brands")
REACHED = "reached as (" + " union all ".join(f"select qid, len, rels, rel, tail from ({sql_chain(i)})" for i in (1, 2, 3)) + ")"
SHORTEST = "best as (select r.qid, r.tail, min(len) len from reached r join gold g on g.qid = r.qid and g.answer = r.tail group by 1, 2), shortest as (select distinct r.qid, r.tail answer, r.len, r.rels, r.rel from reached r join best b using (qid, tail, len))"
_BASE = (KG, sql_questions(*SHORT), sql_gold(*SHORT), REACHED, SHORTEST)


def _shortest(spark, d):
    q = asked(spark, d, *SHORT)
    g, gold = graph(spark, d), typed(workload.gold(spark, d, q))
    return supervision.shortest_paths(q, gold, g.triples, max_len=3, sigs=g.signatures)


@query("shortest_path_len", with_(*_BASE, then="select distinct qid, answer, len, rels from shortest"))
def _(spark, d):
    return _shortest(spark, d).select("qid", "answer", "len", F.concat_ws(">", "rels").alias("rels"))


@query("shortest_last_relation", with_(*_BASE, then="select distinct qid, rel from shortest"))
def _(spark, d):
    return supervision.last_relation(_shortest(spark, d))


VALID = "valid as (select distinct qid, tail_type etype from shortest join sigs using (rel))"


def _target(spark, d):
    g = graph(spark, d)
    return supervision.soft_target(supervision.valid_types(supervision.last_relation(_shortest(spark, d)), g.signatures))


@query("answer_types", with_(*_BASE, SIGS, VALID, then="select qid, etype from valid"))
def _(spark, d):
    return _target(spark, d).select("qid", "etype")


@query("type_soft_target", """
with last as (select distinct o_custkey qid, cast(year(o_orderdate) as varchar) rel from orders), s as (select distinct cast(year(o_orderdate) as varchar) rel, o_orderstatus tail_type from orders union select distinct cast(year(o_orderdate) as varchar), o_orderpriority from orders where o_totalprice > 400000),
v as (select distinct qid, tail_type etype from last join s using (rel)) select cast(qid as bigint) qid, etype, round(1.0 / count(*) over (partition by qid), 6) q from v""")  # fmt: skip
def _(spark, d):
    """Each customer's years of orders stand for last relations; a year leads to the states of its orders
    and to the priorities of its dear ones."""
    orders = table(spark, d, "orders").withColumn("rel", F.year("o_orderdate").cast("string"))
    last = orders.select(F.col("o_custkey").cast("long").alias("qid"), "rel").distinct()
    dear = orders.filter("o_totalprice > 400000").select("rel", F.col("o_orderpriority").alias("tail_type"))
    sigs = orders.select("rel", F.col("o_orderstatus").alias("tail_type")).unionByName(dear).distinct()
    return supervision.soft_target(supervision.valid_types(last, sigs)).withColumn("q", F.round("q", 6))


#: Questions about every customer and part.
MANY = ("w_customer_nation", "w_part_brand", "w_customer_orders", "w_customer_region", "w_customer_parts", "w_part_supplier_nations", "w_segment_peers", "w_customer_brands")
NAMES = {"nation": "place.nation", "region": "place.region", "brand": "item.brand", "part": "item.part", "order": "trade.order", "customer": "party.customer"}


def _many(spark, d):
    q = every(spark, d, *MANY)
    names = F.create_map(*[F.lit(x) for kv in NAMES.items() for x in kv])
    return q.withColumn("etype", names[F.col("etype")])


def _model(spark, d):
    q = _many(spark, d)
    train = q.filter("split = 'train'")
    target = train.select("qid", "etype", F.lit(1.0).alias("q"))
    return q, typepredict.NaiveBayes().fit(train, target)


_MANY = sql_questions(*MANY, step=1)
_NAMED = "case etype " + " ".join(f"when '{a}' then '{b}'" for a, b in NAMES.items()) + " end"
NB = f"""qn as (select qid, split, text, template, {_NAMED} etype, {sql_tokens('text')} toks from q),
trn as (select * from qn where split = 'train'),
cls as (select etype, count(*) * 1.0 n_c from trn group by 1),
ct as (select etype, token, count(*) * 1.0 n_ct from (select etype, unnest(toks) token from trn) group by 1, 2),
prior as (select etype, ln((n_c + 1) / ((select sum(n_c) from cls) + (select count(*) from cls))) prior, (select sum(n_ct) from ct c where c.etype = cls.etype) + (select count(distinct token) from ct) den from cls),
tok as (select qid, unnest(toks) token from qn),
raw as (select a.qid, p.etype, p.prior + a.len * (0 - ln(p.den)) + coalesce(g.gain, 0) raw from (select qid, len(toks) len from qn) a cross join prior p
  left join (select qid, etype, sum(ln(n_ct + 1)) gain from tok join ct using (token) group by 1, 2) g on g.qid = a.qid and g.etype = p.etype),
scores as (select qid, etype, raw - top - ln(sum(exp(raw - top)) over (partition by qid)) logp from (select *, max(raw) over (partition by qid) top from raw)),
ranked as (select *, row_number() over (partition by qid order by round(logp, 9) desc, etype) k from scores)"""


@query("type_nb_predict", with_(_MANY, NB, then="select qid, etype, round(logp, 6) + 0 logp from ranked where k = 1 and qid in (select qid from qn where split = 'test')"))
def _(spark, d):
    q, model = _model(spark, d)
    return typepredict.predict(model.scores(q.filter("split = 'test'"))).select("qid", "etype", (F.round("logp", 6) + F.lit(0.0)).alias("logp"))


@query("type_top_m", with_(_MANY, NB, then="select qid, etype, k from ranked where k <= 2 and qid in (select qid from qn where split = 'test')"))
def _(spark, d):
    q, model = _model(spark, d)
    best = typepredict.predict(model.scores(q.filter("split = 'test'")), m=2)
    from pyspark.sql import Window

    return best.withColumn("k", F.row_number().over(Window.partitionBy("qid").orderBy(F.desc(F.round("logp", 9)), "etype")).cast("long")).select("qid", "etype", "k")


@query("type_chain_logp", with_(_MANY, NB, then="select qid, etype, round(logp, 5) + 0 logp from scores where qid in (select qid from qn where split = 'test')"))
def _(spark, d):
    q, model = _model(spark, d)
    return typepredict.chain_logp(model.scores(q.filter("split = 'test'"))).select("qid", "etype", (F.round("logp", 5) + F.lit(0.0)).alias("logp"))


@query("type_accuracy", with_(_MANY, NB, then="select count(*) questions, round(avg(case when r.etype = qn.etype then 1.0 else 0.0 end), 6) accuracy from ranked r join qn using (qid) where k = 1 and split = 'test'"))
def _(spark, d):
    q, model = _model(spark, d)
    test = q.filter("split = 'test'")
    return typepredict.accuracy(typepredict.predict(model.scores(test)), gold_type(test))


@query("type_cross_entropy", with_(_MANY, NB, then="select round(avg(-logp), 5) cross_entropy from scores s join qn using (qid, etype) where split = 'test'"))
def _(spark, d):
    q, model = _model(spark, d)
    test = q.filter("split = 'test'")
    target = test.select("qid", "etype", F.lit(1.0).alias("q"))
    return typepredict.cross_entropy(target, model.scores(test)).withColumn("cross_entropy", F.round("cross_entropy", 5))


@query("type_knn_predict", with_(_MANY, NB, f"""protos as (select proto, etype, {sql_tokens('proto')} b from (select distinct regexp_replace(text, '[0-9]+', '', 'g') proto, etype from trn)),
ask as (select qid, {sql_tokens("regexp_replace(text, '[0-9]+', '', 'g')")} a from qn where split = 'test'),
sims as (select qid, etype, proto, {sql_cosine('a', 'b')} sim from ask cross join protos),
near as (select * from (select *, row_number() over (partition by qid order by sim desc, proto, etype) k from sims) where k <= 3),
votes as (select qid, etype, sum(sim) s from near group by 1, 2)""", then="select qid, etype from (select qid, etype, row_number() over (partition by qid order by round(ln(s / total), 9) desc, etype) k from (select *, sum(s) over (partition by qid) total from votes)) where k = 1"))  # fmt: skip
def _(spark, d):
    q = _many(spark, d)
    train = q.filter("split = 'train'")
    model = typepredict.Nearest(3).fit(train, train.select("qid", "etype", F.lit(1.0).alias("q")))
    return typepredict.predict(model.scores(q.filter("split = 'test'"))).select("qid", "etype")


@query("type_oracle", with_(*_BASE, SIGS, VALID, then="select qid, etype, round(ln(1.0 / count(*) over (partition by qid)), 6) logp from valid"))
def _(spark, d):
    return typepredict.Oracle(_target(spark, d)).scores(asked(spark, d, *SHORT)).withColumn("logp", F.round("logp", 6))


@query("oneshot_sample", with_(_MANY, then="select qid, template from (select *, row_number() over (partition by template order by md5(qid || '#0'), qid) k from q where split = 'train') where k = 1"))
def _(spark, d):
    return workload.one_shot(_many(spark, d).filter("split = 'train'")).select("qid", "template")
