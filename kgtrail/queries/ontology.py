"""Queries on ontology construction (O-01 to O-15)."""

from __future__ import annotations

from pyspark.sql import functions as F

from kgtrail.operators import ontology as o
from kgtrail.queries.common import KG, SIGS, with_
from kgtrail.registry import query
from kgtrail.sources import light, star
from kgtrail.sources.star import ADMIN, CATALOGUE, NO_DOMAIN, NO_RANGE

def _present() -> str:
    parts = []
    for r in CATALOGUE:
        has = f"where exists (select 1 from {r.table} where {r.head} is not null and {r.tail} is not null)"
        parts.append(f"select '{r.rel}' rel, '{r.domain}' head_type, '{r.range}' tail_type {has}")
        if r.inverse:
            parts.append(f"select '{r.inverse}', '{r.range}', '{r.domain}' {has}")
    return "present as (" + "\n union all ".join(parts) + ")"


#: The relations that occur in the tables, and a schema dump of them.
PRESENT = _present()
FACTS = f"""{PRESENT}, facts as (select rel subject, 'domain' predicate, head_type as object from present where rel <> '{NO_DOMAIN}' union all select rel, 'range', tail_type from present where rel <> '{NO_RANGE}'
 union all select 'admin.note', 'domain', '{ADMIN}' where exists (select 1 from region where r_regionkey is not null) union all select 'admin.note', 'range', 'region' where exists (select 1 from region where r_regionkey is not null))"""
PARTIAL = "part_sigs as (select coalesce(d.subject, r.subject) rel, d.object head_type, r.object tail_type from (select * from facts where predicate = 'domain') d full join (select * from facts where predicate = 'range') r on d.subject = r.subject)"
COMPLETE = "declared as (select head_type, rel, tail_type from part_sigs where head_type is not null and tail_type is not null)"

LIGHT = """light as (
 select distinct cast(doc_id as varchar) head, 'document.source' rel, source tail from documents where source is not null and source <> ''
 union all select distinct cast(doc_id as varchar), 'document.lang', lang from documents where lang is not null and lang <> ''
 union all select distinct cast(doc_id as varchar), 'document.quality', 'quality' || quality from labels where quality is not null
 union all select distinct cast(doc_id as varchar), 'document.toxicity', 'toxic' || toxic from labels where toxic is not null
 union all select distinct cast(page_id + 1000000000 as varchar), 'page.host', regexp_extract(url, '^https?://([^/?#]+)', 1) from pages where regexp_extract(url, '^https?://([^/?#]+)', 1) <> ''
 union all select distinct cast(page_id + 1000000000 as varchar), 'page.lang', regexp_extract(html, 'lang="([a-z]+)"', 1) from pages where regexp_extract(html, 'lang="([a-z]+)"', 1) <> ''
 union all select distinct cast(event_id + 2000000000 as varchar), 'event.actor', cast(user_id + 3000000000 as varchar) from events
 union all select distinct cast(event_id + 2000000000 as varchar), 'event.kind', event_type from events
 union all select distinct cast(event_id + 2000000000 as varchar), 'event.day', strftime(ts, '%Y-%m-%d') from events)"""
CALLED = "called(rel, head_name, tail_name) as (values " + ", ".join(f"('{r}', '{a}', '{b}')" for r, (a, b) in light.CALLED.items()) + ")"
OBSERVED = "observed as (select head entity, head_name etype from light join called using (rel) where cast(head as bigint) % 10 < 8 union all select tail, tail_name from light join called using (rel) where cast(head as bigint) % 10 < 8)"
MAIN = "main as (select entity, etype from (select entity, etype, row_number() over (partition by entity order by count(*) desc, etype) k from observed group by 1, 2) where k = 1)"
PAIRS = "pairs as (select rel, a.etype head_type, b.etype tail_type, count(*) support from light join main a on a.entity = head join main b on b.entity = tail group by all)"


def _declared(spark, d):
    return o.drop_types(o.from_schema(star.schema_facts(spark, d)), [ADMIN])


@query("ontology_schema", with_(FACTS, PARTIAL, COMPLETE, then="select head_type, rel, tail_type from declared"))
def _(spark, d):
    return o.from_schema(star.schema_facts(spark, d)).select("head_type", "rel", "tail_type")


@query("ontology_blocklist", with_(FACTS, PARTIAL, COMPLETE, then=f"select head_type, rel, tail_type from declared where head_type <> '{ADMIN}' and tail_type <> '{ADMIN}'"))
def _(spark, d):
    return _declared(spark, d).select("head_type", "rel", "tail_type")


@query("ontology_complete", with_(FACTS, PARTIAL, then="select rel, head_type, tail_type from part_sigs where head_type is not null and tail_type is not null"))
def _(spark, d):
    return o.complete_only(o.partial(star.schema_facts(spark, d)))


@query("ontology_incomplete", with_(FACTS, PARTIAL, then=f"""select r.rel, case when p.rel is null then 'both' when head_type is null then 'head' else 'tail' end missing
 from (select rel from present) r left join part_sigs p on p.rel = r.rel where p.rel is null or head_type is null or tail_type is null"""))  # fmt: skip
def _(spark, d):
    return o.incomplete(o.partial(star.schema_facts(spark, d)), star.present(spark, d).select("rel"))


def _completed(spark, d):
    holes = o.incomplete(o.partial(star.schema_facts(spark, d)), star.present(spark, d).select("rel"))
    kg = star.triples(spark, d)
    train = kg.filter(F.col("rel").isin(star.NO_RANGE, star.NO_DOMAIN)).filter(F.substring_index("head", ":", -1).try_cast("long") % 10 < 8)
    return o.complete_from_training(holes, train, star.entity_types(train))


COMPLETED = f"""completed as (select a.t head_type, a.rel, b.t tail_type, n support from
 (select rel, split_part(head, ':', 1) t, count(*) n from kg where rel in ('{star.NO_RANGE}', '{star.NO_DOMAIN}') and try_cast(split_part(head, ':', 2) as bigint) % 10 < 8 group by all) a
 join (select distinct rel, split_part(tail, ':', 1) t from kg where rel in ('{star.NO_RANGE}', '{star.NO_DOMAIN}') and try_cast(split_part(head, ':', 2) as bigint) % 10 < 8) b using (rel))"""


@query("ontology_completion", with_(KG, COMPLETED, then="select head_type, rel, tail_type, support from completed"))
def _(spark, d):
    return _completed(spark, d).select("head_type", "rel", "tail_type", "support")


@query("ontology_domain_range", with_(FACTS, then="select d.object head_type, d.subject rel, r.object tail_type from (select * from facts where predicate = 'domain') d join (select * from facts where predicate = 'range' union all select rel, 'range', 'area' from present where rel = 'nation.region') r on d.subject = r.subject"))
def _(spark, d):
    more = star.schema_facts(spark, d).unionByName(star.present(spark, d).filter("rel = 'nation.region'").select(F.col("rel").alias("subject"), F.lit("range").alias("predicate"), F.lit("area").alias("object")))
    web = more.withColumn("predicate", F.concat(F.lit("rdfs:"), "predicate"))
    return o.from_schema(web, domain_pred="rdfs:domain", range_pred="rdfs:range").select("head_type", "rel", "tail_type")


def _light_types(spark, d):
    kg = light.triples(spark, d)
    return kg, o.induce_entity_types(light.training(kg))


@query("ontology_main_type", with_(LIGHT, CALLED, OBSERVED, MAIN, then="select entity, etype from main"))
def _(spark, d):
    return _light_types(spark, d)[1]


@query("ontology_induced", with_(LIGHT, CALLED, OBSERVED, MAIN, PAIRS, then="select head_type, rel, tail_type, support from (select *, row_number() over (partition by rel order by support desc, head_type, tail_type) k from pairs) where k = 1"))
def _(spark, d):
    return o.induce_signatures(*_light_types(spark, d)).select("head_type", "rel", "tail_type", "support")


@query("ontology_induced_all", with_(LIGHT, CALLED, OBSERVED, MAIN, PAIRS, then="select head_type, rel, tail_type, support from (select *, support / sum(support) over (partition by rel) share from pairs) where support >= 2 and share >= 0.01"))
def _(spark, d):
    return o.induce_signatures(*_light_types(spark, d), keep="all", min_support=2, min_share=0.01).select("head_type", "rel", "tail_type", "support")


@query("ontology_hierarchy", """
select 'customer@r' || n_regionkey head_type, 'customer.segment' rel, 'segment' tail_type, count(*) support from customer join nation on c_nationkey = n_nationkey group by 1
union all select 'supplier@r' || n_regionkey, 'supplier.nation', 'nation', count(*) from supplier join nation on s_nationkey = n_nationkey group by 1""")  # fmt: skip
def _(spark, d):
    inst, sub = star.subclasses(spark, d)
    kg = star.triples(spark, d).filter(F.col("rel").isin("customer.segment", "supplier.nation"))
    plain = star.entity_types(kg).filter(F.col("etype").isin("segment", "nation"))
    return o.induce_with_hierarchy(kg, inst.unionByName(plain), sub, levels=1).select("head_type", "rel", "tail_type", "support")


MERGED = f"""merged as (select head_type, rel, tail_type, arg_min(support, o) support, arg_min(source, o) source from (
 select head_type, rel, tail_type, 0 support, 'declared' source, 0 o from declared where head_type <> '{ADMIN}'
 union all select head_type, rel, tail_type, support, 'completed', 1 from completed
 union all select split_part(head, ':', 1), rel, split_part(tail, ':', 1), count(*), 'induced', 2 from kg group by 1, 2, 3) group by 1, 2, 3)"""


def _merged(spark, d):
    kg = star.triples(spark, d)
    return o.merge(_declared(spark, d), _completed(spark, d), o.induce_signatures(kg, star.entity_types(kg)))


@query("ontology_merged", with_(KG, FACTS, PARTIAL, COMPLETE, COMPLETED, MERGED, then="select head_type, rel, tail_type, cast(support as bigint) support, source from merged"))
def _(spark, d):
    return _merged(spark, d)


@query("ontology_stats", with_(KG, SIGS, then="""select 'triples' metric, cast((select count(*) from kg) as double) as value union all select 'relations', count(distinct rel) from sigs union all select 'signatures', count(*) from sigs
 union all select 'types', count(distinct t) from (select head_type t from sigs union all select tail_type from sigs) union all select 'compression', round((select count(*) from kg) / count(*), 6) from sigs"""))  # fmt: skip
def _(spark, d):
    return o.stats(star.signatures(spark), star.triples(spark, d))


@query("ontology_coverage", with_(FACTS, PARTIAL, COMPLETE, then="""select scope, count(*) total, count(case when f.rel is null then 1 end) incomplete, round(100.0 * count(case when f.rel is null then 1 end) / count(*), 6) pct from (
 select 'a' scope, unnest(['customer.orders', 'order.parts', 'order.status']) rel union all select 'b', unnest(['customer.orders', 'order.parts', 'order.priority', 'order.status', 'part.brand'])
 union all select 'shared', unnest(['customer.orders', 'order.parts', 'order.status']) union all select 'union', unnest(['customer.orders', 'order.parts', 'order.priority', 'order.status', 'part.brand'])) s
 join present using (rel) left join (select distinct rel from declared) f on f.rel = s.rel group by scope"""))  # fmt: skip
def _(spark, d):
    used = lambda *r: star.present(spark, d).filter(F.col("rel").isin(*r)).select("rel")
    a = used("customer.orders", "order.parts", "order.status")
    b = used("customer.orders", "order.parts", "order.priority", "order.status", "part.brand")
    return o.coverage(o.partial(star.schema_facts(spark, d)), a, b)


@query("ontology_by_tail", with_(PRESENT, then="select tail_type, string_agg(head_type || '/' || rel, ',' order by head_type || '/' || rel) last_hops from present group by 1"))
def _(spark, d):
    return o.by_tail(star.present(spark, d)).select("tail_type", F.concat_ws(",", "last_hops").alias("last_hops"))


@query("ontology_violations", with_(KG, FACTS, PARTIAL, COMPLETE, then="select rel, count(*) n from kg where not exists (select 1 from declared s where s.rel = kg.rel and s.head_type = split_part(head, ':', 1) and s.tail_type = split_part(tail, ':', 1)) group by rel"))
def _(spark, d):
    kg = star.triples(spark, d)
    return o.violations(kg, star.entity_types(kg), _declared(spark, d))
