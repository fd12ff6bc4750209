"""Queries on retrieval and ranking (R-01 to R-20, K-01 to K-06)."""

from __future__ import annotations

from pyspark.sql import functions as F

from kgtrail.functions.text import path_text
from kgtrail.operators import graph as graphs
from kgtrail.operators import rank
from kgtrail.plans import expand, retrieve
from kgtrail.plans.retrieve import Config
from kgtrail.queries.common import KG, SIGS, asked, gold_type, graph, path_rows, sql_chain, sql_forward, sql_questions, sql_scored, sql_tokens, sql_two, sql_walks, with_
from kgtrail.registry import query
from kgtrail.sources.shared import stored
from kgtrail.sources.star import table

B3 = ("w_customer_brands",)
_Q3 = (KG, SIGS, sql_questions(*B3))
ROWS = "select qid, len, rels, tail, path_key from "


def _two(spark, d, names, **config):
    q, g = asked(spark, d, *names), graph(spark, d)
    return path_rows(retrieve.bidirectional(q, gold_type(q), g.triples, g.entity_types, g.signatures, Config(covered=True, texts=True, **config)))


@query("last_hop_relations", with_(SIGS, sql_questions(*B3, "w_customer_region"), then="select qid, rel, head_type from q join sigs on tail_type = etype"))
def _(spark, d):
    q = asked(spark, d, *B3, "w_customer_region")
    return retrieve.last_hop(gold_type(q), graph(spark, d).signatures)


@query("expand_one_hop", with_(*_Q3, then=ROWS + f"({sql_chain(1)})"))
def _(spark, d):
    q = asked(spark, d, *B3)
    return path_rows(expand.step(expand.start(q), graph(spark, d).triples, shared=True).withColumnRenamed("v", "tail"))


@query("prefixes_depth2", with_(*_Q3, then=f"select qid, 0 len, '' rels, topic tail, topic path_key from q union all {ROWS} ({sql_chain(1)}) union all {ROWS} ({sql_chain(2)})"))
def _(spark, d):
    q = asked(spark, d, *B3)
    return path_rows(expand.union(expand.prefixes(q, graph(spark, d).triples, depth=2)).withColumnRenamed("v", "tail"))


@query("meeting_nodes", with_(*_Q3, then=f"""select p.qid, p.tail v, z.rel, count(*) prefixes from (select qid, tail from ({sql_chain(1)}) union all select qid, tail from ({sql_chain(2)}) union all select qid, topic from q) p
 join q using (qid) join sigs z on z.tail_type = q.etype and z.head_type = split_part(p.tail, ':', 1) group by all"""))  # fmt: skip
def _(spark, d):
    q, g = asked(spark, d, *B3), graph(spark, d)
    fronts = retrieve.typed_prefixes(q, gold_type(q), g.triples, g.signatures, depth=2)
    met = retrieve.meet(stored(expand.union(fronts), "prefixes"), g.entity_types, retrieve.last_hop(gold_type(q), g.signatures))
    return met.groupBy("qid", "v", "rel").agg(F.count("*").alias("prefixes"))


@query("bidirectional_paths", with_(*_Q3, sql_two(3), then=ROWS + "two"))
def _(spark, d):
    return _two(spark, d, B3, depth=3)


for _h, _n in ((1, "w_customer_orders"), (2, "w_customer_parts"), (3, "w_customer_supplier_nations"), (4, "w_customer_supplier_regions")):

    @query(f"bidirectional_{_h}hop", with_(KG, SIGS, sql_questions(_n), sql_two(_h), then=ROWS + "two"))
    def _(spark, d, h=_h, n=_n):
        return _two(spark, d, (n,), depth=h, use_mask=h == 4)


@query("bidirectional_masked", with_(*_Q3, sql_two(3), then=ROWS + "two"))
def _(spark, d):
    return _two(spark, d, B3, depth=3, use_mask=True)


@query("bidirectional_exact", with_(KG, SIGS, sql_questions("w_customer_supplier_nations"), sql_two(3, exact=True), then=ROWS + "two"))
def _(spark, d):
    return _two(spark, d, ("w_customer_supplier_nations",), depth=3, length_mode="exact")


@query("bidirectional_edge_check", with_(*_Q3, sql_two(3, check="edge"), then=ROWS + "two"))
def _(spark, d):
    return _two(spark, d, B3, depth=3, head_check="edge")


@query("bidirectional_simple", with_(KG, SIGS, sql_questions("w_segment_peers"), then=f"""select qid, len, rels, tail, path_key from (
 {sql_chain(1, where="t1.rel in (select rel from sigs where tail_type = s.etype) and t1.tail <> s.topic")}
 union all {sql_chain(2, where="t2.rel in (select rel from sigs where tail_type = s.etype) and t1.tail <> s.topic and t2.tail <> s.topic and t2.tail <> t1.tail")})"""))  # fmt: skip
def _(spark, d):
    return _two(spark, d, ("w_segment_peers",), depth=2, path_mode="simple")


@query("fallback_paths", with_(KG, sql_questions("w_customer_region"), sql_forward(2), then=ROWS + "fwd"))
def _(spark, d):
    return path_rows(retrieve.fallback(asked(spark, d, "w_customer_region"), graph(spark, d).triples, depth=2, texts=True))


_R = ("w_customer_parts", "w_customer_region")
ROUTED = f"""select qid, len, rels, tail, path_key, 'bidirectional' mode from (select * from two) where qid in (select qid from q where template = 'w_customer_parts')
 union all select qid, len, rels, tail, path_key, 'fallback' from fwd where qid not in (select qid from q where template = 'w_customer_parts')"""


@query("retrieval_router", with_(KG, SIGS, sql_questions(*_R), sql_two(2), sql_forward(2), then=ROUTED))
def _(spark, d):
    q, g = asked(spark, d, *_R), graph(spark, d)
    pred = q.select("qid", F.when(F.col("template") == "w_customer_parts", F.col("etype")).otherwise("planet").alias("etype"))
    routed = retrieve.route(q, pred, g.triples, g.entity_types, g.signatures, Config(covered=True, depth=2))
    return routed.select("qid", "len", F.concat_ws(">", "rels").alias("rels"), "tail", "path_key", "mode")


@query("type_reach_mask", with_(SIGS, sql_questions(*B3), """m1 as (select distinct qid, head_type etype from q join sigs on tail_type = etype), m2 as (select distinct qid, head_type etype from m1 join sigs on tail_type = etype),
 m3 as (select distinct qid, head_type etype from m2 join sigs on tail_type = etype)""", then="select qid, 1 hops_left, etype from m1 union all select qid, 2, etype from m2 union all select qid, 3, etype from m3"))  # fmt: skip
def _(spark, d):
    return retrieve.reach_mask(graph(spark, d).signatures, gold_type(asked(spark, d, *B3)), depth=3)


def _plans(spark, d, q, depth):
    types = q.select("qid", F.substring_index("topic", ":", 1).alias("etype"))
    return retrieve.type_plans(q, gold_type(q), graph(spark, d).signatures, types, depth=depth)


PLANS = """plans as (select q.qid, a.rel rels from q join sigs a on a.head_type = split_part(q.topic, ':', 1) where a.tail_type = q.etype
 union select q.qid, a.rel || '>' || b.rel from q join sigs a on a.head_type = split_part(q.topic, ':', 1) join sigs b on b.head_type = a.tail_type where b.tail_type = q.etype
 union select q.qid, a.rel || '>' || b.rel || '>' || c.rel from q join sigs a on a.head_type = split_part(q.topic, ':', 1) join sigs b on b.head_type = a.tail_type join sigs c on c.head_type = b.tail_type where c.tail_type = q.etype)"""


@query("type_plans", with_(SIGS, sql_questions(*B3), PLANS, then="select qid, rels from plans"))
def _(spark, d):
    return _plans(spark, d, asked(spark, d, *B3), 3).select("qid", F.concat_ws(">", "rels").alias("rels"))


@query("grounded_plans", with_(*_Q3, PLANS, sql_forward(3), then="select f.qid, len, f.rels, tail, path_key from fwd f join plans p on p.qid = f.qid and p.rels = f.rels"))
def _(spark, d):
    q = asked(spark, d, *B3)
    return path_rows(retrieve.ground(q, _plans(spark, d, q, 3), graph(spark, d).triples, depth=3))


@query("tail_type_violations", with_(*_Q3, sql_two(3), then="select qid, path_key from two where split_part(tail, ':', 1) <> 'brand'"))
def _(spark, d):
    q, g = asked(spark, d, *B3), graph(spark, d)
    paths = retrieve.bidirectional(q, gold_type(q), g.triples, g.entity_types, g.signatures, Config(covered=True, depth=3))
    return retrieve.check_tail_type(paths, g.entity_types, gold_type(q)).select("qid", "path_key")


COUNTS = """n0 as (select qid, topic v, cast(1 as double) n from q),
n1 as (select qid, rel, tail v, n from n0 join kg on head = v), s1 as (select qid, v, sum(n) n from n1 group by 1, 2),
n2 as (select qid, rel, tail v, n from s1 join kg on head = v), s2 as (select qid, v, sum(n) n from n2 group by 1, 2),
n3 as (select qid, rel, tail v, n from s2 join kg on head = v), s3 as (select qid, v, sum(n) n from n3 group by 1, 2),
n4 as (select qid, rel, tail v, n from s3 join kg on head = v)"""


def _counted(where: str) -> str:
    return " union all ".join(f"select qid, {i} hop, sum(n) n_paths, count(distinct v) n_answers from n{i} {where} group by qid" for i in (1, 2, 3, 4))


def _double(rows):
    return rows.withColumn("n_paths", F.col("n_paths").cast("double"))


@query("path_counts_forward", with_(KG, sql_questions(*B3), COUNTS, then=_counted("")))
def _(spark, d):
    q, g = asked(spark, d, *B3), graph(spark, d)
    hops = retrieve.typed_hops(g.signatures, g.signatures.select(F.col("tail_type").alias("etype")), depth=4, starts=retrieve.topic_types(q))
    return _double(expand.count_back(q, g.triples, hops, answers=False).join(expand.reached(q, g.triples, depth=4), ["qid", "hop"]))


@query("path_counts_constrained", with_(*_Q3, COUNTS, then=_counted("where rel in (select rel from sigs where tail_type = 'brand')")))
def _(spark, d):
    q, g = asked(spark, d, *B3), graph(spark, d)
    hops = retrieve.typed_hops(g.signatures, gold_type(q), depth=4, starts=retrieve.topic_types(q))
    return _double(expand.count_back(q, g.triples, hops, last=retrieve.last_hop(gold_type(q), g.signatures)))


@query("branching_factor", with_(KG, SIGS, then="""select tail_type etype, round((select count(*) / count(distinct head) from kg), 6) b, round(count(*) / (select count(distinct head) from kg), 6) beta, round(count(*) / (select count(*) from kg), 6) selectivity
 from kg join sigs using (rel) group by tail_type"""))  # fmt: skip
def _(spark, d):
    g = graph(spark, d)
    return expand.branching(g.triples, g.signatures)


@query("candidate_answers", with_(*_Q3, sql_two(3), then="select qid, tail answer, count(*) n_paths from two group by 1, 2"))
def _(spark, d):
    q, g = asked(spark, d, *B3), graph(spark, d)
    return retrieve.answers(retrieve.bidirectional(q, gold_type(q), g.triples, g.entity_types, g.signatures, Config(covered=True, depth=3))).select("qid", "answer", "n_paths")


@query("path_text", with_(*_Q3, sql_walks(1, "w"), "pb as (select head, rel, tail from kg where rel = 'order.parts')", then="""select w.qid, w.path_key || '|' || b.rel || '|' || b.tail path_key, w.v || ' -> ' || replace(w.rel, '.', ' ') || ' -> ' || w.tail || ' -> ' || replace(b.rel, '.', ' ') || ' -> ' || b.tail as text
 from w_1 w join pb b on b.head = w.tail"""))  # fmt: skip
def _(spark, d):
    q, g = asked(spark, d, *B3), graph(spark, d)
    two = expand.step(expand.step(expand.start(q), g.triples), g.triples, rels=["order.parts"])
    return two.select("qid", "path_key", path_text(F.col("rels"), F.col("nodes")).alias("text"))


@query("subgraph_triples", with_(KG, sql_questions(*B3), "heads as materialized (select distinct topic head from q union select tail from kg join q on head = topic)", then="select head, rel, tail from kg join heads using (head)"))
def _(spark, d):
    return graphs.neighbourhood(asked(spark, d, *B3), graph(spark, d).triples, depth=2).select("head", "rel", "tail")


@query("topic_lookup", "select cast(c_custkey as bigint) qid, 'customer:' || c_custkey entity, 0 edits from customer")
def _(spark, d):
    c = table(spark, d, "customer")
    texts = c.select(F.col("c_custkey").cast("long").alias("qid"), F.upper("c_name").alias("text"))
    names = c.select(F.concat(F.lit("customer:"), F.col("c_custkey").cast("string")).alias("entity"), F.col("c_name").alias("name"))
    return graphs.link_topics(texts, names)


@query("topic_lookup_edits", "select cast(s_suppkey as bigint) qid, 'supplier:' || b.s_suppkey entity, cast(levenshtein(lower(replace(a.s_name, '#', 'x')), lower(replace(b.s_name, '#', ' '))) as int) edits from supplier a, supplier b where levenshtein(lower(replace(a.s_name, '#', 'x')), lower(replace(b.s_name, '#', ' '))) <= 1".replace("cast(s_suppkey", "cast(a.s_suppkey"))
def _(spark, d):
    c = table(spark, d, "supplier")
    texts = c.select(F.col("s_suppkey").cast("long").alias("qid"), F.replace("s_name", F.lit("#"), F.lit("x")).alias("text"))
    names = c.select(F.concat(F.lit("supplier:"), F.col("s_suppkey").cast("string")).alias("entity"), F.col("s_name").alias("name"))
    return graphs.link_topics(texts, names, max_edit=1)


_TOP = f"select qid, path_key, score, row_number() over (partition by qid order by score desc, len, path_key) rank from scored"


@query("rerank_topk", with_(*_Q3, sql_two(3), sql_scored("two"), then=f"select qid, path_key, score, cast(rank as int) rank from ({_TOP}) where rank <= 16"))
def _(spark, d):
    q, g = asked(spark, d, *B3), graph(spark, d)
    paths = retrieve.bidirectional(q, gold_type(q), g.triples, g.entity_types, g.signatures, Config(covered=True, depth=3))
    return rank.top_k(paths, q, k=16).select("qid", "path_key", "score", "rank")


@query("rerank_token_cosine", with_(KG, sql_questions("w_customer_region"), sql_forward(2), sql_scored("fwd"), then="select distinct qid, rels, score from scored"))
def _(spark, d):
    q = asked(spark, d, "w_customer_region")
    paths = retrieve.fallback(q, graph(spark, d).triples, depth=2)
    return rank.TokenCosine().score(paths, q).select("qid", F.concat_ws(">", "rels").alias("rels"), "score").distinct()


def _pool2(spark, d):
    q = asked(spark, d, "w_customer_region")
    return q, retrieve.fallback(q, graph(spark, d).triples, depth=2)


_RANKED = "select qid, path_key, score, cast(rank as int) rank from (select *, row_number() over (partition by qid order by score desc, len, path_key) rank from scored) where rank <= 16"
_KINDS = f"kinds as (select distinct qid, rels from fwd), texts as (select distinct rels from kinds), pt as (select rels, unnest({sql_tokens('rels')}) t from texts), qt as (select qid, unnest({sql_tokens('text')}) t from q)"
_COSINE = "dots as (select k.qid, k.rels, sum(p.w * a.w) dot from kinds k join wp p using (rels) join wq a on a.qid = k.qid and a.t = p.t group by 1, 2), scored as (select f.*, coalesce(round(dot / nullif(np * nq, 0), 6), 0) score from fwd f left join dots using (qid, rels) left join (select rels, sqrt(sum(w * w)) np from wp group by 1) using (rels) left join (select qid, sqrt(sum(w * w)) nq from wq group by 1) using (qid))"
_TFIDF = "tf as (select rels, t, count(*) n from pt group by 1, 2), idf as (select t, ln(((select count(*) from texts) + 1) / (count(*) + 1)) idf from tf group by 1), wp as (select rels, t, n * (idf + 1) w from tf join idf using (t)), wq as (select qid, t, n * (coalesce(idf, 0) + 1) w from (select qid, t, count(*) n from qt group by 1, 2) left join idf using (t))"


def _hashed(source: str, key: str) -> str:
    return f"(select {key}, cast('0x' || substr(md5(t), 1, 8) as bigint) % 32 t, sum(case when cast('0x' || substr(md5(t), 9, 1) as bigint) % 2 = 0 then 1.0 else -1.0 end) w from {source} group by 1, 2)"


@query("rerank_tfidf", with_(KG, sql_questions("w_customer_region"), sql_forward(2), _KINDS, _TFIDF, _COSINE, then=_RANKED))
def _(spark, d):
    q, paths = _pool2(spark, d)
    return rank.top_k(paths, q, k=16, encoder=rank.TfIdf()).select("qid", "path_key", "score", "rank")


@query("rerank_hashed_vector", with_(KG, sql_questions("w_customer_region"), sql_forward(2), _KINDS, "wp as " + _hashed("pt", "rels"), "wq as " + _hashed("qt", "qid"), _COSINE, then=_RANKED))
def _(spark, d):
    q, paths = _pool2(spark, d)
    return rank.top_k(paths, q, k=16, encoder=rank.HashedVector(32)).select("qid", "path_key", "score", "rank")


def _vectors(spark, d):
    e = table(spark, d, "embeddings")
    items = e.select(F.col("vec_id").alias("id"), F.col("embedding").alias("vec"))
    return items.filter("id % 100 = 0").withColumnRenamed("id", "qid"), items


@query("embedding_topk", """
with s as (select a.vec_id qid, b.vec_id id, round(list_dot_product(a.embedding::double[], b.embedding::double[]) / (sqrt(list_dot_product(a.embedding::double[], a.embedding::double[])) * sqrt(list_dot_product(b.embedding::double[], b.embedding::double[]))), 6) score
 from embeddings a, embeddings b where a.vec_id % 100 = 0 and a.vec_id <> b.vec_id)
select qid, id, score, cast(rank as int) rank from (select *, row_number() over (partition by qid order by score desc, id) rank from s) where rank <= 10""")  # fmt: skip
def _(spark, d):
    q, items = _vectors(spark, d)
    return rank.vector_top_k(q, items, k=10)


@query("embedding_lsh_recall")
def _(spark, d):
    q, items = _vectors(spark, d)
    return rank.recall(rank.lsh_top_k(q, items, k=10, bits=8, tables=24), rank.vector_top_k(q, items, k=10))
