"""The operator surface a user of the methods needs: scans, joins, aggregates, windows, functions
and the batch twins of the streaming operators (SURVEY 2.9 to 2.15)."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from kgtrail.functions import vector
from kgtrail.operators import graph as graphs
from kgtrail.plans import skew, temporal
from kgtrail.queries.common import KG, graph, with_
from kgtrail.queries.ontology import LIGHT
from kgtrail.registry import query
from kgtrail.sources import light, star
from kgtrail.sources.star import table
from kgtrail.streaming import events as stream

C = F.col


def _q(key, sql, f):
    query(key, sql)(f)


# ---- sources ----
_q("scan_parquet", "select o_orderkey, o_totalprice from orders where o_orderpriority = '1-URGENT' and o_totalprice > 300000",
   lambda s, d: table(s, d, "orders").filter("o_orderpriority = '1-URGENT' and o_totalprice > 300000").select("o_orderkey", "o_totalprice"))
_q("triples_star", with_(KG, then="select rel, count(*) n, count(distinct head) heads, count(distinct tail) tails from kg group by rel"),
   lambda s, d: star.triples(s, d).groupBy("rel").agg(F.count("*").alias("n"), F.countDistinct("head").alias("heads"), F.countDistinct("tail").alias("tails")))
_q("triples_by_relation", with_(KG, then="select head, tail from kg where rel = 'part.brand'"),
   lambda s, d: star.triples(s, d).filter("rel = 'part.brand'").select("head", "tail"))
_q("triples_light", with_(LIGHT, then="select head, rel, tail from light"), lambda s, d: light.triples(s, d))
_q("dictionary_roundtrip", with_(KG, then="select head, rel, tail from kg where rel in ('nation.region', 'part.brand')"),
   lambda s, d: (lambda kg: graphs.decode(graphs.encode(kg), graphs.dictionary(kg)))(star.triples(s, d).filter(C("rel").isin("nation.region", "part.brand"))))


@query("sql_view_paths", with_(KG, then="select a.head topic, b.tail answer, count(*) n from kg a join kg b on b.head = a.tail where a.rel = 'customer.nation' and b.rel = 'nation.region' group by 1, 2"))
def _(spark, d):
    graph(spark, d).triples.createOrReplaceTempView("kg_triples")
    return spark.sql("select a.head as topic, b.tail as answer, count(*) as n from kg_triples a join kg_triples b on b.head = a.tail where a.rel = 'customer.nation' and b.rel = 'nation.region' group by 1, 2")


# ---- projections, filters ----
_q("op_project", "select p_partkey, p_size * 2 twice, upper(p_name) as name from part", lambda s, d: table(s, d, "part").select("p_partkey", (C("p_size") * 2).alias("twice"), F.upper("p_name").alias("name")))
_q("op_filter_in", "select p_partkey, p_brand from part where p_brand in ('Brand#1', 'Brand#2')", lambda s, d: table(s, d, "part").filter(C("p_brand").isin("Brand#1", "Brand#2")).select("p_partkey", "p_brand"))
_q("op_filter_range", "select o_orderkey from orders where o_orderdate between timestamp '1997-01-01' and timestamp '1997-12-31' and o_totalprice between 1000 and 50000",
   lambda s, d: table(s, d, "orders").filter("o_orderdate between timestamp '1997-01-01' and timestamp '1997-12-31' and o_totalprice between 1000 and 50000").select("o_orderkey"))
_q("op_nulls", "select d.doc_id, coalesce(toxic, -1) toxic, toxic is null missing from documents d left join labels l on l.doc_id = d.doc_id",
   lambda s, d: table(s, d, "documents").select("doc_id").join(table(s, d, "labels"), "doc_id", "left").select("doc_id", F.coalesce("toxic", F.lit(-1)).alias("toxic"), C("toxic").isNull().alias("missing")))
_q("op_like", "select p_partkey from part where p_name like 'red%' and regexp_matches(p_name, 'o[lr]t?')", lambda s, d: table(s, d, "part").filter(C("p_name").like("red%") & C("p_name").rlike("o[lr]t?")).select("p_partkey"))
_q("op_case", "select s_suppkey, case when s_acctbal < 0 then 'debt' when s_acctbal < 5000 then 'low' else 'high' end band from supplier",
   lambda s, d: table(s, d, "supplier").select("s_suppkey", F.when(C("s_acctbal") < 0, "debt").when(C("s_acctbal") < 5000, "low").otherwise("high").alias("band")))
_q("op_distinct", "select distinct o_custkey, o_orderstatus from orders", lambda s, d: table(s, d, "orders").select("o_custkey", "o_orderstatus").distinct())
_q("op_exists", "select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey and o_totalprice > 450000)",
   lambda s, d: table(s, d, "customer").join(table(s, d, "orders").filter("o_totalprice > 450000"), C("o_custkey") == C("c_custkey"), "left_semi").select("c_custkey"))
_q("op_not_exists", "select c_custkey from customer where not exists (select 1 from orders where o_custkey = c_custkey and o_totalprice > 300000)",
   lambda s, d: table(s, d, "customer").join(table(s, d, "orders").filter("o_totalprice > 300000"), C("o_custkey") == C("c_custkey"), "left_anti").select("c_custkey"))


@query("op_scalar_subquery", "select p_partkey from part where p_retailprice > (select avg(p_retailprice) from part)")
def _(spark, d):
    table(spark, d, "part").createOrReplaceTempView("part_v")
    return spark.sql("select p_partkey from part_v where p_retailprice > (select avg(p_retailprice) from part_v)")


_q("op_pivot", "select o_orderpriority, count(case when o_orderstatus = 'F' then 1 end) f, count(case when o_orderstatus = 'O' then 1 end) o from orders group by 1",
   lambda s, d: table(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O"]).agg(F.count(F.lit(1))).select("o_orderpriority", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o")))
_q("op_unpivot", "select s_suppkey, 'nation' name, cast(s_nationkey as double) as value from supplier union all select s_suppkey, 'balance', s_acctbal from supplier",
   lambda s, d: table(s, d, "supplier").select("s_suppkey", C("s_nationkey").cast("double").alias("nation"), C("s_acctbal").alias("balance")).unpivot("s_suppkey", ["nation", "balance"], "name", "value"))
_q("op_explode", "select p_partkey, pos - 1 pos, w[pos] word from (select p_partkey, string_split(p_name, ' ') w, unnest(range(1, len(string_split(p_name, ' ')) + 1)) pos from part)",
   lambda s, d: table(s, d, "part").select("p_partkey", F.posexplode(F.split("p_name", " ")).alias("pos", "word")).withColumn("pos", C("pos").cast("long")))
_q("op_sample", None, lambda s, d: table(s, d, "orders").sample(0.1, seed=3).select("o_orderkey"))

# ---- joins ----
_CO = "select c_custkey, count(*) n from customer join orders on c_custkey = o_custkey group by 1"
_co = lambda hint: lambda s, d: table(s, d, "customer").select("c_custkey").join(table(s, d, "orders").select("o_custkey").hint(hint), C("c_custkey") == C("o_custkey")).groupBy("c_custkey").agg(F.count("*").alias("n"))
_q("join_inner", _CO, _co("shuffle_hash"))
_q("join_sort_merge", _CO, _co("merge"))
_q("join_broadcast", "select n_name, r_name from nation join region on n_regionkey = r_regionkey", lambda s, d: table(s, d, "nation").join(F.broadcast(table(s, d, "region")), C("n_regionkey") == C("r_regionkey")).select("n_name", "r_name"))
_side = lambda how: lambda s, d: table(s, d, "documents").select("doc_id").join(table(s, d, "labels").filter("quality = 1").select("doc_id", "quality"), "doc_id", how)
_q("join_left", "select d.doc_id, quality from documents d left join (select * from labels where quality = 1) l using (doc_id)", _side("left"))
_q("join_right", "select doc_id, quality from documents d right join (select * from labels where quality = 1) l using (doc_id)", _side("right"))
_q("join_full", "select coalesce(d.doc_id, l.doc_id) doc_id, source, toxic from documents d full join labels l on d.doc_id = l.doc_id",
   lambda s, d: table(s, d, "documents").select("doc_id", "source").join(table(s, d, "labels").select("doc_id", "toxic"), "doc_id", "full"))
_q("join_semi", "select doc_id from documents where doc_id in (select doc_id from labels where toxic = 1)", lambda s, d: table(s, d, "documents").join(table(s, d, "labels").filter("toxic = 1"), "doc_id", "left_semi").select("doc_id"))
_q("join_anti", "select doc_id from documents where doc_id not in (select doc_id from labels)", lambda s, d: table(s, d, "documents").join(table(s, d, "labels"), "doc_id", "left_anti").select("doc_id"))
_q("join_self", "select a.s_suppkey a, b.s_suppkey b from supplier a join supplier b on a.s_nationkey = b.s_nationkey and a.s_suppkey < b.s_suppkey",
   lambda s, d: (lambda t: t.alias("x").join(t.alias("y"), (C("x.s_nationkey") == C("y.s_nationkey")) & (C("x.s_suppkey") < C("y.s_suppkey"))).select(C("x.s_suppkey").alias("a"), C("y.s_suppkey").alias("b")))(table(s, d, "supplier")))
_q("join_theta", "select n_name, s_suppkey from nation join supplier on s_nationkey < n_nationkey and n_nationkey < 4", lambda s, d: table(s, d, "supplier").join(F.broadcast(table(s, d, "nation").filter("n_nationkey < 4")), C("s_nationkey") < C("n_nationkey")).select("n_name", "s_suppkey"))
_q("join_cross", "select n_nationkey, r_regionkey from nation cross join region", lambda s, d: table(s, d, "nation").select("n_nationkey").crossJoin(F.broadcast(table(s, d, "region").select("r_regionkey"))))
_q("join_range", "select a.event_id a, b.event_id b from events a join events b on a.user_id = b.user_id and a.event_type = 'view' and b.event_type = 'purchase' and b.ts >= a.ts and b.ts <= a.ts + interval 1 hour",
   lambda s, d: temporal.within(table(s, d, "events").filter("event_type = 'view'"), table(s, d, "events").filter("event_type = 'purchase'"), key="user_id", seconds=3600).select(C("l_event_id").alias("a"), C("r_event_id").alias("b")))
_q("join_asof", "select p.event_id, (select max(v.event_id) from events v where v.event_type = 'view' and v.user_id = p.user_id and v.ts <= p.ts and v.ts = (select max(w.ts) from events w where w.event_type = 'view' and w.user_id = p.user_id and w.ts <= p.ts)) before from events p where p.event_type = 'purchase'",
   lambda s, d: temporal.as_of(table(s, d, "events").filter("event_type = 'purchase'"), table(s, d, "events").filter("event_type = 'view'"), key="user_id", ts="ts", value="event_id").select("event_id", C("value").alias("before")))
_q("join_chain3", "select c_custkey, count(distinct p_brand) brands from customer join orders on c_custkey = o_custkey join lineitem on o_orderkey = l_orderkey join part on l_partkey = p_partkey group by 1",
   lambda s, d: table(s, d, "customer").select("c_custkey").join(table(s, d, "orders").select("o_custkey", "o_orderkey"), C("c_custkey") == C("o_custkey")).join(table(s, d, "lineitem").select("l_orderkey", "l_partkey"), C("o_orderkey") == C("l_orderkey")).join(table(s, d, "part").select("p_partkey", "p_brand"), C("l_partkey") == C("p_partkey")).groupBy("c_custkey").agg(F.countDistinct("p_brand").alias("brands")))
_q("join_salted", "select s_nationkey, count(*) n from lineitem join supplier on l_suppkey = s_suppkey group by 1",
   lambda s, d: skew.salted_join(table(s, d, "lineitem").select("l_suppkey"), table(s, d, "supplier").select("s_suppkey", "s_nationkey"), "l_suppkey", "s_suppkey", salts=8).groupBy("s_nationkey").agg(F.count("*").alias("n")))
_q("join_null_safe", "select a.k, b.v from (select nullif(r_regionkey, 2) k from region) a join (select nullif(r_regionkey, 2) k, r_name v from region) b on a.k is not distinct from b.k",
   lambda s, d: (lambda t: t.select(C("k")).join(t.select(C("k").alias("j"), C("r_name").alias("v")), C("k").eqNullSafe(C("j"))).select("k", "v"))(table(s, d, "region").withColumn("k", F.nullif("r_regionkey", F.lit(2)))))


@query("join_lateral", "select n_nationkey, s_suppkey from nation, lateral (select s_suppkey from supplier where s_nationkey = n_nationkey order by s_acctbal desc, s_suppkey limit 2)")
def _(spark, d):
    table(spark, d, "nation").createOrReplaceTempView("nation_v")
    table(spark, d, "supplier").createOrReplaceTempView("supplier_v")
    return spark.sql("select n_nationkey, s_suppkey from nation_v, lateral (select s_suppkey from supplier_v where s_nationkey = n_nationkey order by s_acctbal desc, s_suppkey limit 2)")


# ---- aggregates ----
_q("agg_basic", "select l_returnflag, count(*) n, round(sum(l_quantity), 2) qty, round(avg(l_discount), 6) disc, min(l_extendedprice) lo, max(l_extendedprice) hi from lineitem group by 1",
   lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("qty"), F.round(F.avg("l_discount"), 6).alias("disc"), F.min("l_extendedprice").alias("lo"), F.max("l_extendedprice").alias("hi")))
_q("agg_distinct", "select l_returnflag, count(distinct l_partkey) parts, count(distinct l_suppkey) suppliers from lineitem group by 1",
   lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.countDistinct("l_suppkey").alias("suppliers")))
_q("agg_approx_distinct", None, lambda s, d: table(s, d, "lineitem").agg(F.approx_count_distinct("l_partkey").alias("approx"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("hll"), F.countDistinct("l_partkey").alias("exact")))
_q("agg_mode", "select l_suppkey, min(l_returnflag) flag from (select *, rank() over (partition by l_suppkey order by n desc) k from (select l_suppkey, l_returnflag, count(*) n from lineitem group by 1, 2)) where k = 1 group by 1",
   lambda s, d: table(s, d, "lineitem").groupBy("l_suppkey", "l_returnflag").agg(F.count("*").alias("n")).groupBy("l_suppkey").agg(F.min(F.struct((-C("n")).alias("n"), "l_returnflag")).alias("m")).select("l_suppkey", C("m.l_returnflag").alias("flag")))
_q("agg_max_by", "select o_custkey, arg_max(o_orderkey, (o_totalprice, o_orderkey)) best from orders group by 1", lambda s, d: table(s, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("best")))
_q("agg_collect", "select n_regionkey, string_agg(n_name, ',' order by n_name) as names from nation group by 1", lambda s, d: table(s, d, "nation").groupBy("n_regionkey").agg(F.concat_ws(",", F.array_sort(F.collect_set("n_name"))).alias("names")))


@query("agg_listagg", "select s_nationkey, string_agg(cast(s_suppkey as varchar), '>' order by s_suppkey) keys from supplier group by 1")
def _(spark, d):
    table(spark, d, "supplier").createOrReplaceTempView("supplier_v")
    return spark.sql("select s_nationkey, listagg(cast(s_suppkey as string), '>') within group (order by s_suppkey) as keys from supplier_v group by s_nationkey")


_GROUPED = "select o_orderstatus, o_orderpriority, count(*) n from orders group by {}"
_grouped = lambda f: lambda s, d: f(table(s, d, "orders")).agg(F.count("*").alias("n"))
_q("agg_rollup", _GROUPED.format("rollup (o_orderstatus, o_orderpriority)"), _grouped(lambda t: t.rollup("o_orderstatus", "o_orderpriority")))
_q("agg_cube", _GROUPED.format("cube (o_orderstatus, o_orderpriority)"), _grouped(lambda t: t.cube("o_orderstatus", "o_orderpriority")))
_q("agg_grouping_sets", _GROUPED.format("grouping sets ((o_orderstatus), (o_orderpriority))"), _grouped(lambda t: t.groupingSets([[C("o_orderstatus")], [C("o_orderpriority")]], "o_orderstatus", "o_orderpriority")))
_q("agg_filter", "select o_custkey, count(*) filter (o_orderstatus = 'F') f, round(coalesce(sum(o_totalprice) filter (o_orderstatus = 'O'), 0), 2) o from orders group by 1",
   lambda s, d: table(s, d, "orders").groupBy("o_custkey").agg(F.count_if(C("o_orderstatus") == "F").alias("f"), F.round(F.coalesce(F.sum(F.when(C("o_orderstatus") == "O", C("o_totalprice"))), F.lit(0.0)), 2).alias("o")))
_q("agg_percentile", "select l_returnflag, round(quantile_cont(l_extendedprice, 0.5), 4) med, round(quantile_cont(l_extendedprice, 0.9), 4) p90 from lineitem group by 1",
   lambda s, d: table(s, d, "lineitem").groupBy("l_returnflag").agg(F.round(F.percentile("l_extendedprice", 0.5), 4).alias("med"), F.round(F.percentile("l_extendedprice", 0.9), 4).alias("p90")))
_q("agg_approx_top_k", None, lambda s, d: graph(s, d).triples.selectExpr("approx_top_k(rel, 5) as top").select(F.explode("top").alias("t")).select(C("t.item").alias("rel"), C("t.count").alias("n")))
_q("agg_stats", "select p_brand, round(stddev_samp(p_retailprice), 4) sd, round(corr(p_size, p_retailprice), 6) r from part group by 1", lambda s, d: table(s, d, "part").groupBy("p_brand").agg(F.round(F.stddev_samp("p_retailprice"), 4).alias("sd"), F.round(F.corr(C("p_size").cast("double"), "p_retailprice"), 6).alias("r")))
_q("agg_entropy", "select o_orderstatus, round(-sum(p * ln(p)), 6) h from (select o_orderstatus, n / sum(n) over (partition by o_orderstatus) p from (select o_orderstatus, o_orderpriority, count(*) n from orders group by 1, 2)) group by 1",
   lambda s, d: table(s, d, "orders").groupBy("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n")).withColumn("p", C("n") / F.sum("n").over(Window.partitionBy("o_orderstatus"))).groupBy("o_orderstatus").agg(F.round(-F.sum(C("p") * F.log("p")), 6).alias("h")))
_q("agg_having", "select l_partkey, count(*) n from lineitem group by 1 having count(*) > 40", lambda s, d: table(s, d, "lineitem").groupBy("l_partkey").agg(F.count("*").alias("n")).filter("n > 40"))
_q("agg_bool", "select o_custkey, bool_or(o_orderstatus = 'P') any_p, bool_and(o_totalprice > 1000) all_big from orders group by 1", lambda s, d: table(s, d, "orders").groupBy("o_custkey").agg(F.bool_or(C("o_orderstatus") == "P").alias("any_p"), F.every(C("o_totalprice") > 1000).alias("all_big")))

# ---- windows, sorts, sets ----
_w = lambda p, *o: Window.partitionBy(p).orderBy(*o)
_SW = "over (partition by s_nationkey order by s_acctbal, s_suppkey)"
_sup = lambda f: lambda s, d: f(table(s, d, "supplier"), _w("s_nationkey", "s_acctbal", "s_suppkey"))
_q("win_ranking", f"select s_suppkey, row_number() {_SW} rn, rank() {_SW} rk, dense_rank() {_SW} dr from supplier", _sup(lambda t, w: t.select("s_suppkey", F.row_number().over(w).cast("long").alias("rn"), F.rank().over(w).cast("long").alias("rk"), F.dense_rank().over(w).cast("long").alias("dr"))))
_q("win_distribution", f"select s_suppkey, ntile(3) {_SW} nt, round(percent_rank() {_SW}, 6) pr, round(cume_dist() {_SW}, 6) cd from supplier", _sup(lambda t, w: t.select("s_suppkey", F.ntile(3).over(w).cast("long").alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))))
_q("win_lag_lead", f"select s_suppkey, lag(s_suppkey) {_SW} before, lead(s_suppkey) {_SW} after, first_value(s_suppkey) {_SW} lowest from supplier", _sup(lambda t, w: t.select("s_suppkey", F.lag("s_suppkey").over(w).alias("before"), F.lead("s_suppkey").over(w).alias("after"), F.first("s_suppkey").over(w).alias("lowest"))))
_q("win_running", f"select s_suppkey, round(sum(s_acctbal) over (partition by s_nationkey order by s_acctbal, s_suppkey rows unbounded preceding), 2) total from supplier", _sup(lambda t, w: t.select("s_suppkey", F.round(F.sum("s_acctbal").over(w.rowsBetween(Window.unboundedPreceding, 0)), 2).alias("total"))))
_q("win_rows_frame", "select s_suppkey, round(avg(s_acctbal) over (partition by s_nationkey order by s_acctbal, s_suppkey rows between 1 preceding and 1 following), 4) around from supplier", _sup(lambda t, w: t.select("s_suppkey", F.round(F.avg("s_acctbal").over(w.rowsBetween(-1, 1)), 4).alias("around"))))
_q("win_range_frame", "select event_id, count(*) over (partition by user_id order by epoch(date_trunc('second', ts)) range between 86400 preceding and current row) n from events",
   lambda s, d: table(s, d, "events").select("event_id", F.count("*").over(Window.partitionBy("user_id").orderBy(C("ts").cast("timestamp").cast("long")).rangeBetween(-86400, 0)).alias("n")))
_q("win_share", "select s_suppkey, round(s_acctbal / sum(s_acctbal) over (partition by s_nationkey), 6) share from supplier", lambda s, d: table(s, d, "supplier").select("s_suppkey", F.round(C("s_acctbal") / F.sum("s_acctbal").over(Window.partitionBy("s_nationkey")), 6).alias("share")))
_q("sort_global", "select c_custkey, c_acctbal from customer order by c_acctbal desc, c_custkey", lambda s, d: table(s, d, "customer").select("c_custkey", "c_acctbal").orderBy(F.desc("c_acctbal"), "c_custkey"))
_q("limit_offset", "select c_custkey from customer order by c_acctbal, c_custkey limit 10 offset 5", lambda s, d: table(s, d, "customer").orderBy("c_acctbal", "c_custkey").offset(5).limit(10).select("c_custkey"))
_q("topk_per_group", "select o_custkey, o_orderkey from (select *, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey) k from orders) where k <= 3",
   lambda s, d: table(s, d, "orders").withColumn("k", F.row_number().over(_w("o_custkey", F.desc("o_totalprice"), "o_orderkey"))).filter("k <= 3").select("o_custkey", "o_orderkey"))
_q("topk_global", "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 20", lambda s, d: table(s, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20))
_A, _B = "select o_custkey k from orders where o_orderstatus = 'F'", "select o_custkey k from orders where o_orderstatus = 'O'"
_ab = lambda f: lambda s, d: f(*[table(s, d, "orders").filter(C("o_orderstatus") == x).select(C("o_custkey").alias("k")) for x in "FO"])
_q("set_union_all", f"{_A} union all {_B}", _ab(lambda a, b: a.unionByName(b)))
_q("set_union", f"{_A} union {_B}", _ab(lambda a, b: a.union(b).distinct()))
_q("set_intersect", f"{_A} intersect {_B}", _ab(lambda a, b: a.intersect(b)))
_q("set_except", f"{_A} except {_B}", _ab(lambda a, b: a.subtract(b)))
_q("set_intersect_all", f"{_A} intersect all {_B}", _ab(lambda a, b: a.intersectAll(b)))
_q("set_except_all", f"{_A} except all {_B}", _ab(lambda a, b: a.exceptAll(b)))

# ---- functions ----
_q("fn_string", "select c_custkey, lower(c_name) lo, trim('  ' || c_mktsegment || ' ') as tr, substring(c_name, 1, 8) as sub, length(c_name) as len, replace(c_name, '#', '-') as rep, concat_ws('/', c_mktsegment, c_name) cat from customer",
   lambda s, d: table(s, d, "customer").select("c_custkey", F.lower("c_name").alias("lo"), F.trim(F.concat(F.lit("  "), "c_mktsegment", F.lit(" "))).alias("tr"), F.substring("c_name", 1, 8).alias("sub"), F.length("c_name").cast("long").alias("len"), F.replace("c_name", F.lit("#"), F.lit("-")).alias("rep"), F.concat_ws("/", "c_mktsegment", "c_name").alias("cat")))
_q("fn_regexp", "select page_id, regexp_extract(url, '^(https?)://([^/]+)', 2) host, regexp_replace(url, '[0-9]+', 'N', 'g') shape from pages",
   lambda s, d: table(s, d, "pages").select("page_id", F.regexp_extract("url", "^(https?)://([^/]+)", 2).alias("host"), F.regexp_replace("url", "[0-9]+", "N").alias("shape")))
_q("fn_levenshtein", "select p_partkey, cast(levenshtein(p_name, 'red bolt') as integer) d from part", lambda s, d: table(s, d, "part").select("p_partkey", F.levenshtein("p_name", F.lit("red bolt")).alias("d")))
_q("fn_date", "select o_orderkey, cast(year(o_orderdate) as integer) y, cast(month(o_orderdate) as integer) m, cast(date_diff('day', date '1995-01-01', cast(o_orderdate as date)) as integer) n_days, strftime(o_orderdate + interval 40 day, '%Y-%m-%d') later, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') as mon from orders",
   lambda s, d: table(s, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).alias("n_days"), F.date_format(C("o_orderdate") + F.expr("interval 40 days"), "yyyy-MM-dd").alias("later"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("mon")))
_q("fn_math", "select p_partkey, round(ln(p_retailprice), 6) l, round(sqrt(p_size), 6) r, round(exp(p_size / 50.0), 6) e, power(p_size, 2) p, greatest(p_size, 25) g, p_partkey % 7 as md from part",
   lambda s, d: table(s, d, "part").select("p_partkey", F.round(F.log("p_retailprice"), 6).alias("l"), F.round(F.sqrt("p_size"), 6).alias("r"), F.round(F.exp(C("p_size") / 50.0), 6).alias("e"), F.pow("p_size", F.lit(2)).alias("p"), F.greatest("p_size", F.lit(25)).alias("g"), F.pmod("p_partkey", F.lit(7)).alias("md")))
_q("fn_array_basic", "select p_partkey, len(w) n, w[1] head, list_contains(w, 'ring') ring, array_to_string(list_sort(list_distinct(w || ['a', 'a'])), ',') srt from (select p_partkey, string_split(p_name, ' ') w from part)",
   lambda s, d: table(s, d, "part").select("p_partkey", F.split("p_name", " ").alias("w")).select("p_partkey", F.size("w").cast("long").alias("n"), F.element_at("w", 1).alias("head"), F.array_contains("w", "ring").alias("ring"), F.concat_ws(",", F.sort_array(F.array_distinct(F.concat("w", F.array(F.lit("a"), F.lit("a")))))).alias("srt")))
_q("fn_array_hof", "select p_partkey, array_to_string([upper(x) for x in w], ' ') up, array_to_string([x for x in w if length(x) > 4], ',') long_, cast(list_sum([length(x) for x in w]) as integer) total from (select p_partkey, string_split(p_name, ' ') w from part)",
   lambda s, d: table(s, d, "part").select("p_partkey", F.split("p_name", " ").alias("w")).select("p_partkey", F.concat_ws(" ", F.transform("w", F.upper)).alias("up"), F.concat_ws(",", F.filter("w", lambda x: F.length(x) > 4)).alias("long_"), F.aggregate("w", F.lit(0), lambda a, x: a + F.length(x)).alias("total")))
_q("fn_map", "select p_partkey, p_brand || '=' || p_size || ';' || p_type || '=1' m, p_size sz from part",
   lambda s, d: table(s, d, "part").select("p_partkey", F.create_map("p_brand", C("p_size"), "p_type", F.lit(1)).alias("m"), "p_brand").select("p_partkey", F.concat_ws(";", F.transform(F.map_entries("m"), lambda e: F.concat(e["key"], F.lit("="), e["value"].cast("string")))).alias("m"), C("m")[C("p_brand")].alias("sz")))
_q("fn_json", "select event_id, cast(props->>'$.k' as integer) k from events", lambda s, d: table(s, d, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k")))
_q("fn_struct", "select s_suppkey, s_name as name, s_nationkey nat from supplier", lambda s, d: table(s, d, "supplier").select("s_suppkey", F.struct(C("s_name").alias("name"), C("s_nationkey").alias("nat")).alias("st")).select("s_suppkey", "st.*"))
_q("fn_hash", "select c_custkey, md5(c_name) m, sha256(c_name) s from customer", lambda s, d: table(s, d, "customer").select("c_custkey", F.md5("c_name").alias("m"), F.sha2("c_name", 256).alias("s")))
_q("fn_cosine", "select a.vec_id a, b.vec_id b, round(list_cosine_similarity(a.embedding::double[], b.embedding::double[]), 6) c from embeddings a join embeddings b on a.vec_id + 1 = b.vec_id",
   lambda s, d: (lambda t: t.select(C("vec_id").alias("a"), C("embedding").alias("x"), (C("vec_id") + 1).alias("b")).join(t.select(C("vec_id").alias("b"), C("embedding").alias("y")), "b").select("a", "b", F.round(vector.cosine(C("x"), C("y")), 6).alias("c")))(table(s, d, "embeddings")))
_q("fn_cast", "select p_partkey, try_cast(p_name as integer) bad, cast(p_size as varchar) txt, try_cast(right(p_brand, 1) as integer) num from part",
   lambda s, d: table(s, d, "part").select("p_partkey", C("p_name").try_cast("int").alias("bad"), C("p_size").cast("string").alias("txt"), F.right("p_brand", F.lit(1)).try_cast("int").alias("num")))

# ---- batch twins of the stream operators ----
_ev = lambda s, d: table(s, d, "events")
_q("stream_tumbling", "select strftime(time_bucket(interval 1 day, ts), '%Y-%m-%d %H:%M:%S') start, event_type, count(*) n from events group by 1, 2",
   lambda s, d: stream.counts(_ev(s, d), "1 day").select(F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "event_type", "n"))
_q("stream_sliding", "select strftime(b - o * interval 12 hour, '%Y-%m-%d %H:%M:%S') start, event_type, count(*) n from (select time_bucket(interval 12 hour, ts) b, event_type, unnest([0, 1]) o from events) group by 1, 2",
   lambda s, d: stream.counts(_ev(s, d), "1 day", "12 hours").select(F.date_format("window.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "event_type", "n"))
_q("stream_session", "select user_id, min(ts) start, count(*) n from (select *, sum(case when ts >= before + interval 6 hour or before is null then 1 else 0 end) over (partition by user_id order by ts, event_id) g from (select *, lag(ts) over (partition by user_id order by ts, event_id) before from events)) group by user_id, g",
   lambda s, d: stream.sessions(_ev(s, d), "6 hours").select("user_id", C("session_window.start").alias("start"), "n"))
_q("stream_dedup", "select distinct head, rel, tail from (select cast(user_id as varchar) head, 'did' rel, event_type tail from events)", lambda s, d: stream.as_triples(_ev(s, d)).dropDuplicates(["head", "rel", "tail"]).select("head", "rel", "tail"))
_q("stream_interval_join", "select v.event_id v, p.event_id p from events v join events p on v.user_id = p.user_id and v.event_type = 'view' and p.event_type = 'purchase' and p.ts between v.ts and v.ts + interval 2 hour",
   lambda s, d: stream.view_to_purchase(_ev(s, d).filter("event_type = 'view'"), _ev(s, d).filter("event_type = 'purchase'"), "2 hours").select("v", "p"))
