"""Queries on Spark's extension points and on sketches that merge (U rows, AG3)."""

from __future__ import annotations

from pyspark.sql import functions as F

from kgtrail.functions import external
from kgtrail.registry import query
from kgtrail.sources import star
from kgtrail.sources.star import table


@query("udf_path_f1", "select p_partkey, round(case when p_size / 50.0 + p_partkey % 7 / 7.0 = 0 then 0 else 2 * (p_size / 50.0) * (p_partkey % 7 / 7.0) / (p_size / 50.0 + p_partkey % 7 / 7.0) end, 6) f1 from part")
def _(spark, d):
    external.register_path_f1(spark)
    return table(spark, d, "part").selectExpr("p_partkey", "round(path_f1(p_size / 50.0d, p_partkey % 7 / 7.0d), 6) as f1")


@query("udf_path_support", "select p_brand, round(1 - product(1 - p_size / 500.0), 6) support from part group by 1")
def _(spark, d):
    return table(spark, d, "part").groupBy("p_brand").agg(F.round(external.path_support(F.col("p_size") / 500.0), 6).alias("support"))


@query("udf_grouped_verdict", "select cast(o_custkey as bigint) qid, count(*) n, arg_max('order:' || o_orderkey, (o_totalprice, o_orderkey)) best from orders group by 1")
def _(spark, d):
    rows = table(spark, d, "orders").select(F.col("o_custkey").cast("long").alias("qid"), "o_orderkey", "o_totalprice")
    best = lambda x: {"n": len(x), "best": "order:" + str(x.sort_values(["o_totalprice", "o_orderkey"])["o_orderkey"].iloc[-1])}
    return external.verdicts(rows, best, "qid long, n long, best string")


@query("udtf_expand_paths", """with e as (select 'nation:' || n_nationkey head, 'nation.region' rel, 'region:' || n_regionkey tail from nation union all select 'region:' || n_regionkey, 'region.nations', 'nation:' || n_nationkey from nation)
select 'nation:' || n_nationkey topic, 1 len, tail, 'nation:' || n_nationkey || '|' || rel || '|' || tail path_key from nation join e on head = 'nation:' || n_nationkey
union all select 'nation:' || n_nationkey, 2, b.tail, 'nation:' || n_nationkey || '|' || a.rel || '|' || a.tail || '|' || b.rel || '|' || b.tail from nation join e a on a.head = 'nation:' || n_nationkey join e b on b.head = a.tail""")  # fmt: skip
def _(spark, d):
    external.register_expand_paths(spark, star.triples(spark, d).filter(F.col("rel").isin("nation.region", "region.nations")))
    table(spark, d, "nation").select(F.concat(F.lit("nation:"), F.col("n_nationkey").cast("string")).alias("topic")).createOrReplaceTempView("topics_to_expand")
    return spark.sql("select topic, len, tail, path_key from topics_to_expand, lateral expand_paths(topic, 2)")


@query("udf_replies", "select cast(c_custkey as bigint) qid, upper(c_name) reply from customer")
def _(spark, d):
    prompts = table(spark, d, "customer").select(F.col("c_custkey").cast("long").alias("qid"), F.col("c_name").alias("prompt"))
    return external.replies(prompts, lambda: lambda texts: [t.upper() for t in texts])


@query("udf_encoder", "select s_suppkey, cast(length(s_name) as double) x, cast(length(replace(s_name, '0', '')) as double) y from supplier")
def _(spark, d):
    encode = external.encoder(lambda: lambda texts: [[len(t), len(t.replace("0", ""))] for t in texts])
    return table(spark, d, "supplier").select("s_suppkey", encode("s_name").alias("v")).select("s_suppkey", F.col("v")[0].alias("x"), F.col("v")[1].alias("y"))


@query("agg_sketch_merge", "select count(distinct o_custkey) exact, true as close_enough from orders")
def _(spark, d):
    """Sketches of each priority merged: their estimate is within a twentieth of the exact count."""
    orders = table(spark, d, "orders")
    each = orders.groupBy("o_orderpriority").agg(F.hll_sketch_agg("o_custkey", F.lit(14)).alias("sketch"))
    whole = each.agg(F.hll_sketch_estimate(F.hll_union_agg("sketch")).alias("n"))
    return orders.agg(F.countDistinct("o_custkey").alias("exact")).crossJoin(F.broadcast(whole)).select("exact", (F.abs(F.col("n") - F.col("exact")) <= 0.05 * F.col("exact")).alias("close_enough"))
