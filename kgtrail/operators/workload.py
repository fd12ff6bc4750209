"""Question templates over the star graph, their gold answers, and sampling (W-01 to W-19, P-10)."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kgtrail.sources.shared import stored
from kgtrail.sources.star import table

CONSTRAINTS = "array<struct<target:string,rel:string,op:string,value:string>>"
SCALE = 1_000_000_000


@dataclass(frozen=True)
class Template:
    no: int
    name: str
    topic: str
    hops: int
    chain: tuple[str, ...]
    answer: str
    category: str
    texts: tuple[str, str, str]
    constraints: tuple[tuple[str, str, str, str], ...] = ()


def _t(no, name, topic, chain, answer, category, texts, constraints=()):
    return Template(no, name, topic, len(chain), tuple(chain), answer, category, texts, tuple(constraints))


TEMPLATES = [
    _t(1, "w_customer_nation", "customer", ["customer.nation"], "nation", "simple", ("which nation is {} from", "country of {}", "{} lives in what nation")),
    _t(2, "w_part_brand", "part", ["part.brand"], "brand", "simple", ("which brand is {}", "brand of {}", "who makes {} by brand")),
    _t(3, "w_customer_orders", "customer", ["customer.orders"], "order", "simple", ("which orders did {} place", "orders of {}", "list every order by {}")),
    _t(4, "w_customer_region", "customer", ["customer.nation", "nation.region"], "region", "simple", ("which region is the nation of {} in", "region of {}", "{} lives in what region")),
    _t(5, "w_customer_parts", "customer", ["customer.orders", "order.parts"], "part", "simple", ("which parts are in orders of {}", "parts bought by {}", "what parts did {} order")),
    _t(6, "w_part_supplier_nations", "part", ["part.suppliers", "supplier.nation"], "nation", "simple", ("which nation are suppliers of {} from", "nations of suppliers of {}", "{} comes from suppliers in what nation")),
    _t(7, "w_segment_peers", "customer", ["customer.segment", "segment.customers"], "customer", "simple", ("which customers share the segment of {}", "customers in the segment of {}", "peers of {} by segment")),
    _t(8, "w_customer_brands", "customer", ["customer.orders", "order.parts", "part.brand"], "brand", "simple", ("which brand do parts in orders of {} have", "brands bought by {}", "what brand of parts did {} order")),
    _t(9, "w_customer_supplier_nations", "customer", ["customer.orders", "order.suppliers", "supplier.nation"], "nation", "simple", ("which nation are suppliers in orders of {} from", "supplier nations of orders by {}", "nations of suppliers serving {}")),
    _t(10, "w_home_parts", "customer", ["customer.nation", "nation.suppliers", "supplier.parts"], "part", "simple", ("which parts do suppliers in the nation of {} sell", "parts of home suppliers of {}", "parts sold by suppliers from the nation of {}")),
    _t(11, "w_customer_supplier_regions", "customer", ["customer.orders", "order.suppliers", "supplier.nation", "nation.region"], "region", "simple", ("which region are suppliers in orders of {} from", "supplier regions of orders by {}", "regions of suppliers serving {}")),
    _t(12, "w_nation_categories", "nation", ["nation.customers", "customer.orders", "order.parts", "part.category"], "category", "simple", ("which category of parts do customers of {} order", "part categories ordered from {}", "categories bought in {}")),
    _t(13, "w_parts_in_year", "customer", ["customer.orders", "order.parts"], "part", "temporal", ("which parts did {} order in 1997", "parts bought by {} in 1997", "what parts did {} order during 1997"), [("node1", "order.year", "=", "1997")]),
    _t(14, "w_parts_over_size", "customer", ["customer.orders", "order.parts"], "part", "attribute", ("which parts over size 40 did {} order", "parts bigger than 40 bought by {}", "what parts of size above 40 did {} order"), [("answer", "part.size", ">", "40")]),
    _t(15, "w_suppliers_in_nation", "part", ["part.suppliers"], "supplier", "constrained", ("which suppliers of {} are in asia", "asian suppliers of {}", "suppliers from asia selling {}"), [("answer", "supplier.region", "=", "ASIA")]),
    _t(16, "w_urgent_brands", "customer", ["customer.orders", "order.parts", "part.brand"], "brand", "constrained", ("which brand of parts are in urgent orders of {}", "brands bought urgently by {}", "what brand did {} order with urgent priority"), [("node1", "order.priority", "=", "1-URGENT")]),
    _t(17, "w_latest_order", "customer", ["customer.orders"], "order", "temporal", ("which order of {} is the latest", "latest order of {}", "last order by {}")),
]
BY_NAME = {t.name: t for t in TEMPLATES}
KEYS = {"customer": ("customer", "c_custkey"), "part": ("part", "p_partkey"), "nation": ("nation", "n_nationkey")}


def questions(spark: SparkSession, sf_dir: str, names: list[str], *, step: int = 1) -> DataFrame:
    """One row per (template, topic): topics whose key is divisible by step, and all nations."""
    out = None
    for t in (BY_NAME[n] for n in names):
        name, key = KEYS[t.topic]
        m = 1 if t.topic == "nation" else step
        k = F.col(key).cast("long")
        topic = F.concat(F.lit(t.topic + ":"), k.cast("string"))
        spoken = F.concat(F.lit(t.topic + " "), k.cast("string"))
        text = F.when(k % 3 == 0, F.replace(F.lit(t.texts[0]), F.lit("{}"), spoken)).when(k % 3 == 1, F.replace(F.lit(t.texts[1]), F.lit("{}"), spoken)).otherwise(F.replace(F.lit(t.texts[2]), F.lit("{}"), spoken))
        held = F.array(*[F.struct(*[F.lit(v).alias(n) for v, n in zip(c, ("target", "rel", "op", "value"), strict=True)]) for c in t.constraints]).cast(CONSTRAINTS)
        topics = table(spark, sf_dir, name)
        rows = (topics if m == 1 else topics.filter(F.pmod(k, F.lit(m)) == 0)).select(
            (F.lit(t.no * SCALE).cast("long") + k).alias("qid"), text.alias("text"), topic.alias("topic"), F.lit(t.hops).alias("hops"), F.lit(t.category).alias("category"), F.lit(t.name).alias("template"),
            F.when(k % 10 < 8, "train").when(k % 10 == 8, "dev").otherwise("test").alias("split"), F.lit(t.answer).alias("etype"), held.alias("constraints"),
        )
        out = rows if out is None else out.unionByName(rows)
    return out


#: Templates whose answers come by the lines of a customer's orders.
BOUGHT = {"w_customer_parts", "w_customer_brands", "w_customer_supplier_nations", "w_customer_supplier_regions", "w_parts_in_year", "w_parts_over_size", "w_urgent_brands"}


def gold(spark: SparkSession, sf_dir: str, q: DataFrame, *, few: bool = False) -> DataFrame:
    """qid, answer from the raw tables, never from the derived graph: one join chain per template. few: what
    the customers of q bought is read once for all templates and written, orders first, so that its size is
    known; for questions about a small part of the customers."""
    T = lambda n: table(spark, sf_dir, n)
    keyed = q.select("qid", "template", F.substring_index("topic", ":", -1).cast("long").alias("k"))
    names = {r["template"] for r in q.select("template").distinct().collect()}  # at most one per template
    orders = T("orders").select("o_orderkey", "o_custkey", F.year("o_orderdate").alias("y"), "o_orderpriority", "o_orderdate")
    lines = T("lineitem").select("l_orderkey", "l_partkey", "l_suppkey")
    customer, supplier = T("customer"), T("supplier").select("s_suppkey", "s_nationkey")
    nation, part = T("nation"), T("part")
    bought = lambda x: x.join(orders, F.col("k") == F.col("o_custkey")).join(lines, F.col("o_orderkey") == F.col("l_orderkey"))
    if few and names & BOUGHT:
        asked = keyed.filter(F.col("template").isin(*BOUGHT)).select(F.col("k").alias("o_custkey")).distinct()
        mine = stored(orders.join(asked, "o_custkey", "left_semi"), "bought-orders")
        items = stored(mine.join(lines, F.col("o_orderkey") == F.col("l_orderkey")), "bought")
        bought = lambda x: x.join(items, F.col("k") == F.col("o_custkey"))
    home = lambda x: x.join(customer.select("c_custkey", "c_nationkey", "c_mktsegment"), F.col("k") == F.col("c_custkey"))
    where = lambda x: x.join(supplier, F.col("l_suppkey") == F.col("s_suppkey"))
    sold = lambda x: x.join(lines, F.col("k") == F.col("l_partkey"))
    region = lambda x, c: x.join(F.broadcast(nation.select("n_nationkey", "n_regionkey")), F.col(c) == F.col("n_nationkey"))
    ways = {
        "w_customer_nation": lambda x: (home(x), "nation", "c_nationkey"),
        "w_part_brand": lambda x: (x.join(part, F.col("k") == F.col("p_partkey")), "brand", "p_brand"),
        "w_customer_orders": lambda x: (x.join(orders, F.col("k") == F.col("o_custkey")), "order", "o_orderkey"),
        "w_customer_region": lambda x: (region(home(x), "c_nationkey"), "region", "n_regionkey"),
        "w_customer_parts": lambda x: (bought(x), "part", "l_partkey"),
        "w_part_supplier_nations": lambda x: (where(sold(x)), "nation", "s_nationkey"),
        "w_segment_peers": lambda x: (home(x).join(customer.select(F.col("c_custkey").alias("peer"), F.col("c_mktsegment").alias("g")), F.col("c_mktsegment") == F.col("g")), "customer", "peer"),
        "w_customer_brands": lambda x: (bought(x).join(part, F.col("l_partkey") == F.col("p_partkey")), "brand", "p_brand"),
        "w_customer_supplier_nations": lambda x: (where(bought(x)), "nation", "s_nationkey"),
        "w_home_parts": lambda x: (home(x).join(supplier, F.col("c_nationkey") == F.col("s_nationkey")).join(lines, F.col("s_suppkey") == F.col("l_suppkey")), "part", "l_partkey"),
        "w_customer_supplier_regions": lambda x: (region(where(bought(x)), "s_nationkey"), "region", "n_regionkey"),
        "w_nation_categories": lambda x: (x.join(customer.select("c_custkey", "c_nationkey"), F.col("k") == F.col("c_nationkey")).join(orders, F.col("c_custkey") == F.col("o_custkey")).join(lines, F.col("o_orderkey") == F.col("l_orderkey")).join(part, F.col("l_partkey") == F.col("p_partkey")), "category", "p_type"),
        "w_parts_in_year": lambda x: (bought(x).filter("y = 1997"), "part", "l_partkey"),
        "w_parts_over_size": lambda x: (bought(x).join(part, F.col("l_partkey") == F.col("p_partkey")).filter("p_size > 40"), "part", "l_partkey"),
        "w_suppliers_in_nation": lambda x: (region(where(sold(x)), "s_nationkey").join(F.broadcast(T("region")), F.col("n_regionkey") == F.col("r_regionkey")).filter("r_name = 'ASIA'"), "supplier", "l_suppkey"),
        "w_urgent_brands": lambda x: (bought(x).filter("o_orderpriority = '1-URGENT'").join(part, F.col("l_partkey") == F.col("p_partkey")), "brand", "p_brand"),
        "w_latest_order": lambda x: (x.join(orders, F.col("k") == F.col("o_custkey")).groupBy("qid").agg(F.max(F.struct("o_orderdate", "o_orderkey")).alias("m")).select("qid", F.col("m.o_orderkey").alias("latest")), "order", "latest"),
    }
    out = None
    for name in sorted(names):
        rows, kind, col = ways[name](keyed.filter(F.col("template") == name))
        rows = rows.select("qid", F.concat(F.lit(kind + ":"), F.col(col).cast("string")).alias("answer")).distinct()
        out = rows if out is None else out.unionByName(rows)
    return out


def one_shot(train: DataFrame, *, seed: int = 0) -> DataFrame:
    """One training question of each template, by a seeded hash: the same in every run."""
    order = Window.partitionBy("template").orderBy(F.md5(F.concat(F.col("qid").cast("string"), F.lit(f"#{seed}"))), "qid")
    return train.withColumn("k", F.row_number().over(order)).filter("k = 1").drop("k")


def dataset_stats(q: DataFrame) -> DataFrame:
    """template, hops, train, dev, test."""
    return q.groupBy("template", "hops").pivot("split", ["train", "dev", "test"]).agg(F.count(F.lit(1))).fillna(0)
