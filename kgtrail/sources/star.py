"""The star schema read as a graph with declared types (K-STAR)."""

from __future__ import annotations

import uuid
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgtrail.sources.shared import shared_dir


@dataclass(frozen=True)
class Relation:
    rel: str
    domain: str
    range: str
    table: str
    head: str
    tail: str
    inverse: str | None
    repeats: bool = False


#: The catalogue: relation, head type, tail type, source table, key and value expressions, inverse.
CATALOGUE = [
    Relation("customer.nation", "customer", "nation", "customer", "c_custkey", "c_nationkey", "nation.customers"),
    Relation("supplier.nation", "supplier", "nation", "supplier", "s_suppkey", "s_nationkey", "nation.suppliers"),
    Relation("nation.region", "nation", "region", "nation", "n_nationkey", "n_regionkey", "region.nations"),
    Relation("order.customer", "order", "customer", "orders", "o_orderkey", "o_custkey", "customer.orders"),
    Relation("order.parts", "order", "part", "lineitem", "l_orderkey", "l_partkey", "part.orders", True),
    Relation("order.suppliers", "order", "supplier", "lineitem", "l_orderkey", "l_suppkey", "supplier.orders", True),
    Relation("supplier.parts", "supplier", "part", "lineitem", "l_suppkey", "l_partkey", "part.suppliers", True),
    Relation("part.brand", "part", "brand", "part", "p_partkey", "p_brand", "brand.parts"),
    Relation("part.category", "part", "category", "part", "p_partkey", "p_type", "category.parts"),
    Relation("customer.segment", "customer", "segment", "customer", "c_custkey", "c_mktsegment", "segment.customers"),
    Relation("order.priority", "order", "priority", "orders", "o_orderkey", "o_orderpriority", None),
    Relation("order.status", "order", "status", "orders", "o_orderkey", "o_orderstatus", None),
    Relation("order.year", "order", "year", "orders", "o_orderkey", "year(o_orderdate)", None),
]
#: Planted in the declared schema: one relation without range, one without domain, one
#: administrative type.
NO_RANGE, NO_DOMAIN, ADMIN = "order.status", "order.priority", "topic_admin"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def triples(spark: SparkSession, sf_dir: str, *, inverses: bool = True) -> DataFrame:
    """head, rel, tail: a set. Each relation is a branch with a constant `rel`, so a filter on rel
    drops whole branches, their scans included, before anything runs."""
    out = None
    for r in CATALOGUE:
        pairs = table(spark, sf_dir, r.table).select(F.expr(r.head).alias("h"), F.expr(r.tail).alias("t")).filter("h is not null and t is not null")
        if r.repeats:
            pairs = pairs.distinct()
        head, tail = F.concat(F.lit(r.domain + ":"), F.col("h").cast("string")), F.concat(F.lit(r.range + ":"), F.col("t").cast("string"))
        rows = pairs.select(head.alias("head"), F.lit(r.rel).alias("rel"), tail.alias("tail"))
        if inverses and r.inverse:
            rows = rows.unionByName(pairs.select(tail.alias("head"), F.lit(r.inverse).alias("rel"), head.alias("tail")))
        out = rows if out is None else out.unionByName(rows)
    return out


STORED = "head string, tail string, head_type string, tail_type string, rel string"
WRITERS = "spark.sql.maxConcurrentOutputFileWriters"
_stores: dict[tuple[str, str], str] = {}


def store(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """(triples, entity types). Triples come from a store that is laid out once per application and source:
    partitioned by relation, so that a search reads only the relations it may take, and with the types of
    both ends, so that no hop has to look them up. Entity types are a plan over it, as few queries read them."""
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _stores:
        base = f"{shared_dir(spark)}/kgtrail/star-{uuid.uuid4().hex}"
        kg = triples(spark, sf_dir).withColumns({f"{end}_type": F.substring_index(end, ":", 1) for end in ("head", "tail")})
        before = spark.conf.get(WRITERS)
        spark.conf.set(WRITERS, str(len(CATALOGUE) * 2))  # with a file open for each relation no row is sorted by relation
        try:
            kg.write.partitionBy("rel").parquet(f"{base}/triples")
        finally:
            spark.conf.set(WRITERS, before)
        _stores[key] = f"{base}/triples"
    kg = spark.read.schema(STORED).parquet(_stores[key]).select("head", "rel", "tail", "head_type", "tail_type")
    return kg, entity_types(kg)


def declared() -> list[tuple[str, str, str]]:
    """(relation, domain, range) of all relations, inverses included."""
    found = []
    for r in CATALOGUE:
        found.append((r.rel, r.domain, r.range))
        if r.inverse:
            found.append((r.inverse, r.range, r.domain))
    return found


def present(spark: SparkSession, sf_dir: str) -> DataFrame:
    """rel, head_type, tail_type of every relation that has an edge in the tables, inverses included.
    Each table is scanned once, for all its relations, and gives one row."""
    out = None
    for name in sorted({r.table for r in CATALOGUE}):
        mine = [r for r in CATALOGUE if r.table == name]
        flags = table(spark, sf_dir, name).agg(*[F.max(F.expr(r.head).isNotNull() & F.expr(r.tail).isNotNull()).alias(f"r{i}") for i, r in enumerate(mine)])
        rows = []
        for i, r in enumerate(mine):
            for rel, head, tail in [(r.rel, r.domain, r.range)] + ([(r.inverse, r.range, r.domain)] if r.inverse else []):
                rows.append(F.struct(F.lit(rel).alias("rel"), F.lit(head).alias("head_type"), F.lit(tail).alias("tail_type"), F.col(f"r{i}").alias("has")))
        one = flags.select(F.inline(F.array(*rows))).filter("has").drop("has")
        out = one if out is None else out.unionByName(one)
    return out


def schema_facts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """subject, predicate, object as a schema dump of the tables would print them: domain and range of
    the relations that occur, with the planted holes, and a note on the regions of the region table."""
    rows = present(spark, sf_dir)
    fact = lambda df, predicate, col, hole: df.filter(F.col("rel") != hole).select(F.col("rel").alias("subject"), F.lit(predicate).alias("predicate"), F.col(col).alias("object"))
    note = table(spark, sf_dir, "region").filter("r_regionkey is not null").select(F.lit("admin.note").alias("rel"), F.lit(ADMIN).alias("head_type"), F.lit("region").alias("tail_type")).distinct()
    rows = rows.unionByName(note)
    return fact(rows, "domain", "head_type", NO_DOMAIN).unionByName(fact(rows, "range", "tail_type", NO_RANGE))


def signatures(spark: SparkSession) -> DataFrame:
    """All declared signatures (the holes filled): one row per relation."""
    rows = [(d, r, t, 0, "declared") for r, d, t in declared()]
    return spark.createDataFrame(rows, "head_type string, rel string, tail_type string, support long, source string")


def entity_types(kg: DataFrame) -> DataFrame:
    ends = kg.select(F.col("head").alias("entity")).unionByName(kg.select(F.col("tail").alias("entity"))).distinct()
    return ends.select("entity", F.substring_index("entity", ":", 1).alias("etype"))


def attributes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """entity, attr, value (text): what constraints are checked against besides the graph."""
    part, orders = table(spark, sf_dir, "part"), table(spark, sf_dir, "orders")
    supplier = table(spark, sf_dir, "supplier").join(F.broadcast(table(spark, sf_dir, "nation")), F.col("s_nationkey") == F.col("n_nationkey"))
    supplier = supplier.join(F.broadcast(table(spark, sf_dir, "region")), F.col("n_regionkey") == F.col("r_regionkey"))
    named = lambda df, kind, key, attr, value: df.select(F.concat(F.lit(kind + ":"), F.col(key).cast("string")).alias("entity"), F.lit(attr).alias("attr"), F.expr(value).cast("string").alias("value"))
    rows = named(part, "part", "p_partkey", "part.size", "p_size")
    rows = rows.unionByName(named(part, "part", "p_partkey", "part.price", "p_retailprice"))
    rows = rows.unionByName(named(orders, "order", "o_orderkey", "order.year", "year(o_orderdate)"))
    rows = rows.unionByName(named(orders, "order", "o_orderkey", "order.priority", "o_orderpriority"))
    return rows.unionByName(named(supplier, "supplier", "s_suppkey", "supplier.region", "r_name"))


def subclasses(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """(instance_of, subclass_of): customer@nation under customer@region under customer, and the
    same for suppliers; every other entity is an instance of its plain type."""
    nation = table(spark, sf_dir, "nation")
    kinds, inst = None, None
    for kind, name, key, where in (("customer", "customer", "c_custkey", "c_nationkey"), ("supplier", "supplier", "s_suppkey", "s_nationkey")):
        leaf = F.concat(F.lit(f"{kind}@n"), F.col("n_nationkey").cast("string"))
        mid = F.concat(F.lit(f"{kind}@r"), F.col("n_regionkey").cast("string"))
        rows = nation.select(leaf.alias("child"), mid.alias("parent")).unionByName(nation.select(mid.alias("child"), F.lit(kind).alias("parent"))).distinct()
        kinds = rows if kinds is None else kinds.unionByName(rows)
        mine = table(spark, sf_dir, name).select(F.concat(F.lit(f"{kind}:"), F.col(key).cast("string")).alias("entity"), F.concat(F.lit(f"{kind}@n"), F.col(where).cast("string")).alias("etype"))
        inst = mine if inst is None else inst.unionByName(mine)
    return inst, kinds
