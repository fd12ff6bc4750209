"""Connected components of a link table, distributed: alternating large-star and small-star steps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgtrail.llm.common import stored

#: Links from which the least neighbours are written before they are joined: then both sides of the
#: join are plain exchanges, and Spark splits the rows of a node that has very many links.
MANY = 2_000_000
#: Rounds after which an error is raised; chains of n nodes need about log n of them.
MOST_ROUNDS = 60


def _least(edges: DataFrame) -> DataFrame:
    """(u, m): the smallest node among u and its neighbours v in edges (u, v)."""
    return edges.groupBy("u").agg(F.least(F.col("u"), F.min("v")).alias("m"))


def components(links: DataFrame) -> DataFrame:
    """links: (a, b) of comparable ids. Returns (id, component) for every id that has a link to
    another one; the component is the smallest id in it.

    Every step hands on one row per edge and joins it with one row per node; a node with very many
    links is never gathered, and split where there are MANY links. Each round is written to the
    shared folder.
    Null ids and links of a node with itself are left out; repeated links count once.
    """
    edges = links.select(F.col("a").alias("x"), F.col("b").alias("y")).filter("x <> y")
    edges = stored(edges.select(F.greatest("x", "y").alias("u"), F.least("x", "y").alias("v")).distinct(), "edges")
    many = edges.count() >= MANY
    least = lambda e: stored(_least(e), "least") if many else _least(e)
    before = None
    for _ in range(MOST_ROUNDS):
        # large star: larger neighbours of u are hung on the smallest one
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = both.filter("v > u").join(least(both), "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        large = large.filter("u <> v").distinct()
        # small star: smaller neighbours of u, and u itself, are hung on the smallest one
        hung = large.join(least(large), "u")
        small = hung.select(F.explode(F.array("u", "v")).alias("u"), F.col("m").alias("v")).filter("u <> v").distinct()
        edges = stored(small, "edges")
        now = edges.agg(F.count("*").alias("n"), F.sum(F.hash("u", "v").cast("decimal(38,0)")).alias("h"), F.sum(F.hash("v", "u").cast("decimal(38,0)")).alias("g")).first()
        if before == now:
            break
        before = now
    else:
        raise RuntimeError("the components did not settle")
    nodes = edges.select(F.col("u").alias("id"), F.col("v").alias("component"))
    return nodes.unionByName(edges.select(F.col("v").alias("id"), F.col("v").alias("component")).distinct())
