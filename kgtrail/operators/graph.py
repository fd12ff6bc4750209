"""Operations on triple tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def dictionary(kg: DataFrame) -> DataFrame:
    """entity, eid: a 64-bit surrogate, the same in every run. collisions() audits it."""
    ends = kg.select(F.col("head").alias("entity")).unionByName(kg.select(F.col("tail").alias("entity"))).distinct()
    return ends.select("entity", F.xxhash64("entity").alias("eid"))


def collisions(ids: DataFrame) -> DataFrame:
    return ids.groupBy("eid").agg(F.count("*").alias("n")).filter("n > 1")


def encode(kg: DataFrame) -> DataFrame:
    return kg.select(F.xxhash64("head").alias("head_id"), "rel", F.xxhash64("tail").alias("tail_id"))


def decode(ids: DataFrame, entities: DataFrame) -> DataFrame:
    heads = entities.select(F.col("eid").alias("head_id"), F.col("entity").alias("head"))
    tails = entities.select(F.col("eid").alias("tail_id"), F.col("entity").alias("tail"))
    return ids.join(heads, "head_id").join(tails, "tail_id").select("head", "rel", "tail")


def neighbourhood(topics: DataFrame, kg: DataFrame, *, depth: int) -> DataFrame:
    """The triples within `depth` hops of the topics (column topic): what a walk of that many
    steps can use. Only distinct nodes travel from hop to hop."""
    front = topics.select(F.col("topic").alias("head")).distinct()
    seen, out = front, None
    for _ in range(depth):
        hop = kg.join(front, "head", "left_semi")
        out = hop if out is None else out.unionByName(hop)
        front = hop.select(F.col("tail").alias("head")).distinct().join(seen, "head", "left_anti")
        seen = seen.unionByName(front)
    return out


def link_topics(texts: DataFrame, names: DataFrame, *, max_edit: int = 0) -> DataFrame:
    """qid, entity, edits: names (entity, name) that equal the text after normalisation, or differ
    by at most max_edit letters. For edits, both sides are blocked: within one edit, texts agree on
    their first half or on their second half (by max_edit + 1 pieces in general)."""
    norm = lambda c: F.trim(F.regexp_replace(F.lower(c), "[^a-z0-9]+", " "))
    a = texts.select("qid", norm(F.col("text")).alias("a")).filter("a <> ''")
    b = names.select("entity", norm(F.col("name")).alias("b")).filter("b <> ''")
    if max_edit == 0:
        return a.join(b, F.col("a") == F.col("b")).select("qid", "entity", F.lit(0).alias("edits")).distinct()
    pieces = max_edit + 1
    # one piece of b stands unchanged in a, moved by at most max_edit letters
    width = F.ceil(F.length("b") / pieces)
    cut_b = b.select("entity", "b", F.explode(F.transform(F.sequence(F.lit(0), F.lit(pieces - 1)), lambda k: F.struct((k * width + 1).cast("int").alias("at"), F.substr(F.col("b"), (k * width + 1).cast("int"), width.cast("int")).alias("piece")))).alias("p")).select("entity", "b", "p.*")
    cut_b = cut_b.filter("piece <> ''").select("entity", "b", "piece", F.explode(F.sequence(F.greatest(F.lit(1), F.col("at") - max_edit), F.col("at") + max_edit)).alias("at"))
    sizes = cut_b.select(F.length("piece").alias("n")).distinct()
    cut_a = a.crossJoin(F.broadcast(sizes)).filter("length(a) >= n").select("qid", "a", F.explode(F.sequence(F.lit(1), F.length("a") - F.col("n") + 1)).alias("at"), "n")
    cut_a = cut_a.select("qid", "a", "at", F.substr(F.col("a"), F.col("at"), F.col("n")).alias("piece"))
    met = cut_a.join(cut_b, ["piece", "at"]).select("qid", "a", "entity", "b").distinct()
    return met.select("qid", "entity", F.levenshtein("a", "b").alias("edits")).filter(F.col("edits") <= max_edit)
