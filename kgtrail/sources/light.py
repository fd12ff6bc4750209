"""Documents, pages and events read as a graph without declared types (K-LIGHT)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from kgtrail.sources.star import table

#: Numeric ids are kept apart by an offset for each source; values stand for themselves.
PAGE, EVENT, USER = 1_000_000_000, 2_000_000_000, 3_000_000_000
#: What the training questions call the two ends of each relation.
CALLED = {
    "document.source": ("document", "source"),
    "document.lang": ("document", "language"),
    "document.quality": ("document", "grade"),
    "document.toxicity": ("document", "flag"),
    "page.host": ("page", "host"),
    "page.lang": ("page", "locale"),
    "event.actor": ("event", "actor"),
    "event.kind": ("event", "kind"),
    "event.day": ("event", "day"),
}


def _id(c: Column, offset: int = 0) -> Column:
    return (c + F.lit(offset)).cast("string")


def triples(spark: SparkSession, sf_dir: str, *, inverses: bool = False) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    pages, events = table(spark, sf_dir, "pages"), table(spark, sf_dir, "events")
    parts = {
        "document.source": docs.select(_id(F.col("doc_id")).alias("head"), F.col("source").alias("tail")),
        "document.lang": docs.select(_id(F.col("doc_id")).alias("head"), F.col("lang").alias("tail")),
        "document.quality": labels.select(_id(F.col("doc_id")).alias("head"), F.concat(F.lit("quality"), F.col("quality").cast("string")).alias("tail")),
        "document.toxicity": labels.select(_id(F.col("doc_id")).alias("head"), F.concat(F.lit("toxic"), F.col("toxic").cast("string")).alias("tail")),
        "page.host": pages.select(_id(F.col("page_id"), PAGE).alias("head"), F.regexp_extract("url", "^https?://([^/?#]+)", 1).alias("tail")),
        "page.lang": pages.select(_id(F.col("page_id"), PAGE).alias("head"), F.regexp_extract("html", 'lang="([a-z]+)"', 1).alias("tail")),
        "event.actor": events.select(_id(F.col("event_id"), EVENT).alias("head"), _id(F.col("user_id"), USER).alias("tail")),
        "event.kind": events.select(_id(F.col("event_id"), EVENT).alias("head"), F.col("event_type").alias("tail")),
        "event.day": events.select(_id(F.col("event_id"), EVENT).alias("head"), F.date_format("ts", "yyyy-MM-dd").alias("tail")),
    }
    out = None
    for rel, rows in parts.items():
        rows = rows.filter("head is not null and tail is not null and tail <> ''").distinct()
        both = rows.select("head", F.lit(rel).alias("rel"), "tail")
        if inverses:
            both = both.unionByName(rows.select(F.col("tail").alias("head"), F.lit("~" + rel).alias("rel"), F.col("head").alias("tail")))
        out = both if out is None else out.unionByName(both)
    return out


def training(kg: DataFrame) -> DataFrame:
    """topic, answer, type_path of one-hop training questions: heads whose key ends in 0 to 7."""
    names = F.create_map(*[x for rel, (a, b) in CALLED.items() for x in (F.lit(rel), F.array(F.lit(a), F.lit(b)))])
    return kg.filter(F.col("head").cast("long") % 10 < 8).select(F.col("head").alias("topic"), F.col("tail").alias("answer"), names[F.col("rel")].alias("type_path"))
