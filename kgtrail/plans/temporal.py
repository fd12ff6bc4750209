"""Joins along time: within an interval, and as of a moment."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def within(left: DataFrame, right: DataFrame, *, key: str, seconds: int, ts: str = "ts") -> DataFrame:
    """Pairs with equal key and l.ts <= r.ts <= l.ts + seconds; columns get the prefixes l_ and r_.
    Time is cut into buckets of that width: a row of the left side looks into its own bucket and
    the next, so the join is on equality and hot keys are split by time."""
    bucket = lambda c: F.floor(F.unix_micros(c.cast("timestamp")) / (seconds * 1_000_000))
    a = left.select([F.col(c).alias(f"l_{c}") for c in left.columns]).withColumn("_b", F.explode(F.array(bucket(F.col(f"l_{ts}")), bucket(F.col(f"l_{ts}")) + 1)))
    b = right.select([F.col(c).alias(f"r_{c}") for c in right.columns]).withColumn("_b", bucket(F.col(f"r_{ts}")))
    met = a.join(b, (F.col(f"l_{key}") == F.col(f"r_{key}")) & (a["_b"] == b["_b"]))
    gap = F.unix_micros(F.col(f"r_{ts}").cast("timestamp")) - F.unix_micros(F.col(f"l_{ts}").cast("timestamp"))
    return met.filter((gap >= 0) & (gap <= seconds * 1_000_000)).drop("_b")


def as_of(left: DataFrame, right: DataFrame, *, key: str, ts: str, value: str) -> DataFrame:
    """left with `value` of the latest right row of the same key at or before its time (the greatest
    value if several share that time). One union and one window: no range join."""
    latest = right.groupBy(key, ts).agg(F.max(value).alias("value"))
    a = left.withColumn("_side", F.lit(1)).withColumn("value", F.lit(None).cast(latest.schema["value"].dataType))
    b = latest.withColumn("_side", F.lit(0))
    both = a.unionByName(b, allowMissingColumns=True)
    w = Window.partitionBy(key).orderBy(ts, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return both.withColumn("value", F.last("value", ignorenulls=True).over(w)).filter("_side = 1").drop("_side")
