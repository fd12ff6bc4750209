"""Joins for hot keys."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def salted_join(big: DataFrame, small: DataFrame, left: str, right: str, *, salts: int, how: str = "inner") -> DataFrame:
    """big joined with small on left = right, with the rows of each key spread over `salts` tasks:
    big gets a salt from its row, small is repeated once for each salt. For inner and left joins;
    AQE splits hot partitions by itself where the plan lets it, this works everywhere."""
    if how not in ("inner", "left", "left_semi"):
        raise ValueError("small is repeated, so only inner, left and left_semi keep their meaning")
    a = big.withColumn("_salt", F.pmod(F.xxhash64(*big.columns, F.monotonically_increasing_id()), F.lit(salts)).cast("int"))
    b = small.withColumn("_s", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, (F.col(left) == F.col(right)) & (F.col("_salt") == F.col("_s")), how).drop("_salt", "_s")
