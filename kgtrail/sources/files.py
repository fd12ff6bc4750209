"""Readers and writers besides plain Parquet tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TRIPLES = "head string, rel string, tail string"
QUESTIONS = "qid long, text string, topic string, hops int, category string, answers array<string>"
#: <subject> <predicate> <object-or-literal> .
_LINE = r'^\s*<([^>]*)>\s+<([^>]*)>\s+(?:<([^>]*)>|"((?:[^"\\]|\\.)*)"(?:@[A-Za-z-]+|\^\^<[^>]*>)?)\s*\.\s*$'


def read_ntriples(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame]:
    """(triples, quarantined lines) of an N-Triples file; blank lines and comments are neither."""
    lines = spark.read.text(path).filter(~F.col("value").rlike(r"^\s*(#.*)?$"))
    get = lambda k: F.regexp_extract("value", _LINE, k)
    good = lines.filter(F.col("value").rlike(_LINE)).select(get(1).alias("head"), get(2).alias("rel"), F.when(get(3) != "", get(3)).otherwise(get(4)).alias("tail"))
    return good.distinct(), lines.filter(~F.col("value").rlike(_LINE)).select(F.col("value").alias("line"))


def read_delimited(spark: SparkSession, path: str, sep: str = "|") -> DataFrame:
    return spark.read.csv(path, sep=sep, schema=TRIPLES).filter("head is not null and rel is not null and tail is not null").distinct()


def read_questions_json(spark: SparkSession, path: str) -> DataFrame:
    """JSON lines with nested gold; malformed lines become rows of nulls and are left out."""
    return spark.read.json(path, schema=QUESTIONS, mode="PERMISSIVE").filter("qid is not null")


def write_triple_store(kg: DataFrame, name: str, buckets: int) -> None:
    """A table partitioned by relation, bucketed and sorted by head: a hop then shuffles only the
    frontier and reads only the relations it may take."""
    kg.write.partitionBy("rel").bucketBy(buckets, "head").sortBy("head").saveAsTable(name)


def write_signatures(sigs: DataFrame, path: str) -> None:
    sigs.write.partitionBy("tail_type").parquet(path)


def write_columnar(df: DataFrame, path: str, kind: str = "parquet", *partition_by: str) -> None:
    """df as Parquet or ORC files, split by the given columns."""
    if kind not in ("parquet", "orc"):
        raise ValueError(f"kind is parquet or orc, not {kind}")
    df.write.partitionBy(*partition_by).format(kind).save(path)


def export_paths(paths: DataFrame, path: str, kind: str = "csv") -> None:
    flat = paths.select("qid", "len", F.concat_ws(">", "rels").alias("rels"), F.concat_ws("|", "nodes").alias("nodes"), "tail", "path_key")
    (flat.write.option("header", True).csv if kind == "csv" else flat.write.json)(path)
