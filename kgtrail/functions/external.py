"""Python functions behind Spark's extension points, for models that live outside the JVM (U-1 to
U-6). Nothing on the native path uses them."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Edges that a table function may hold in memory; larger graphs are searched by joins.
MOST_EDGES = 200_000


def encoder(make: Callable[[], Callable[[list[str]], np.ndarray]]):
    """A Column function text -> vector. The model is made once for each worker, not for each batch."""

    @F.pandas_udf("array<double>")
    def encode(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        model = make()
        for texts in batches:
            yield pd.Series(list(np.asarray(model(texts.fillna("").tolist()), np.float64)), dtype=object)

    return encode


def verdicts(paths: DataFrame, judge: Callable[[pd.DataFrame], dict], schema: str) -> DataFrame:
    """One row for each question from judge(its paths): schema names qid and what judge returns. A
    question has at most k paths, so a group is bounded."""

    def run(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame([{"qid": key[0]} | judge(rows)])

    return paths.groupBy("qid").applyInPandas(run, schema)


def path_support(score: Column) -> Column:
    """An aggregate: how well several paths support one answer, 1 minus the product of what each leaves open."""

    @F.pandas_udf("double")
    def support(scores: pd.Series) -> float:
        return float(1.0 - np.prod(1.0 - scores.fillna(0.0).clip(0.0, 1.0).to_numpy()))

    return support(score)


def register_expand_paths(spark: SparkSession, edges: DataFrame, name: str = "expand_paths") -> None:
    """Registers the table function name(topic, depth): all walks from a topic over a small graph, for
    interactive use. The edges are counted before they are taken to the driver."""
    rows = edges.select("head", "rel", "tail").limit(MOST_EDGES + 1).collect()
    if len(rows) > MOST_EDGES:
        raise ValueError(f"more than {MOST_EDGES} edges: search this graph by joins")
    near: dict[str, list[tuple[str, str]]] = {}
    for r in sorted(rows):
        near.setdefault(r["head"], []).append((r["rel"], r["tail"]))

    class Expand:
        def eval(self, topic: str, depth: int):
            front = [(topic, topic)]
            for i in range(1, depth + 1):
                front = [(f"{key}|{rel}|{tail}", tail) for key, v in front for rel, tail in near.get(v, ())]
                for key, v in front:
                    yield i, v, key

    spark.udtf.register(name, F.udtf(Expand, returnType="len int, tail string, path_key string"))


def replies(prompts: DataFrame, make: Callable[[], Callable[[list[str]], list[str]]]) -> DataFrame:
    """qid, reply: prompts (qid, prompt) sent to a model by Arrow batches."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = make()
        for batch in batches:
            got = model([x.as_py() or "" for x in batch.column(1)])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(got, pa.string())], ["qid", "reply"])

    return prompts.select("qid", "prompt").mapInArrow(run, "qid long, reply string")


def register_path_f1(spark: SparkSession, name: str = "path_f1") -> None:
    """A SQL function: the harmonic mean of precision and recall, 0 if both are."""
    spark.sql(f"create or replace temporary function {name}(p double, r double) returns double return case when p + r = 0 then 0.0d else 2 * p * r / (p + r) end")
