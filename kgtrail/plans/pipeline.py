"""The whole procedure, question to answers (F-17), and its retrieval-only form (B-05)."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgtrail.operators import rank, refine
from kgtrail.plans import retrieve
from kgtrail.sources.shared import stored


@dataclass(frozen=True)
class Graph:
    triples: DataFrame
    entity_types: DataFrame
    signatures: DataFrame
    facts: DataFrame


def pool(q: DataFrame, pred: DataFrame, g: Graph, config: retrieve.Config, encoder=None) -> DataFrame:
    """The ranked initial pool: routed retrieval, then the k best paths of each question."""
    return rank.top_k(retrieve.route(q, pred, g.triples, g.entity_types, g.signatures, config), q, k=config.k, encoder=encoder)


def retrieval_only(ranked: DataFrame) -> DataFrame:
    """qid, answer, rank: the tails of the pool, ordered by their best path."""
    return ranked.groupBy("qid", F.col("tail").alias("answer")).agg(F.min("rank").alias("rank"))


def answer(q: DataFrame, pred: DataFrame, g: Graph, config: retrieve.Config, *, margin: float = 1.0, max_rounds: int = 3, adaptive: bool = True, encoder=None) -> DataFrame:
    """qid, y_gen, y_ref, confidence, issue, rounds. The pool is computed and written once."""
    p0 = stored(pool(q, pred, g, config, encoder), "pool")
    typed = q.drop("etype").join(pred.select("qid", "etype"), "qid", "left")
    return refine.run(typed, p0, refine.RuleGenerator(margin), refine.RuleRefiner(g.facts), max_rounds=max_rounds, adaptive=adaptive)
