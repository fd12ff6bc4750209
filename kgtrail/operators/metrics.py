"""Accuracy and cost measures (A-01 to A-19). Macro averages over all questions; a question without
prediction counts zero."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kgtrail.functions.text import etype_of


def per_question(q: DataFrame, pred: DataFrame, gold: DataFrame) -> DataFrame:
    """qid, hit1, precision, recall, f1, any_hit, n_pred, n_gold, n_both. pred: qid, answer, rank
    (1 is first; may be null if the order is not known)."""
    p = pred.groupBy("qid", "answer").agg(F.min("rank").alias("rank"), F.lit(1).alias("in_p"))
    g = gold.select("qid", "answer").distinct().withColumn("in_g", F.lit(1))
    both = p.join(g, ["qid", "answer"], "full")
    per = both.groupBy("qid").agg(
        F.count("in_p").alias("n_pred"), F.count("in_g").alias("n_gold"), F.count_if(F.col("in_p").isNotNull() & F.col("in_g").isNotNull()).alias("n_both"),
        F.max(F.when((F.col("rank") == 1) & F.col("in_g").isNotNull(), 1).otherwise(0)).alias("hit1"),
    )
    rows = q.select("qid").join(per, "qid", "left").fillna(0)
    precision, recall = F.when(F.col("n_pred") > 0, F.col("n_both") / F.col("n_pred")).otherwise(0.0), F.when(F.col("n_gold") > 0, F.col("n_both") / F.col("n_gold")).otherwise(0.0)
    # 2PR/(P+R) from the counts, so that it is exact to the last rounding
    f1 = F.when(F.col("n_both") > 0, 2.0 * F.col("n_both") / (F.col("n_pred") + F.col("n_gold"))).otherwise(0.0)
    return rows.select("qid", F.col("hit1").cast("double").alias("hit1"), precision.alias("precision"), recall.alias("recall"), f1.alias("f1"), (F.col("n_both") > 0).cast("double").alias("any_hit"), "n_pred", "n_gold", "n_both")


def summary(rows: DataFrame, *by: str) -> DataFrame:
    """questions, hit1, f1, precision, recall, gold_hit: macro averages, by the given columns."""
    mean = lambda c: F.round(F.avg(c), 6)
    return rows.groupBy(*by).agg(F.count("*").alias("questions"), mean("hit1").alias("hit1"), mean("f1").alias("f1"), mean("precision").alias("precision"), mean("recall").alias("recall"), mean("any_hit").alias("gold_hit"))


def micro(rows: DataFrame) -> DataFrame:
    sums = rows.agg(F.sum("n_both").alias("b"), F.sum("n_pred").alias("p"), F.sum("n_gold").alias("g"))
    return sums.select(F.round(F.col("b") / F.col("p"), 6).alias("precision"), F.round(F.col("b") / F.col("g"), 6).alias("recall"), F.round(2.0 * F.col("b") / (F.col("p") + F.col("g")), 6).alias("f1"))


def ranked(y: DataFrame, col: str = "y_ref") -> DataFrame:
    """qid, answer, rank of an array column."""
    return y.select("qid", F.posexplode(col).alias("rank", "answer")).select("qid", "answer", (F.col("rank") + 1).alias("rank"))


def n_paths(q: DataFrame, paths: DataFrame) -> DataFrame:
    per = q.select("qid").join(paths.groupBy("qid").agg(F.count("*").alias("n_paths"), F.countDistinct("tail").alias("n_answers")), "qid", "left").fillna(0)
    return per.select("qid", "n_paths", "n_answers")


def reduction(ours: DataFrame, forward: DataFrame) -> DataFrame:
    """measure, ours, forward, pct: mean paths and answers per question, and what is saved."""
    a = ours.agg(F.avg("n_paths").alias("paths"), F.avg("n_answers").alias("answers"))
    b = forward.agg(F.avg("n_paths").alias("f_paths"), F.avg("n_answers").alias("f_answers"))
    rows = a.crossJoin(b).select(F.explode(F.array(F.struct(F.lit("paths").alias("measure"), F.col("paths").alias("ours"), F.col("f_paths").alias("forward")), F.struct(F.lit("answers").alias("measure"), F.col("answers").alias("ours"), F.col("f_answers").alias("forward")))).alias("r")).select("r.*")
    return rows.select("measure", F.round("ours", 6).alias("ours"), F.round("forward", 6).alias("forward"), F.round(100 * (1 - F.col("ours") / F.col("forward")), 6).alias("pct"))


def timed(df: DataFrame) -> float:
    """Seconds to compute every row of df, without keeping any."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def plan_text(df: DataFrame, mode: str = "formatted") -> str:
    """The plan of df as explain() prints it."""
    modes = df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode
    return df._jdf.queryExecution().explainString(modes.fromString(mode))


def rounds(runs: DataFrame, limit: int = 3) -> DataFrame:
    return runs.agg(F.round(F.avg("rounds"), 6).alias("mean_rounds"), F.round(100 * (1 - F.avg("rounds") / limit), 6).alias("saved_pct"))


def gain_by_category(q: DataFrame, first: DataFrame, last: DataFrame) -> DataFrame:
    """category, f1_first, f1_last, gain in points. first, last: per_question rows."""
    rows = q.select("qid", "category").join(first.select("qid", F.col("f1").alias("a")), "qid").join(last.select("qid", F.col("f1").alias("b")), "qid")
    return rows.groupBy("category").agg(F.round(F.avg("a"), 6).alias("f1_first"), F.round(F.avg("b"), 6).alias("f1_last"), F.round(100 * (F.avg("b") - F.avg("a")), 4).alias("gain"))


def tail_types(paths: DataFrame) -> DataFrame:
    return paths.groupBy("len", etype_of(F.col("tail")).alias("etype")).agg(F.count("*").alias("n"))


def bounds(forward: DataFrame, constrained: DataFrame, kg: DataFrame) -> DataFrame:
    """hop, forward, constrained, limit, holds: constrained <= forward <= questions * b_max^hop."""
    b_max = kg.groupBy("head").agg(F.count("*").alias("d")).agg(F.max("d").alias("b_max"))
    f = forward.groupBy("hop").agg(F.sum("n_paths").alias("forward"), F.count("*").alias("questions"))
    c = constrained.groupBy("hop").agg(F.sum("n_paths").alias("constrained"))
    rows = f.join(c, "hop", "left").crossJoin(F.broadcast(b_max))
    constrained_ = F.coalesce("constrained", F.lit(0)).cast("double")
    limit = F.col("questions") * F.pow(F.col("b_max").cast("double"), F.col("hop"))
    return rows.select("hop", F.col("forward").cast("double").alias("forward"), constrained_.alias("constrained"), limit.alias("limit"), ((constrained_ <= F.col("forward")) & (F.col("forward").cast("double") <= limit)).alias("holds"))


def unreachable(gold: DataFrame, paths: DataFrame) -> DataFrame:
    """Gold answers that no path reaches; none are expected where the depth suffices."""
    return gold.join(paths.select("qid", F.col("tail").alias("answer")), ["qid", "answer"], "left_anti")
