"""Answer-type supervision from shortest paths (P-01 to P-04)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kgtrail.plans import retrieve
from kgtrail.sources.shared import stored


def shortest_paths(q: DataFrame, gold: DataFrame, kg: DataFrame, *, max_len: int, ties: str = "all", sigs: DataFrame | None = None) -> DataFrame:
    """qid, answer, len, rels: relation sequences of the shortest paths from topic to each gold
    answer. A breadth-first search by levels over distinct (node, sequence); nodes seen at an
    earlier level are not entered again, as no shortest path passes them later. Each level is written
    once, as the next reads it several times. With sigs, which must cover a graph of typed edges, and
    the answers' etype in gold, a level enters only types that lead on to an answer's type."""
    if sigs is not None and "etype" in gold.columns:
        gold, out = stored(gold.select("qid", "answer", "etype").distinct(), "gold"), None
        for r in gold.select("etype").distinct().collect():  # one row for each type
            one = _typed_levels(q, gold.filter(F.col("etype").eqNullSafe(F.lit(r["etype"]))), kg, sigs, max_len)
            out = one if out is None else out.unionByName(one)
        if out is not None:
            return out.groupBy("qid", "answer", "len").agg(F.min("rels").alias("rels")) if ties == "first" else out
    front = q.select("qid", F.col("topic").alias("v"), F.array().cast("array<string>").alias("rels"))
    seen = front.select("qid", "v")
    open_ = stored(gold.select("qid", "answer").distinct(), "open")
    out = None
    for i in range(1, max_len + 1):
        live = front.join(open_.select("qid").distinct(), "qid", "left_semi")
        front = live.join(kg, live["v"] == kg["head"]).select("qid", F.col("tail").alias("v"), F.concat("rels", F.array("rel")).alias("rels")).distinct()
        front = stored(front.join(seen, ["qid", "v"], "left_anti"), "level")
        hit = front.join(open_, (front["qid"] == open_["qid"]) & (front["v"] == open_["answer"])).select(front["qid"], "answer", F.lit(i).alias("len"), "rels")
        out = hit if out is None else out.unionByName(hit)
        if i < max_len:
            open_ = stored(open_.join(hit.select("qid", "answer").distinct(), ["qid", "answer"], "left_anti"), "open")
            seen = seen.unionByName(front.select("qid", "v").distinct())
    if ties == "first":
        return out.groupBy("qid", "answer", "len").agg(F.min("rels").alias("rels"))
    return out


def _typed_levels(q: DataFrame, gold: DataFrame, kg: DataFrame, sigs: DataFrame, max_len: int) -> DataFrame:
    """shortest_paths() to answers of one type. Answers are met at the edge that enters them; only what
    is still open then goes one level further."""
    mine = q.join(gold.select("qid").distinct(), "qid", "left_semi")
    hops = retrieve.typed_hops(sigs, gold, depth=max_len, starts=retrieve.topic_types(mine))
    ends = [r["etype"] for r in gold.select("etype").distinct().collect()]
    front = stored(mine.select("qid", F.col("topic").alias("v"), F.array().cast("array<string>").alias("rels")), "level")
    topics = front.select("qid", F.col("v").alias("answer"))
    seen, out = front.select("qid", "v"), None
    open_ = stored(gold.select("qid", "answer").distinct().join(topics, ["qid", "answer"], "left_anti"), "open")
    for i in range(1, max_len + 1):
        live = front.join(open_.select("qid").distinct(), "qid", "left_semi")
        over = retrieve.along(kg, [h for h in hops[i - 1] if h[2] in ends]).select(F.col("head").alias("v"), "rel", F.col("tail").alias("answer"))
        hit = live.join(over, "v").join(open_, ["qid", "answer"]).select("qid", "answer", F.lit(i).alias("len"), F.concat("rels", F.array("rel")).alias("rels")).distinct()
        hit = stored(hit, "hit")
        out = hit if out is None else out.unionByName(hit)
        if i == max_len:
            break
        open_ = stored(open_.join(hit.select("qid", "answer").distinct(), ["qid", "answer"], "left_anti"), "open")
        if open_.isEmpty():
            break
        inner = {h for h, _, _ in set().union(*hops[i:])}
        on = retrieve.along(kg, [h for h in hops[i - 1] if h[2] in inner]).select(F.col("head").alias("v"), "rel", "tail")
        live = front.join(open_.select("qid").distinct(), "qid", "left_semi")
        front = live.join(on, "v").select("qid", F.col("tail").alias("v"), F.concat("rels", F.array("rel")).alias("rels")).distinct()
        front = stored(front.join(seen, ["qid", "v"], "left_anti"), "level")
        seen = seen.unionByName(front.select("qid", "v").distinct())
    return out


def last_relation(paths: DataFrame) -> DataFrame:
    return paths.select("qid", F.element_at("rels", -1).alias("rel")).distinct()


def valid_types(last: DataFrame, sigs: DataFrame) -> DataFrame:
    """qid, etype: tail types of the last relations."""
    s = F.broadcast(sigs.select("rel", F.col("tail_type").alias("etype")).distinct())
    return last.join(s, "rel").select("qid", "etype").distinct()


def soft_target(valid: DataFrame) -> DataFrame:
    """qid, etype, q: uniform over the valid types; absent types have weight zero."""
    return valid.withColumn("q", 1.0 / F.count("*").over(Window.partitionBy("qid")))
