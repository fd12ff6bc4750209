"""Frontier algebra: steps along edges, prefixes, and counting without enumeration (R-02, R-03,
R-15, R-16).

A path is a row (qid, len, rels, nodes, v, path_key); v is its end, and vtype, where edges carry
`tail_type` and the search asks for it, the type of the end (null at a topic, which no edge led to).
Depth is a static loop, so a whole
search is one logical plan that Catalyst sees at once.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kgtrail.sources.shared import stored


def start(q: DataFrame) -> DataFrame:
    return q.select(
        "qid", F.lit(0).alias("len"), F.array().cast("array<string>").alias("rels"), F.array("topic").alias("nodes"), F.col("topic").alias("v"), F.col("topic").alias("path_key")
    )


def step(front: DataFrame, kg: DataFrame, *, rels: list[str] | None = None, path_mode: str = "walk", shared: bool = False) -> DataFrame:
    """One hop along the edges' own direction. rels restricts the relations (whole branches of the
    triple table then drop out); shared reads the edges of each distinct end once for all
    questions before they are joined back."""
    edges = kg if rels is None else kg.filter(F.col("rel").isin(rels))
    if shared:
        edges = edges.join(front.select(F.col("v").alias("head")).distinct(), "head", "left_semi")
    hop = front.join(edges, front["v"] == edges["head"])
    if path_mode == "simple":
        hop = hop.filter(~F.array_contains("nodes", F.col("tail")))
    elif path_mode != "walk":
        raise ValueError(f"path_mode is walk or simple, not {path_mode}")
    return hop.select(
        "qid", (F.col("len") + 1).alias("len"), F.concat("rels", F.array("rel")).alias("rels"), F.concat("nodes", F.array("tail")).alias("nodes"), F.col("tail").alias("v"), F.concat_ws("|", "path_key", "rel", "tail").alias("path_key"),
        *[F.col("tail_type").alias("vtype")] * ("vtype" in front.columns),
    )


def within_budget(front: DataFrame, budget: int | None, score: str | None = None) -> DataFrame:
    """The best `budget` rows of each question; partial group limits keep the shuffle small."""
    if budget is None:
        return front
    order = ([F.desc(score)] if score else []) + [F.col("path_key")]
    return front.withColumn("_k", F.row_number().over(Window.partitionBy("qid").orderBy(*order))).filter(F.col("_k") <= budget).drop("_k")


def prefixes(q: DataFrame, kg: DataFrame, *, depth: int, budget: int | None = None, path_mode: str = "walk", masks: list[DataFrame] | None = None, etypes: DataFrame | None = None, typed: bool = False) -> list[DataFrame]:
    """Prefixes of length 0 to depth, a frame for each length. With masks (one for each length:
    qid, etype) a prefix stays only if the type of its end is allowed. typed: prefixes keep vtype,
    if the edges carry types; then none is looked up."""
    front = start(q)
    if typed and {"head_type", "tail_type"} <= set(kg.columns):
        front = front.withColumn("vtype", F.lit(None).cast("string"))
    out = [front]
    for i in range(1, depth + 1):
        front = step(front, kg, path_mode=path_mode)
        if masks is not None and "vtype" in front.columns:
            front = front.join(masks[i].withColumnRenamed("etype", "vtype"), ["qid", "vtype"], "left_semi").select(*out[0].columns)
        elif masks is not None:
            ends = front.join(etypes, front["v"] == etypes["entity"]).drop("entity")
            front = ends.join(masks[i], ["qid", "etype"], "left_semi").select(*out[0].columns)
        front = within_budget(front, budget)
        out.append(front)
    return out


def union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def count_paths(q: DataFrame, kg: DataFrame, *, depth: int, last: DataFrame | None = None) -> DataFrame:
    """qid, hop, n_paths, n_answers for walks of exactly 1..depth hops, without listing them: only
    (qid, node, number of walks) travels. last (qid, rel) restricts the final hop. Counts are
    decimals, as they grow as a power of the depth."""
    ways = q.select("qid", F.col("topic").alias("v"), F.lit(1).cast("decimal(38,0)").alias("n"))
    out = None
    for hop in range(1, depth + 1):
        ends = ways.join(kg, ways["v"] == kg["head"])
        final = ends if last is None else ends.join(last.select("qid", "rel").distinct(), ["qid", "rel"], "left_semi")
        per = final.groupBy("qid", "tail").agg(F.sum("n").alias("n"))
        rows = per.groupBy("qid").agg(F.sum("n").cast("decimal(38,0)").alias("n_paths"), F.count("*").alias("n_answers")).withColumn("hop", F.lit(hop))
        out = rows if out is None else out.unionByName(rows)
        if hop < depth:
            ways = ends.groupBy("qid", F.col("tail").alias("v")).agg(F.sum("n").cast("decimal(38,0)").alias("n"))
    return out.select("qid", "hop", "n_paths", "n_answers")


#: Tails that backward counting keeps as bits, 64 to a row.
MOST_TAILS = 4_096


def count_back(q: DataFrame, kg: DataFrame, hops: list[list[tuple[str, str, str]]], *, last: DataFrame | None = None, answers: bool = True) -> DataFrame:
    """What count_paths gives, counted from the last hop back: the walks that start at a node are the
    same for all questions, so work grows with the edges and not with questions times nodes. hops
    holds for each hop the signatures it may take, as retrieve.typed_hops() gives them. Distinct answers are bits beside the counts, which takes `last`
    with at most MOST_TAILS tails; without answers n_answers is left out."""
    depth, kind = len(hops), F.lit("").alias("ends")
    some = lambda m: kg.filter(F.col("rel").isin(sorted({h[1] for one in hops[: m + 1] for h in one}))).select("head", "rel", "tail")
    asked = q.select("qid", F.col("topic").alias("v"), kind)
    kinds = None
    if last is not None:  # questions with the same last relations are one class
        ends = last.groupBy("qid").agg(F.array_join(F.array_sort(F.collect_set("rel")), ",").alias("ends"))
        kinds = F.broadcast(last.select("qid", "rel").distinct().join(ends, "qid").select("ends", "rel").distinct())
        asked = asked.drop("ends").join(ends, "qid")
    asked = stored(asked, "asked")
    near, now = [asked.select("v").distinct()], asked.select("v").distinct()
    for one in hops[:-1]:  # the nodes that any question can stand on after so many hops
        e = kg.filter(F.col("rel").isin(sorted({h[1] for h in one})))
        now = stored(e.join(now.withColumnRenamed("v", "head"), "head", "left_semi").select(F.col("tail").alias("v")).distinct(), "near")
        near.append(now)
    within = lambda m: union(near[: m + 1]).distinct()
    first = some(depth - 1)
    ends_in = first.withColumn("ends", F.lit("")) if kinds is None else first.join(kinds, "rel")
    blk, bit = F.lit(0).alias("blk"), F.lit(0).cast("long").alias("bit")
    if answers:
        tails = stored(ends_in.select("tail").distinct(), "tails")
        n = tails.count()
        if n > MOST_TAILS:
            raise ValueError(f"{n} tails are too many to keep as bits")
        ids = F.broadcast(tails.select("tail", (F.row_number().over(Window.orderBy("tail")) - 1).alias("id")))
        ends_in = ends_in.join(ids, "tail")
        blk, bit = F.floor(F.col("id") / 64).cast("int").alias("blk"), F.expr("shiftleft(1L, cast(id % 64 as int))").alias("bit")
    ways = ends_in.join(within(depth - 1).withColumnRenamed("v", "head"), "head", "left_semi").select("ends", "head", blk, F.lit(1).cast("decimal(38,0)").alias("n"), bit)
    out = None
    for hop in range(1, depth + 1):
        if hop > 1:
            on = some(depth - hop).join(within(depth - hop).withColumnRenamed("v", "head"), "head", "left_semi")
            ways = on.join(back.withColumnRenamed("v", "tail"), "tail").select("ends", "head", "blk", "n", "bit")
        back = stored(ways.groupBy("ends", F.col("head").alias("v"), "blk").agg(F.sum("n").cast("decimal(38,0)").alias("n"), F.bit_or("bit").alias("bit")), "back")
        rows = asked.join(back, ["ends", "v"]).groupBy("qid").agg(F.sum("n").cast("decimal(38,0)").alias("n_paths"), F.sum(F.bit_count("bit")).cast("long").alias("n_answers")).withColumn("hop", F.lit(hop))
        out = rows if out is None else out.unionByName(rows)
    return out.select("qid", "hop", "n_paths", *["n_answers"] * answers)


#: Questions that one row of reached() holds, as longs of 64 bits each.
WIDE = 8


def reached(q: DataFrame, kg: DataFrame, *, depth: int, up_to: bool = False) -> DataFrame:
    """qid, hop, n_answers: the distinct nodes that walks of exactly 1..depth hops reach; up_to gives one
    row for each question instead, with the nodes reached by any of these lengths and hop as depth.
    Questions without a walk are left out. A node keeps the questions that reach it as bits, WIDE longs to a
    row, so that no hop has a row for each pair of question and node. Row numbers of the questions are
    made in ranges; q has a row for each qid."""
    numbered = stored(q.select("qid", "topic").orderBy("qid").withColumn("part", F.spark_partition_id()), "numbered")
    before, at = {}, 0
    for r in numbered.groupBy("part").agg(F.count("*").alias("n")).orderBy("part").collect():  # a row for each task
        before[r["part"]], at = at, at + r["n"]
    if not before:
        return q.sparkSession.createDataFrame([], q.select("qid").schema.add("hop", "integer").add("n_answers", "long"))
    offset = F.element_at(F.create_map(*[F.lit(x) for kv in before.items() for x in kv]), F.col("part"))
    n = F.row_number().over(Window.partitionBy("part").orderBy("qid")) - 1 + offset
    numbered = stored(numbered.select("qid", "topic", n.cast("long").alias("n")), "numbered")
    wide = min(WIDE, -(-at // 64))
    bits = [f"b{i}" for i in range(wide)]
    word = F.floor(F.col("n") / 64).cast("long")
    mine = [F.when(word % wide == i, F.expr("shiftleft(1L, cast(n % 64 as int))")).otherwise(F.lit(0).cast("long")).alias(b) for i, b in enumerate(bits)]
    merged = lambda df, v: df.groupBy(F.col(v).alias("v"), "blk").agg(*[F.bit_or(b).alias(b) for b in bits])
    front = merged(numbered.select("topic", F.floor(word / wide).cast("int").alias("blk"), *mine), "topic")
    edges, out, every = kg.select("head", "tail"), None, []
    for hop in range(1, depth + 1):
        front = stored(merged(front.join(edges, front["v"] == edges["head"]).select("tail", "blk", *bits), "tail"), "reached")
        every.append(front)
        if not up_to or hop == depth:
            rows = _per_bit(merged(union(every), "v") if up_to and depth > 1 else front, bits).withColumn("hop", F.lit(hop))
            out = rows if out is None else out.unionByName(rows)
    return numbered.join(out, "n").select("qid", "hop", "n_answers")


def _per_bit(rows: DataFrame, bits: list[str]) -> DataFrame:
    """n, n_answers: how many rows have the bit of question n set."""
    wide = len(bits)
    words = rows.select("blk", F.posexplode(F.array(*bits)).alias("i", "bit")).filter("bit <> 0")
    sums = words.groupBy("blk", "i").agg(*[F.sum(F.expr(f"shiftrightunsigned(bit, {k}) & 1L")).alias(f"s{k}") for k in range(64)])
    each = sums.select("blk", "i", F.posexplode(F.array(*[f"s{k}" for k in range(64)])).alias("k", "n_answers")).filter("n_answers > 0")
    return each.select(((F.col("blk").cast("long") * wide + F.col("i")) * 64 + F.col("k")).alias("n"), "n_answers")


def branching(kg: DataFrame, sigs: DataFrame) -> DataFrame:
    """etype, b, beta, selectivity: mean out-degree, and mean number of edges that end in etype,
    over all heads with edges."""
    heads = kg.agg(F.countDistinct("head").alias("heads"), F.count("*").alias("edges"))
    per_rel = kg.groupBy("rel").agg(F.count("*").alias("n"))
    per_type = per_rel.join(F.broadcast(sigs.select("rel", "tail_type").distinct()), "rel").groupBy(F.col("tail_type").alias("etype")).agg(F.sum("n").alias("n"))
    b = F.col("edges") / F.col("heads")
    return per_type.crossJoin(F.broadcast(heads)).select("etype", F.round(b, 6).alias("b"), F.round(F.col("n") / F.col("heads"), 6).alias("beta"), F.round(F.col("n") / F.col("edges"), 6).alias("selectivity"))
