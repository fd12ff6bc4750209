"""Methods to compare with (B-01 to B-13): structural counterparts that run natively."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kgtrail.operators.rank import TokenCosine
from kgtrail.plans import expand, retrieve
from kgtrail.sources.shared import stored


def forward_only(q: DataFrame, kg: DataFrame, *, depth: int, budget: int | None = None) -> DataFrame:
    return retrieve.fallback(q, kg, depth=depth, budget=budget)


def forward_counts(q: DataFrame, kg: DataFrame, sigs: DataFrame, *, depth: int, answers: bool = True) -> DataFrame:
    """qid, n_paths, n_answers of forward_only() without listing its paths, for walks of up to `depth` hops;
    signatures must cover the graph. Questions without a path count zero; without answers n_answers is
    left out."""
    hops = retrieve.typed_hops(sigs, sigs.select(F.col("tail_type").alias("etype")), depth=depth, starts=retrieve.topic_types(q))
    walks = expand.count_back(q, kg, hops, answers=False).groupBy("qid").agg(F.sum("n_paths").cast("long").alias("n_paths"))
    rows = q.select("qid").join(walks, "qid", "left")
    if answers:
        rows = rows.join(expand.reached(q, kg, depth=depth, up_to=True).select("qid", "n_answers"), "qid", "left")
    return rows.fillna(0)


def beam(q: DataFrame, kg: DataFrame, *, k: int, depth: int, min_degree: int = 0, encoder=None) -> list[DataFrame]:
    """Topic expansion without types: at each hop the extensions of ends with more than min_degree
    edges are pruned to the k best by similarity, others stay. A frame for each length, written once.
    Where a score rests on relations only, extensions of one path by one relation tie, and its key
    puts the first tails first: of a hub, no more than k tails of each relation are ever joined."""
    encoder = encoder or TokenCosine()
    front, out = expand.start(q), []
    for _ in range(depth):
        edges = around(front, kg)
        if getattr(encoder, "by_relations", False):
            edges = first_tails(edges, max(k, min_degree))
        grown = expand.step(front, edges.drop("degree"))
        degree = edges.select(F.col("head").alias("_from"), "degree").distinct()
        scored = encoder.score(grown, q).withColumn("_from", F.element_at("nodes", -2)).join(degree, "_from").drop("_from")
        wide = F.col("degree") > min_degree
        nth = F.row_number().over(Window.partitionBy("qid", wide).orderBy(F.desc("score"), "path_key"))
        front = stored(scored.withColumn("_n", nth).filter(~wide | (F.col("_n") <= k)).select(*grown.columns), "beam")
        out.append(front)
    return out


def around(front: DataFrame, kg: DataFrame) -> DataFrame:
    """head, rel, tail, degree: the edges of the distinct ends of front; degree is all edges of a head.
    Written once, as it is linear in what is read, not in the paths that share an end."""
    edges = kg.select("head", "rel", "tail").join(front.select(F.col("v").alias("head")).distinct(), "head", "left_semi")
    edges = stored(edges, "around")
    return edges.join(edges.groupBy("head").agg(F.count("*").alias("degree")), "head")


def first_tails(edges: DataFrame, k: int) -> DataFrame:
    """Of each head and relation the first k tails."""
    nth = F.row_number().over(Window.partitionBy("head", "rel").orderBy("tail"))
    return stored(edges.withColumn("_n", nth).filter(F.col("_n") <= k).drop("_n"), "first")


def beam_paths(q: DataFrame, kg: DataFrame, **options) -> DataFrame:
    return expand.union(beam(q, kg, **options)).withColumnRenamed("v", "tail")


def post_filter(q: DataFrame, pred: DataFrame, kg: DataFrame, etypes: DataFrame, sigs: DataFrame, **options) -> DataFrame:
    """The same beam, filtered by the answer type's last relations only when it is done."""
    found = beam_paths(q, kg, **options).withColumn("rel", F.element_at("rels", -1)).withColumn("_v", F.element_at("nodes", -2))
    typed = found.join(etypes, F.col("_v") == F.col("entity")).withColumnRenamed("etype", "head_type")
    last = retrieve.last_hop(pred, sigs)
    return typed.join(last, ["qid", "rel", "head_type"], "left_semi").select("qid", "len", "rels", "nodes", "tail", "path_key")


def train_plans(train: DataFrame, shortest: DataFrame, *, n_plans: int = 2) -> DataFrame:
    """template, rels: the relation sequences seen most on shortest paths of training questions."""
    seen = shortest.select("qid", "rels").distinct().join(train.select("qid", "template"), "qid").groupBy("template", "rels").agg(F.count("*").alias("n"))
    order = Window.partitionBy("template").orderBy(F.desc("n"), F.concat_ws(">", "rels"))
    return seen.withColumn("k", F.row_number().over(order)).filter(F.col("k") <= n_plans).select("template", "rels")


def relation_plans(q: DataFrame, plans: DataFrame, kg: DataFrame, *, depth: int) -> DataFrame:
    """Relation paths chosen first (by template), then grounded; no answer types."""
    plans = stored(plans, "plans")  # a few for each template, read twice
    kg = kg.join(F.broadcast(plans.select(F.explode("rels").alias("rel")).distinct()), "rel", "left_semi")
    mine = q.select("qid", "template").join(F.broadcast(plans), "template").select("qid", "rels")
    return retrieve.ground(q, mine, kg, depth=depth)


def grounded_plans(q: DataFrame, kg: DataFrame, *, depth: int, n_plans: int = 2, encoder=None) -> DataFrame:
    """Only relation sequences that exist around the topic are scored; the best are grounded. The
    trie of sequences grows by distinct (node, sequence) pairs, not by paths."""
    front = q.select("qid", F.col("topic").alias("v"), F.array().cast("array<string>").alias("rels"))
    seqs = None
    for _ in range(depth):
        front = front.join(kg, front["v"] == kg["head"]).select("qid", F.col("tail").alias("v"), F.concat("rels", F.array("rel")).alias("rels")).distinct()
        rows = front.select("qid", "rels").distinct()
        seqs = rows if seqs is None else seqs.unionByName(rows)
    scored = (encoder or TokenCosine()).score(seqs, q)
    order = Window.partitionBy("qid").orderBy(F.desc("score"), F.concat_ws(">", "rels"))
    best = scored.withColumn("k", F.row_number().over(order)).filter(F.col("k") <= n_plans).select("qid", "rels")
    return retrieve.ground(q, best, kg, depth=depth)


def two_sided(q: DataFrame, gold: DataFrame, kg: DataFrame, *, depth: int, sigs: DataFrame | None = None) -> DataFrame:
    """qid, answer, n_paths: walks of exactly `depth` hops, met in the middle from both entities.
    The contrast to type-level meeting: it needs the answer beforehand. The far side grows from the
    distinct answers, not from each question's. With sigs, which must cover a graph of typed edges, and
    the answers' etype in gold, both sides enter only types that lead to the other one."""
    near, far = depth - depth // 2, depth // 2
    hops = [kg] * depth
    if sigs is not None and "etype" in gold.columns:
        hops = [retrieve.along(kg, h) for h in retrieve.typed_hops(sigs, gold, depth=depth, exact=True, starts=retrieve.topic_types(q))]
    a = q.select("qid", F.col("topic").alias("v"), F.lit(1).cast("decimal(38,0)").alias("n"))
    for edges in hops[:near]:
        a = a.join(edges, a["v"] == edges["head"]).groupBy("qid", F.col("tail").alias("v")).agg(F.sum("n").cast("decimal(38,0)").alias("n"))
    gold = stored(gold.select("qid", "answer").distinct(), "gold")
    a = stored(a, "near")
    b = gold.select("answer").distinct().select("answer", F.col("answer").alias("v"), F.lit(1).cast("decimal(38,0)").alias("m"))
    for edges in reversed(hops[near:]):
        b = b.join(edges, b["v"] == edges["tail"]).groupBy("answer", F.col("head").alias("v")).agg(F.sum("m").cast("decimal(38,0)").alias("m"))
    both = a.join(b, "v").join(gold, ["qid", "answer"], "left_semi")
    return both.groupBy("qid", "answer").agg(F.sum(F.col("n").cast("double") * F.col("m").cast("double")).alias("n_paths"))


def ppr(q: DataFrame, kg: DataFrame, *, rounds: int = 3, alpha: float = 0.2, n: int = 20) -> DataFrame:
    """qid, node, mass, rank: the n nodes with the most mass of a walk that restarts at the topic
    with probability alpha, after a fixed number of rounds."""
    degree = kg.groupBy("head").agg(F.count("*").alias("d"))
    out = kg.join(degree, "head").select(F.col("head").alias("v"), "tail", (1.0 / F.col("d")).alias("w"))
    seed = q.select("qid", F.col("topic").alias("v"), F.lit(1.0).alias("mass"))
    now = seed
    for _ in range(rounds):
        moved = now.join(out, "v").groupBy("qid", F.col("tail").alias("v")).agg(F.sum(F.col("mass") * F.col("w") * (1 - alpha)).alias("mass"))
        now = moved.unionByName(seed.withColumn("mass", F.lit(alpha))).groupBy("qid", "v").agg(F.sum("mass").alias("mass"))
    top = now.withColumn("mass", F.round("mass", 9))
    order = Window.partitionBy("qid").orderBy(F.desc("mass"), "v")
    return top.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= n).select("qid", F.col("v").alias("node"), "mass", "rank")


def memory(q: DataFrame, kg: DataFrame, *, k: int = 5, encoder=None) -> DataFrame:
    """Facts around the topic scored by similarity, no path: the k best one-hop edges."""
    facts = retrieve.fallback(q, kg, depth=1)
    scored = (encoder or TokenCosine()).score(facts, q)
    order = Window.partitionBy("qid").orderBy(F.desc("score"), "path_key")
    return scored.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)


def prior_only(train: DataFrame, gold: DataFrame, q: DataFrame) -> DataFrame:
    """qid, answer, rank: the answer given most often to training questions of the template."""
    seen = train.select("qid", "template").join(gold, "qid").groupBy("template", "answer").agg(F.count("*").alias("n"))
    best = seen.groupBy("template").agg(F.min(F.struct((-F.col("n")).alias("n"), "answer")).alias("b")).select("template", "b.answer")
    return q.select("qid", "template").join(F.broadcast(best), "template").select("qid", "answer", F.lit(1).alias("rank"))


def explore(q: DataFrame, kg: DataFrame, *, width: int, depth: int, encoder=None) -> DataFrame:
    """Hop by hop: the `width` relations most similar to the question from where it stands, then the
    first `width` entities of each. Of one path and relation only its first `width` tails can be among
    them, so no more of a hub are joined. Each hop is written once."""
    encoder = encoder or TokenCosine()
    front, out = expand.start(q), None
    for _ in range(depth):
        kg_ = first_tails(around(front, kg), width).drop("degree")
        kinds = front.join(kg_, front["v"] == kg_["head"]).select("qid", F.array("rel").alias("rels")).distinct()
        by_q = Window.partitionBy("qid").orderBy(F.desc("score"), F.concat_ws(">", "rels"))
        chosen = encoder.score(kinds, q).withColumn("k", F.row_number().over(by_q)).filter(F.col("k") <= width).select("qid", F.element_at("rels", 1).alias("rel"))
        grown = expand.step(front, kg_).withColumn("rel", F.element_at("rels", -1)).join(chosen, ["qid", "rel"], "left_semi")
        by_rel = Window.partitionBy("qid", "rel").orderBy("path_key")
        front = stored(grown.withColumn("k", F.row_number().over(by_rel)).filter(F.col("k") <= width).select(*expand.start(q).columns), "explored")
        out = front if out is None else out.unionByName(front)
    return out.withColumnRenamed("v", "tail").select("qid", "len", "rels", "nodes", "tail", "path_key")
