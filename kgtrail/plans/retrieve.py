"""Bidirectional retrieval: topic-side prefixes, completed only by final relations that lead to the
predicted type (R-01, R-04 to R-14, R-17).

The semantic rewrites live here, as plan building: the last hop is reserved (prefixes stop one hop
short), its relations come from the answer type, and the head type is tested before the last join.
A Catalyst rule could do the same through injectOptimizerRule, but that needs JVM code.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kgtrail.plans import expand
from kgtrail.sources.shared import stored


@dataclass(frozen=True)
class Config:
    depth: int = 2
    budget: int | None = None
    length_mode: str = "up_to"  # or "exact"
    path_mode: str = "walk"  # or "simple"
    head_check: str = "strict"  # or "edge"
    use_mask: bool = False
    k: int = 256
    covered: bool = False  # every edge has a signature, so types alone may rule prefixes out
    first: int | None = None  # with covered, walks only: what a ranking by relations, length and key to this rank can need
    texts: bool = False  # with covered: rel_text too, the relations as text, put together from two parts for each row


def last_hop(pred: DataFrame, sigs: DataFrame) -> DataFrame:
    """qid, rel, head_type of the final hops that end in a predicted type (qid, etype)."""
    s = F.broadcast(sigs.select("rel", "head_type", F.col("tail_type").alias("etype")).distinct())
    return pred.select("qid", "etype").join(s, "etype").select("qid", "rel", "head_type").distinct()


def meet(prefixes: DataFrame, etypes: DataFrame, last: DataFrame, *, head_check: str = "strict") -> DataFrame:
    """Prefixes with the final relations that may complete them: one row per (prefix, rel). The type
    of an end is read from the prefix, or looked up where prefixes do not carry it. A topic, whose
    type no edge told, meets all final relations; its edges are then held against head_type."""
    if head_check == "edge":
        return prefixes.join(last.select("qid", "rel").distinct(), "qid")
    if "vtype" in prefixes.columns:
        return prefixes.join(last, "qid").filter("vtype is null or vtype = head_type").drop("vtype")
    typed = prefixes.join(etypes, prefixes["v"] == etypes["entity"]).withColumnRenamed("etype", "head_type").drop("entity")
    return typed.join(last, ["qid", "head_type"]).drop("head_type").distinct()


def complete(met: DataFrame, kg: DataFrame, last: DataFrame | None = None, *, path_mode: str = "walk") -> DataFrame:
    """The met prefixes, lengthened by their matched edges only. Of a graph stored by relation only
    the relations that occur in `last` are read: the broadcast side has a row for each relation."""
    edges = kg if last is None else kg.join(F.broadcast(last.select("rel").distinct()), "rel", "left_semi")
    types = ["head_type"] if "head_type" in met.columns else []
    hop = met.join(edges.select(F.col("head").alias("v"), "rel", *types, "tail"), ["v", "rel", *types])
    if path_mode == "simple":
        hop = hop.filter(~F.array_contains("nodes", F.col("tail")))
    return hop.select(
        "qid", (F.col("len") + 1).alias("len"), F.concat("rels", F.array("rel")).alias("rels"), F.concat("nodes", F.array("tail")).alias("nodes"), "tail", F.concat_ws("|", "path_key", "rel", "tail").alias("path_key"),
    )


def reach_mask(sigs: DataFrame, pred: DataFrame, *, depth: int) -> DataFrame:
    """qid, hops_left, etype: types from which a predicted type is reached in exactly 1..depth hops
    of signatures. Works on the small type tables alone."""
    s = F.broadcast(sigs.select("head_type", "tail_type").distinct())
    now = pred.select("qid", "etype")
    out = None
    for i in range(1, depth + 1):
        now = now.join(s, now["etype"] == s["tail_type"]).select("qid", F.col("head_type").alias("etype")).distinct()
        rows = now.withColumn("hops_left", F.lit(i))
        out = rows if out is None else out.unionByName(rows)
    return out.select("qid", "hops_left", "etype")


def typed_hops(sigs: DataFrame, ends: DataFrame, *, depth: int, exact: bool = False, starts: DataFrame | None = None) -> list[list[tuple[str, str, str]]]:
    """For each hop 1..depth the signatures (head_type, rel, tail_type) that a path may take there: it
    leaves from a type of `starts` (etype; none: any) and ends in one of `ends` (etype) after `depth`
    hops, or fewer unless exact. Works on types alone; all three frames have a row for each type."""
    known = [(r["head_type"], r["rel"], r["tail_type"]) for r in sigs.select("head_type", "rel", "tail_type").distinct().collect()]
    wanted = {r["etype"] for r in ends.select("etype").distinct().collect()}
    now = {h for h, _, _ in known} if starts is None else {r["etype"] for r in starts.select("etype").distinct().collect()}
    left = [wanted]  # left[k]: the types from which k more hops end the path
    for _ in range(depth):
        left.append({h for h, _, t in known if t in left[-1]})
    out = []
    for i in range(1, depth + 1):
        fine = left[depth - i] if exact else set().union(*left[: depth - i + 1])
        out.append(sorted(s for s in known if s[0] in now and s[2] in fine))
        now = {t for _, _, t in out[-1]}
    return out


def topic_types(q: DataFrame) -> DataFrame | None:
    """etype of the topics, where the questions say it (topic_type)."""
    return q.select(F.col("topic_type").alias("etype")) if "topic_type" in q.columns else None


def along(kg: DataFrame, hops: list[tuple[str, str, str]]) -> DataFrame:
    """The edges of some signatures: only the parts of these relations are read."""
    heads, rels, tails = (sorted({h[i] for h in hops}) for i in range(3))
    return kg.filter(F.col("rel").isin(rels) & F.col("head_type").isin(heads) & F.col("tail_type").isin(tails))


def typed_prefixes(q: DataFrame, pred: DataFrame, kg: DataFrame, sigs: DataFrame, *, depth: int) -> list[DataFrame]:
    """Prefixes of length 0 to depth from which one hop less or more still leads to a predicted type;
    signatures must cover the graph. Those left out could meet no last hop."""
    fronts = [expand.start(q)]
    for some in typed_hops(sigs, pred, depth=depth + 1, starts=topic_types(q))[:depth]:
        fronts.append(expand.step(fronts[-1], along(kg, some)))
    return fronts


#: Rows of a first hop that stand on one node and go to one task; a node with more is dealt to several.
CROWD = 64
#: Nodes that are dealt out at most.
MOST_CROWDED = 1_000


#: Hash values that likely() tells apart, so that what it broadcasts has a bound.
HASHES = 1 << 21


def likely(edges: DataFrame, nodes: DataFrame, col: str) -> DataFrame:
    """The edges, columns as given, whose head may be among `col` of nodes: heads of another hash are left out before
    any shuffle. The join that follows must still compare the heads."""
    h = lambda c: F.pmod(F.xxhash64(c), F.lit(HASHES)).cast("int").alias("_h")
    return edges.withColumn("_h", h("head")).join(F.broadcast(nodes.select(h(col)).distinct()), "_h", "left_semi").drop("_h")


def spread(front: DataFrame, ways: DataFrame, on: list[str]) -> DataFrame:
    """front joined with ways on `on`, v among them. The ways on from a node where many rows of front stand are dealt
    to several tasks, each with all these rows. ways come first, as a sort-merge join keeps the rows of
    the other side in memory. The number of tasks is given, or else it would go by the size of the inputs, of which
    the result is a product. front is read twice, so it should be written."""
    n, keys = int(front.sparkSession.conf.get("spark.sql.shuffle.partitions")), [*on, "_part"]
    crowds = front.groupBy("v").agg(F.count("*").alias("n")).filter(F.col("n") > CROWD).orderBy(F.desc("n"), "v").limit(MOST_CROWDED)
    crowds = F.broadcast(crowds.select("v", F.least(F.ceil(F.col("n") / CROWD), F.lit(256)).cast("int").alias("_parts")))
    few = front.join(crowds, "v", "left").withColumn("_part", F.explode(F.sequence(F.lit(0), F.coalesce("_parts", F.lit(1)) - 1))).drop("_parts")
    dealt = F.when(F.col("_parts").isNull(), 0).otherwise(F.pmod(F.xxhash64(*[c for c, kind in ways.dtypes if kind == "string"]), F.col("_parts"))).cast("int")
    return ways.join(crowds, "v", "left").withColumn("_part", dealt).drop("_parts").repartition(n, *keys).join(few.repartition(n, *keys), keys).drop("_part")


def _covered(q: DataFrame, pred: DataFrame, kg: DataFrame, sigs: DataFrame, last: DataFrame, config: Config) -> DataFrame:
    """bidirectional() where types rule prefixes out: each hop reads the relations that lead on. Only the
    first hop is made for each question. The ways on from there to the end are the same for all questions
    that come by a node; they are made once for each node and joined to the first hops in the result, so
    that no table and no shuffle carries the paths that questions have through a hub."""
    d, exact = config.depth, config.length_mode == "exact"
    hops = typed_hops(sigs, pred, depth=d, exact=exact, starts=topic_types(q))
    # questions with the same final hops form one class, of which there are few
    ends = last.groupBy("qid").agg(F.array_join(F.array_sort(F.collect_set(F.concat_ws("/", "rel", "head_type"))), ",").alias("ends"))
    kinds = F.broadcast(last.join(ends, "qid").select("ends", "rel", "head_type").distinct())
    final = lambda some: along(kg, some).join(kinds, ["rel", "head_type"]).select("ends", F.col("head").alias("end"), "rel", "tail")
    # written, so that few questions are known to be few: no hop then shuffles the edges to meet them
    asked = stored(expand.start(q).join(ends, "qid"), "asked")
    out = None
    if d == 1 or not exact:
        near = asked.withColumnRenamed("v", "end").join(final(hops[0]), ["end", "ends"])
        out = near.select("qid", F.lit(1).alias("len"), F.array("rel").alias("rels"), F.concat("nodes", F.array("tail")).alias("nodes"), "tail", F.concat_ws("|", "path_key", "rel", "tail").alias("path_key"), F.col("rel").alias("rel_text"))
    if d > 1:
        front = stored(expand.step(asked, likely(along(kg, hops[0]), asked, "v"), path_mode=config.path_mode).join(ends, "qid"), "front")
        none = F.array().cast("array<string>")
        walks, ways = front.select("v").distinct().select("v", F.col("v").alias("end"), *[none.alias(c) for c in ("rels2", "nodes2", "key2")]), None
        on = lambda edges: walks.join(edges, "end").select(
            *["ends"] * ("ends" in edges.columns), "v", F.col("tail").alias("end"), F.concat("rels2", F.array("rel")).alias("rels2"), F.concat("nodes2", F.array("tail")).alias("nodes2"), F.concat("key2", F.array("rel", "tail")).alias("key2"),
        )
        for i in range(2, d + 1):
            if i == d or not exact:
                done = on(final(hops[i - 1]))
                ways = done if ways is None else ways.unionByName(done)
            if i < d:  # written, so that its size is known when it meets the next edges, which may be many more
                walks = stored(on(likely(along(kg, hops[i - 1]), walks, "end").select(F.col("head").alias("end"), "rel", "tail")), "walks")
        # texts are made on both sides, as the rows of the join are many more
        ways = ways.select("ends", "v", F.col("end").alias("tail"), (F.size("rels2") + 1).alias("len"), "rels2", "nodes2", F.concat(F.lit("|"), F.concat_ws("|", "key2")).alias("key2"), F.concat(F.lit(">"), F.concat_ws(">", "rels2")).alias("text2"))
        if config.first is not None and config.path_mode == "walk":
            # paths of a question through one first hop that take the same relations differ in their keys alone
            nth = F.row_number().over(Window.partitionBy("v", "ends", "text2").orderBy("key2"))
            ways = stored(ways.withColumn("_nth", nth).filter(F.col("_nth") <= config.first).drop("_nth"), "ways")
        far = spread(front.drop("len").withColumn("rel_text", F.concat_ws(">", "rels")), ways, ["v", "ends"]).select(
            "qid", "len", F.concat("rels", "rels2").alias("rels"), F.concat("nodes", "nodes2").alias("nodes"), "tail", F.concat("path_key", "key2").alias("path_key"), F.concat("rel_text", "text2").alias("rel_text"),
        )
        out = far if out is None else out.unionByName(far)
    if config.path_mode == "simple":
        out = out.filter(F.size(F.array_distinct("nodes")) == F.size("nodes"))
    return out if config.texts else out.drop("rel_text")


def bidirectional(q: DataFrame, pred: DataFrame, kg: DataFrame, etypes: DataFrame, sigs: DataFrame, config: Config) -> DataFrame:
    """qid, len, rels, nodes, tail, path_key of all paths of the configured lengths that end, by an
    allowed last edge, in the predicted type. Questions whose type has no final hop give none."""
    last = last_hop(pred, sigs)
    d = config.depth
    asked = q.join(last.select("qid").distinct(), "qid", "left_semi")
    if config.covered and config.head_check == "strict" and config.budget is None and {"head_type", "tail_type"} <= set(kg.columns):
        return _covered(asked, pred, kg, sigs, last, config)
    masks = None
    if config.use_mask:
        reach = reach_mask(sigs, pred, depth=d)
        at_most = lambda left: F.col("hops_left") <= left if config.length_mode == "up_to" else F.col("hops_left") == left
        masks = [reach.filter(at_most(d - i)).select("qid", "etype").distinct() for i in range(d)]
    strict = config.head_check == "strict"
    fronts = expand.prefixes(asked, kg, depth=d - 1, budget=config.budget, path_mode=config.path_mode, masks=masks, etypes=etypes, typed=strict)
    chosen = fronts if config.length_mode == "up_to" else fronts[-1:]
    # prefixes of all lengths meet the last edges at once
    return complete(meet(expand.union(chosen), etypes, last, head_check=config.head_check), kg, last, path_mode=config.path_mode)


def _second(front: DataFrame, kg: DataFrame) -> DataFrame:
    """expand.step() from a written first hop, whose hubs are dealt out. Where edges carry types, only those that
    leave from a type of an end are read."""
    if "vtype" in front.columns:
        kg = kg.filter(F.col("head_type").isin([r["vtype"] for r in front.select("vtype").distinct().collect()]))  # a row for each type
    edges = likely(kg, front, "v").select(F.col("head").alias("v"), "rel", "tail", *["tail_type"] * ("vtype" in front.columns), F.concat_ws("|", F.lit(""), "rel", "tail").alias("key2"))
    # the text of the relations comes from both sides, as in _covered()
    hop = spread(front.withColumn("rel_text", F.concat_ws(">", "rels")), edges, ["v"])
    return hop.select(
        "qid", (F.col("len") + 1).alias("len"), F.concat("rels", F.array("rel")).alias("rels"), F.concat("nodes", F.array("tail")).alias("nodes"), F.col("tail").alias("v"), F.concat("path_key", "key2").alias("path_key"),
        *[F.col("tail_type").alias("vtype")] * ("vtype" in front.columns), F.concat("rel_text", F.lit(">"), "rel").alias("rel_text"),
    )


def fallback(q: DataFrame, kg: DataFrame, *, depth: int, budget: int | None = None, path_mode: str = "walk", length_mode: str = "up_to", texts: bool = False) -> DataFrame:
    """Forward search: every path of up to `depth` hops from the topic, whatever it ends in. The first hop
    is written, which the edges of the topics bound, so that its size is known when it meets all edges. texts as in Config."""
    near = kg
    if "topic_type" in q.columns and "head_type" in kg.columns:
        near = kg.filter(F.col("head_type").isin([r["topic_type"] for r in q.select("topic_type").distinct().collect()]))  # a row for each type
    front = stored(expand.prefixes(q, likely(near, q, "topic"), depth=1, budget=budget, path_mode=path_mode, typed=True)[1], "front")
    plain = lambda f: f if "rel_text" in f.columns else f.withColumn("rel_text", F.concat_ws(">", "rels"))
    fronts = [front]
    for hop in range(1, depth):
        grown = _second(front, kg) if hop == 1 and path_mode == "walk" else expand.step(fronts[-1], kg, path_mode=path_mode)
        fronts.append(expand.within_budget(grown, budget))
    chosen = fronts if length_mode == "up_to" else fronts[-1:]
    return expand.union([plain(f) for f in chosen]).withColumnRenamed("v", "tail").select("qid", "len", "rels", "nodes", "tail", "path_key", *["rel_text"] * texts)


def route(q: DataFrame, pred: DataFrame, kg: DataFrame, etypes: DataFrame, sigs: DataFrame, config: Config) -> DataFrame:
    """Bidirectional where the predicted type has final hops, forward search elsewhere; `mode` says
    which. One plan for all questions."""
    known = last_hop(pred, sigs).select("qid").distinct()
    two = bidirectional(q.join(known, "qid", "left_semi"), pred, kg, etypes, sigs, config).withColumn("mode", F.lit("bidirectional"))
    one = fallback(q.join(known, "qid", "left_anti"), kg, depth=config.depth, budget=config.budget, path_mode=config.path_mode, length_mode=config.length_mode)
    return two.unionByName(one.withColumn("mode", F.lit("fallback")))


def type_plans(q: DataFrame, pred: DataFrame, sigs: DataFrame, topic_types: DataFrame, *, depth: int) -> DataFrame:
    """qid, rels: relation sequences that lead in the ontology from the topic's type to the
    predicted one, before any entity is touched. topic_types: (qid, etype)."""
    s = F.broadcast(sigs.select("head_type", "rel", "tail_type").distinct())
    now = topic_types.select("qid", F.col("etype").alias("t"), F.array().cast("array<string>").alias("rels"))
    wanted = pred.select("qid", F.col("etype").alias("t")).distinct()
    out = None
    for _ in range(depth):
        now = now.join(s, now["t"] == s["head_type"]).select("qid", F.col("tail_type").alias("t"), F.concat("rels", F.array("rel")).alias("rels"))
        rows = now.join(wanted, ["qid", "t"], "left_semi").select("qid", "rels")
        out = rows if out is None else out.unionByName(rows)
    return out.distinct()


def ground(q: DataFrame, plans: DataFrame, kg: DataFrame, *, depth: int) -> DataFrame:
    """The paths in the graph that follow a plan (qid, rels): at hop i only edges whose relation is
    the i-th of the plan are joined, so plans without such edges end there."""
    plan = plans.select("qid", F.col("rels").alias("plan"))
    front = expand.start(q).join(plan, "qid")
    out = None
    for i in range(1, depth + 1):
        front = front.filter(F.size("plan") >= i).withColumn("rel", F.element_at("plan", i))
        edges = kg.select(F.col("head").alias("v"), "rel", "tail")
        front = front.join(edges, ["v", "rel"]).select(
            "qid", "plan", F.lit(i).alias("len"), F.concat("rels", F.array("rel")).alias("rels"), F.concat("nodes", F.array("tail")).alias("nodes"), F.col("tail").alias("v"), F.concat_ws("|", "path_key", "rel", "tail").alias("path_key"),
        )
        rows = front.filter(F.size("plan") == i)
        out = rows if out is None else out.unionByName(rows)
    return out.withColumnRenamed("v", "tail").select("qid", "len", "rels", "nodes", "tail", "path_key")


def check_tail_type(paths: DataFrame, etypes: DataFrame, pred: DataFrame) -> DataFrame:
    """Paths whose tail lacks every predicted type of their question; none are expected."""
    typed = paths.join(etypes, paths["tail"] == etypes["entity"]).select("qid", "path_key", "etype")
    fine = typed.join(pred.select("qid", "etype"), ["qid", "etype"], "left_semi")
    return paths.join(fine, ["qid", "path_key"], "left_anti")


def answers(paths: DataFrame, score: str | None = None) -> DataFrame:
    """qid, answer, score, n_paths: the distinct tails of the paths with their best score."""
    best = F.max(score) if score else F.lit(0.0)
    return paths.groupBy("qid", F.col("tail").alias("answer")).agg(best.alias("score"), F.count("*").alias("n_paths"))
