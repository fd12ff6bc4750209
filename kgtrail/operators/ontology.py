"""Typed relation signatures: read from a declared schema or induced from data (O-01 to O-15)."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

COLUMNS = ["head_type", "rel", "tail_type", "support", "source"]


def partial(facts: DataFrame, *, domain_pred: str = "domain", range_pred: str = "range") -> DataFrame:
    """rel, head_type, tail_type with null for an undeclared side: one full join of two filters."""
    heads = facts.filter(F.col("predicate") == domain_pred).select(F.col("subject").alias("rel"), F.col("object").alias("head_type"))
    tails = facts.filter(F.col("predicate") == range_pred).select(F.col("subject").alias("rel"), F.col("object").alias("tail_type"))
    return heads.join(tails, "rel", "full").select("rel", "head_type", "tail_type").distinct()


def complete_only(sigs: DataFrame) -> DataFrame:
    return sigs.filter(F.col("head_type").isNotNull() & F.col("tail_type").isNotNull())


def from_schema(facts: DataFrame, *, domain_pred: str = "domain", range_pred: str = "range") -> DataFrame:
    """Signatures of the relations that declare both sides; several ranges give several rows."""
    both = complete_only(partial(facts, domain_pred=domain_pred, range_pred=range_pred))
    return both.select("head_type", "rel", "tail_type", F.lit(0).cast("long").alias("support"), F.lit("declared").alias("source"))


def drop_types(sigs: DataFrame, blocklist: list[str], *, patterns: tuple[str, ...] = ()) -> DataFrame:
    """Without signatures that touch a blocked type on either side."""
    bad = lambda c: F.coalesce(F.col(c).isin(*blocklist), F.lit(False))
    out = sigs.filter(~bad("head_type") & ~bad("tail_type"))
    for p in patterns:
        out = out.filter(~F.coalesce(F.col("head_type").rlike(p), F.lit(False)) & ~F.coalesce(F.col("tail_type").rlike(p), F.lit(False)))
    return out


def incomplete(sigs: DataFrame, relations: DataFrame) -> DataFrame:
    """rel, missing (head, tail or both) for relations whose signature has a hole."""
    known = sigs.groupBy("rel").agg(F.max(F.col("head_type").isNotNull()).alias("h"), F.max(F.col("tail_type").isNotNull()).alias("t"))
    rows = relations.select("rel").distinct().join(known, "rel", "left").fillna(False, ["h", "t"])
    missing = F.when(~F.col("h") & ~F.col("t"), "both").when(~F.col("h"), "head").when(~F.col("t"), "tail")
    return rows.select("rel", missing.alias("missing")).filter("missing is not null")


def _majority(pairs: DataFrame, least: float) -> DataFrame:
    """rel, etype for relations where one type alone is most frequent, with a share over `least`."""
    counts = pairs.groupBy("rel", "etype").agg(F.count("*").alias("n"))
    by_rel = Window.partitionBy("rel")
    ranked = counts.withColumn("share", F.col("n") / F.sum("n").over(by_rel)).withColumn("top", F.max("n").over(by_rel))
    best = ranked.filter("n = top").withColumn("ties", F.count("*").over(by_rel))
    return best.filter((F.col("ties") == 1) & (F.col("share") > least)).select("rel", "etype", "share")


def complete_from_training(holes: DataFrame, train: DataFrame, etypes: DataFrame, *, min_share: float = 0.5) -> DataFrame:
    """Signatures for incomplete relations from training triples alone, where both sides agree."""
    seen = train.join(F.broadcast(holes.select("rel")), "rel")
    side = lambda end: seen.join(etypes, seen[end] == etypes["entity"]).select("rel", "etype")
    heads = _majority(side("head"), min_share).select("rel", F.col("etype").alias("head_type"))
    tails = _majority(side("tail"), min_share).select("rel", F.col("etype").alias("tail_type"))
    support = seen.groupBy("rel").agg(F.count("*").alias("support"))
    return heads.join(tails, "rel").join(support, "rel").select("head_type", "rel", "tail_type", "support", F.lit("completed").alias("source"))


def induce_entity_types(training: DataFrame) -> DataFrame:
    """entity, etype: the type observed most often on annotated paths; of equals the first name."""
    seen = training.select(F.explode(F.array(F.struct(F.col("topic").alias("entity"), F.element_at("type_path", 1).alias("etype")), F.struct(F.col("answer").alias("entity"), F.element_at("type_path", -1).alias("etype")))).alias("o")).select("o.*")
    counts = seen.groupBy("entity", "etype").agg(F.count("*").alias("n"))
    # the least (-n, etype) per entity: an aggregate, so no entity's rows are ever sorted
    return counts.groupBy("entity").agg(F.min(F.struct((-F.col("n")).alias("m"), "etype")).alias("best")).select("entity", "best.etype")


def induce_signatures(kg: DataFrame, etypes: DataFrame, *, keep: str = "dominant", min_support: int = 1, min_share: float = 0.0) -> DataFrame:
    """Signatures from data: the most frequent type pair of each relation, or all pairs over the
    given support and share. Ties go to the first type names."""
    heads = etypes.select(F.col("entity").alias("head"), F.col("etype").alias("head_type"))
    tails = etypes.select(F.col("entity").alias("tail"), F.col("etype").alias("tail_type"))
    pairs = kg.select("head", "rel", "tail").join(heads, "head").join(tails, "tail").groupBy("rel", "head_type", "tail_type").agg(F.count("*").alias("support"))
    by_rel = Window.partitionBy("rel")
    if keep == "dominant":
        ranked = pairs.withColumn("k", F.row_number().over(by_rel.orderBy(F.desc("support"), "head_type", "tail_type")))
        kept = ranked.filter("k = 1")
    elif keep == "all":
        kept = pairs.withColumn("share", F.col("support") / F.sum("support").over(by_rel)).filter((F.col("support") >= min_support) & (F.col("share") >= min_share))
    else:
        raise ValueError(f"keep is dominant or all, not {keep}")
    return kept.select("head_type", "rel", "tail_type", "support", F.lit("induced").alias("source"))


def lift(etypes: DataFrame, sub: DataFrame, *, levels: int, closure: bool = False) -> DataFrame:
    """Types raised by up to `levels` steps of the class tree; closure keeps the lower ones too."""
    up, out = etypes, etypes
    for _ in range(levels):
        raised = up.join(F.broadcast(sub), up["etype"] == sub["child"], "left")
        up = raised.select("entity", F.coalesce("parent", "etype").alias("etype")).distinct()
        out = out.unionByName(up)
    return out.distinct() if closure else up


def induce_with_hierarchy(kg: DataFrame, inst: DataFrame, sub: DataFrame, *, levels: int = 1, closure: bool = False) -> DataFrame:
    return induce_signatures(kg, lift(inst, sub, levels=levels, closure=closure), keep="all")


def merge(*sigs: DataFrame) -> DataFrame:
    """One row per (rel, types): declared before completed before induced."""
    rows = sigs[0].select(*COLUMNS)
    for s in sigs[1:]:
        rows = rows.unionByName(s.select(*COLUMNS))
    order = F.when(F.col("source") == "declared", 0).when(F.col("source") == "completed", 1).otherwise(2)
    first = rows.groupBy("head_type", "rel", "tail_type").agg(F.min(F.struct(order.alias("o"), "source", "support")).alias("x"))
    return first.select("head_type", "rel", "tail_type", "x.support", "x.source")


def stats(sigs: DataFrame, kg: DataFrame) -> DataFrame:
    """metric, value: sizes of the ontology and how much it condenses the triples."""
    types = sigs.select(F.explode(F.array("head_type", "tail_type")).alias("t")).agg(F.countDistinct("t").alias("types"))
    sizes = sigs.agg(F.countDistinct("rel").alias("relations"), F.count("*").alias("signatures"))
    all_ = kg.agg(F.count("*").alias("triples")).crossJoin(sizes).crossJoin(types)
    all_ = all_.withColumn("compression", F.round(F.col("triples") / F.col("signatures"), 6))
    names = ["triples", "relations", "signatures", "types", "compression"]
    return all_.select(F.explode(F.array(*[F.struct(F.lit(n).alias("metric"), F.col(n).cast("double").alias("value")) for n in names])).alias("r")).select("r.*")


def coverage(sigs: DataFrame, used_a: DataFrame, used_b: DataFrame) -> DataFrame:
    """scope (a, b, shared, union), total, incomplete, pct of the relations that workloads use."""
    a, b = used_a.select("rel").distinct(), used_b.select("rel").distinct()
    scopes = [("a", a), ("b", b), ("shared", a.intersect(b)), ("union", a.union(b).distinct())]
    fine = complete_only(sigs).select("rel").distinct().withColumn("fine", F.lit(1))
    rows = None
    for name, rels in scopes:
        one = rels.join(fine, "rel", "left").agg(F.count("*").alias("total"), F.count_if(F.col("fine").isNull()).alias("incomplete"))
        one = one.select(F.lit(name).alias("scope"), "total", "incomplete", F.round(100 * F.col("incomplete") / F.col("total"), 6).alias("pct"))
        rows = one if rows is None else rows.unionByName(one)
    return rows


def by_tail(sigs: DataFrame) -> DataFrame:
    return sigs.groupBy("tail_type").agg(F.array_sort(F.collect_set(F.concat_ws("/", "head_type", "rel"))).alias("last_hops"))


def by_rel(sigs: DataFrame) -> DataFrame:
    return sigs.groupBy("rel").agg(F.array_sort(F.collect_set("tail_type")).alias("tail_types"))


def by_head(sigs: DataFrame) -> DataFrame:
    return sigs.groupBy("head_type").agg(F.array_sort(F.collect_set("rel")).alias("rels"))


def violations(kg: DataFrame, etypes: DataFrame, sigs: DataFrame) -> DataFrame:
    """rel, n: triples whose typed form is no signature."""
    heads = etypes.select(F.col("entity").alias("head"), F.col("etype").alias("head_type"))
    tails = etypes.select(F.col("entity").alias("tail"), F.col("etype").alias("tail_type"))
    typed = kg.select("head", "rel", "tail").join(heads, "head").join(tails, "tail").groupBy("rel", "head_type", "tail_type").agg(F.count("*").alias("n"))
    odd = typed.join(F.broadcast(sigs.select("rel", "head_type", "tail_type").distinct()), ["rel", "head_type", "tail_type"], "left_anti")
    return odd.groupBy("rel").agg(F.sum("n").alias("n"))
