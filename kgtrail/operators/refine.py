"""Iterative refinement: a generator proposes answers, a refiner judges them, contexts are rebuilt
from the first pool (F-01 to F-16).

A question's state is one row; its paths, at most k, are rows keyed by qid. Contexts always start
from the initial pool p0, so nothing grows over the rounds; each round's result is written to the
shared folder, and only questions that go on take part in the next.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from kgtrail.sources.shared import stored

VERDICT = (
    "struct<confidence:int,issue:string,retained:array<string>,forbidden:array<string>,prioritized:array<string>,"
    "supplementary:array<string>,dropped:array<string>,summary:string>"
)
STRINGS = "array<string>"


def _empty() -> Column:
    return F.array().cast(STRINGS)


@dataclass(frozen=True)
class RuleGenerator:
    """Score of an answer: its best path's score and a small bonus for the number of paths. Answers
    within `margin` of the best stay; forbidden ones go; answers kept before bound the choice."""

    margin: float = 1.0

    def generate(self, ctx: DataFrame, paths: DataFrame) -> DataFrame:
        """ctx (qid, kept, forbidden), paths (qid, tail, score) -> qid, y_gen (answers, best first)."""
        per = paths.groupBy("qid", F.col("tail").alias("answer")).agg(F.max("score").alias("s"), F.count("*").alias("n"))
        per = per.select("qid", "answer", F.round(F.col("s") + 0.01 * F.log(1 + F.col("n")), 6).alias("s"))
        top = per.withColumn("top", F.max("s").over(Window.partitionBy("qid")))
        kept = top.filter(F.col("s") >= F.col("top") - self.margin).join(ctx.select("qid", "kept", "forbidden"), "qid")
        kept = kept.filter(~F.array_contains("forbidden", F.col("answer")) & ((F.size("kept") == 0) | F.array_contains("kept", F.col("answer"))))
        ranked = kept.groupBy("qid").agg(F.array_sort(F.collect_list(F.struct((-F.col("s")).alias("s"), "answer"))).alias("y"))
        got = ranked.select("qid", F.transform("y", lambda x: x["answer"]).alias("y_gen"))
        return ctx.select("qid").join(got, "qid", "left").select("qid", F.coalesce("y_gen", _empty()).alias("y_gen"))


def satisfied(paths: DataFrame, q: DataFrame, facts: DataFrame) -> DataFrame:
    """qid, path_key, ok: whether a path meets all constraints of its question. facts holds
    (entity, attr, value); a constraint's entity is the answer, an inner node, or the path itself
    ('via': the relation occurs on it)."""
    each = paths.select("qid", "path_key", "rels", "nodes", "tail").join(q.select("qid", F.explode_outer("constraints").alias("c")), "qid")
    target = F.when(F.col("c.target") == "answer", F.col("tail")).when(F.col("c.target").startswith("node"), F.get("nodes", F.expr("try_cast(substring(c.target, 5) as int)")))
    each = each.select("qid", "path_key", "c", target.alias("entity"), F.array_contains("rels", F.col("c.rel")).alias("via"))
    # written, so that the facts of all entities need no shuffle where few are asked for
    wanted = stored(each.select("entity", F.col("c.rel").alias("attr")).filter("entity is not null and attr is not null").distinct(), "wanted")
    facts = facts.select("entity", "attr", "value").join(wanted, ["entity", "attr"], "left_semi")
    known = each.join(facts, (each["entity"] == facts["entity"]) & (F.col("c.rel") == facts["attr"]), "left")
    number = F.col("value").try_cast("double")
    want = F.col("c.value").try_cast("double")
    ends = F.split("c.value", r"\.\.")
    op = F.col("c.op")
    holds = (
        F.when(F.col("c").isNull(), True)
        .when(op == "via", F.col("via"))
        .when(op == "=", F.col("value") == F.col("c.value"))
        .when(op == "<>", F.col("value") != F.col("c.value"))
        .when(op == "in", F.array_contains(F.split("c.value", ","), F.col("value")))
        .when(op == "between", number.between(F.get(ends, F.lit(0)).try_cast("double"), F.get(ends, F.lit(1)).try_cast("double")))
        .when(op == "<", number < want).when(op == "<=", number <= want).when(op == ">", number > want).when(op == ">=", number >= want)
    )
    # several facts of one attribute: one that holds is enough; several constraints: all must hold
    one = known.groupBy("qid", "path_key", "c").agg(F.max(F.coalesce(holds, F.lit(False))).alias("holds"))
    return one.groupBy("qid", "path_key").agg(F.min("holds").alias("ok"))


@dataclass(frozen=True)
class RuleRefiner:
    """Checks each answer's paths against the question's constraints on the graph."""

    facts: DataFrame

    def judge(self, q: DataFrame, p0: DataFrame, gen: DataFrame, etypes: DataFrame | None = None) -> DataFrame:
        """qid, verdict. p0 carries `ok` if satisfied() has been joined before; else it is here."""
        if "ok" not in p0.columns:
            p0 = p0.join(satisfied(p0, q, self.facts), ["qid", "path_key"])
        mine = p0.join(gen.select("qid", "y_gen"), "qid").withColumn("said", F.array_contains("y_gen", F.col("tail")))
        ok, said = F.col("ok"), F.col("said")
        some = lambda c, when: F.array_sort(F.collect_set(F.when(when, F.col(c))))
        per = mine.groupBy("qid").agg(
            some("tail", ok & said).alias("good"), some("tail", ~ok & said).alias("bad"), some("path_key", ok & said).alias("prioritized"), some("path_key", ~ok & said).alias("dropped"), some("path_key", ok & ~said).alias("supplementary"),
        )
        odd = F.lit(False)
        rows = gen.select("qid", "y_gen").join(per, "qid", "left")
        if etypes is not None and "etype" in q.columns:  # a tail of another type than predicted
            tails = p0.select("qid", "tail").distinct().join(etypes.withColumnRenamed("etype", "has"), F.col("tail") == F.col("entity"))
            misfit = tails.join(q.select("qid", F.col("etype").alias("want")), "qid").groupBy("qid").agg(F.max(~F.col("has").eqNullSafe(F.col("want"))).alias("odd"))
            rows = rows.join(misfit, "qid", "left")
            odd = F.coalesce("odd", F.lit(False))
        c = lambda name: F.coalesce(F.col(name), _empty())
        rows = rows.select("qid", "y_gen", c("good").alias("good"), c("bad").alias("bad"), c("prioritized").alias("prioritized"), c("dropped").alias("dropped"), c("supplementary").alias("supplementary"), odd.alias("odd"))
        none = F.size("good") == 0
        # where nothing said is supported, violating paths give way to supported ones that were not
        # said; without any they stay, and the next round starts from the same answers
        rows = rows.withColumn("dropped", F.when(none & (F.size("supplementary") == 0), _empty()).otherwise(F.col("dropped")))
        rows = rows.withColumn("forbidden", F.when(none, _empty()).otherwise(F.array_sort(F.array_except("y_gen", "good"))))
        issue = F.when(F.col("odd"), "type_mismatch").when(none, "no_support").when(F.size(F.array_intersect("good", "bad")) > 0, "conflict").when(F.size("forbidden") > 0, "answer_noise").otherwise("none")
        confidence = F.when(none, 1).when(F.size("forbidden") == 0, 3).otherwise(2)
        summary = F.concat(F.size("good").cast("string"), F.lit(" of "), F.size("y_gen").cast("string"), F.lit(" answers supported"))
        verdict = F.struct(confidence.alias("confidence"), issue.alias("issue"), F.col("good").alias("retained"), "forbidden", "prioritized", "supplementary", "dropped", summary.alias("summary")).cast(VERDICT)
        return rows.select("qid", verdict.alias("verdict"))


def select_paths(p0: DataFrame, gen: DataFrame) -> DataFrame:
    """Paths of the initial pool that end in a proposed answer."""
    said = gen.select("qid", F.explode("y_gen").alias("tail"))
    return p0.join(said, ["qid", "tail"], "left_semi")


def post(y: Column, verdict: Column) -> Column:
    """Forbidden answers go; if any is retained, only those stay. Order is kept."""
    left = F.filter(y, lambda a: ~F.array_contains(verdict["forbidden"], a))
    return F.when(F.size(verdict["retained"]) > 0, F.filter(left, lambda a: F.array_contains(verdict["retained"], a))).otherwise(left)


def update_paths(p0: DataFrame, state: DataFrame, *, n_neutral: int = 3, k: int = 256) -> DataFrame:
    """The next context: promoted paths, other paths of the focus (retained answers, or those
    generated if none is), appended paths, a few neutral ones under conflict or noise; dropped
    paths leave. state: qid, y_gen, verdict."""
    v = F.col("verdict")
    rows = p0.join(state.select("qid", "y_gen", "verdict"), "qid")
    focus = F.when(F.size(v["retained"]) > 0, v["retained"]).otherwise(F.col("y_gen"))
    in_ = lambda field: F.array_contains(v[field], F.col("path_key"))
    tier = F.when(in_("prioritized"), 0).when(F.array_contains(focus, F.col("tail")), 1).when(in_("supplementary"), 2).when(~F.array_contains("y_gen", F.col("tail")), 3)
    rows = rows.withColumn("tier", tier).filter("tier is not null").filter(~in_("dropped"))
    nth = F.row_number().over(Window.partitionBy("qid", "tier").orderBy("rank"))
    rows = rows.withColumn("nth", nth).filter((F.col("tier") < 3) | (v["issue"].isin("conflict", "answer_noise") & (F.col("nth") <= n_neutral)))
    place = F.row_number().over(Window.partitionBy("qid").orderBy("tier", "rank"))
    return rows.withColumn("place", place).filter(F.col("place") <= k).select(*p0.columns, "tier", "place")


def update_answers(state: DataFrame) -> DataFrame:
    """qid, kept, forbidden: the answer context holds the retained answers only."""
    return state.select("qid", F.col("verdict.retained").alias("kept"), F.col("verdict.forbidden").alias("forbidden"))


def should_stop(verdict: Column, y_ref: Column, before: Column, *, top: int = 3) -> Column:
    same = before.isNotNull() & (F.array_sort(y_ref) == F.array_sort(before))
    return (verdict["confidence"] >= top) | F.coalesce(same, F.lit(False))


RUN = "qid long, y_gen array<string>, y_ref array<string>, confidence int, issue string, rounds int"


def run(q: DataFrame, p0: DataFrame, generator, refiner, *, max_rounds: int = 3, adaptive: bool = True, n_neutral: int = 3, etypes: DataFrame | None = None) -> DataFrame:
    """qid, y_gen, y_ref, confidence, issue, rounds of every question.

    adaptive stops a question at top confidence, or when its refined answers repeat; else all go
    through max_rounds. max_rounds=0 is the single pass: generated answers, no refiner. Questions
    without paths have no round and no answer.
    """
    if max_rounds == 0:
        asked, none = _split(q, p0)
        got = generator.generate(_start(asked), p0)
        return none.unionByName(got.select("qid", "y_gen", F.col("y_gen").alias("y_ref"), F.lit(0).alias("confidence"), F.lit("none").alias("issue"), F.lit(1).alias("rounds")))
    rounds = trace(q, p0, generator, refiner, max_rounds=max_rounds, adaptive=adaptive, n_neutral=n_neutral, etypes=etypes)
    if adaptive:  # no question went on after it stopped
        return rounds.filter(F.col("stop") | (F.col("rounds") == max_rounds)).drop("stop")
    return cut(rounds, max_rounds=max_rounds, adaptive=False)


def _split(q: DataFrame, p0: DataFrame) -> tuple[DataFrame, DataFrame]:
    """qid of the questions with paths, and the result of those without."""
    asked = q.select("qid").join(p0.select("qid").distinct(), "qid", "left_semi")
    empty = q.select("qid").join(p0.select("qid").distinct(), "qid", "left_anti")
    return asked, empty.select("qid", _empty().alias("y_gen"), _empty().alias("y_ref"), F.lit(0).alias("confidence"), F.lit("no_support").alias("issue"), F.lit(0).alias("rounds"))


def _start(asked: DataFrame) -> DataFrame:
    return asked.select("qid", _empty().alias("kept"), _empty().alias("forbidden"), F.lit(None).cast(STRINGS).alias("before"))


def trace(q: DataFrame, p0: DataFrame, generator, refiner, *, max_rounds: int = 3, adaptive: bool = False, n_neutral: int = 3, etypes: DataFrame | None = None) -> DataFrame:
    """Every round of every question: the columns of run(), where rounds is the number of the round (0 and
    one row for questions without paths), and stop, whether an adaptive run ends there. A round looks at
    no other question and at no limit, so the runs to all limits up to max_rounds, adaptive and fixed, can be
    cut from one trace. adaptive: questions take part only until they stop."""
    p0 = p0 if "ok" in p0.columns else stored(p0.join(satisfied(p0, q, refiner.facts), ["qid", "path_key"]), "pool")
    asked, none = _split(q, p0)
    ctx, out, paths = _start(asked), none.withColumn("stop", F.lit(True)), p0
    for t in range(1, max_rounds + 1):
        gen = generator.generate(ctx, paths)
        active = p0.join(ctx.select("qid"), "qid", "left_semi")
        verdicts = refiner.judge(q, active, gen, etypes)
        state = gen.join(verdicts, "qid").join(ctx.select("qid", "before"), "qid").withColumn("y_ref", post(F.col("y_gen"), F.col("verdict")))
        state = stored(state.withColumn("stop", should_stop(F.col("verdict"), F.col("y_ref"), F.col("before"))), "round")
        out = out.unionByName(state.select("qid", "y_gen", "y_ref", "verdict.confidence", "verdict.issue", F.lit(t).alias("rounds"), "stop"))
        if t == max_rounds:
            break
        going = state.filter("not stop") if adaptive else state
        if going.isEmpty():
            break
        ctx = update_answers(going).join(going.select("qid", F.col("y_ref").alias("before")), "qid")
        paths = update_paths(p0, going, n_neutral=n_neutral).drop("tier", "place")
    return out


def cut(rounds: DataFrame, *, max_rounds: int = 3, adaptive: bool = True) -> DataFrame:
    """The rows that run() gives, out of a trace of at least max_rounds (at least one) rounds."""
    last = (F.col("rounds") == 0) | (F.col("rounds") == max_rounds)
    rows = rounds.filter(F.col("rounds") <= max_rounds)
    if not adaptive:
        return rows.filter(last).drop("stop")
    first = rows.filter(last | F.col("stop")).groupBy("qid").agg(F.min("rounds").alias("rounds"))
    return rows.join(first, ["qid", "rounds"]).select("qid", "y_gen", "y_ref", "confidence", "issue", "rounds")


def prompt(q: DataFrame, paths: DataFrame, gen: DataFrame) -> DataFrame:
    """qid, prompt: what a language model would be sent to judge the answers."""
    shown = paths.groupBy("qid").agg(F.concat_ws("\n", F.transform(F.array_sort(F.collect_list(F.struct("rank", "path_key"))), lambda x: x["path_key"])).alias("shown"))
    rows = q.join(shown, "qid", "left").join(gen, "qid", "left")
    ask = "Judge the answers and reply with one JSON object: confidence (1 to 3), issue, retained, forbidden, prioritized, supplementary, dropped, summary."
    return rows.select("qid", F.concat_ws("\n", F.concat(F.lit("Question: "), "text"), F.lit("Paths:"), "shown", F.concat(F.lit("Answers: "), F.concat_ws(", ", "y_gen")), F.lit(ask)).alias("prompt"))


def parse_reply(reply: Column) -> Column:
    """The verdict in a reply; what is no such object is neutral at the lowest confidence."""
    got = F.from_json(reply, VERDICT, {"mode": "PERMISSIVE"})
    fine = got.isNotNull() & got["confidence"].between(1, 3)
    arr = lambda n: F.when(fine, F.coalesce(got[n], _empty())).otherwise(_empty()).alias(n)
    return F.struct(
        F.when(fine, got["confidence"]).otherwise(1).alias("confidence"), F.when(fine, F.coalesce(got["issue"], F.lit("none"))).otherwise(F.lit("unreadable")).alias("issue"),
        arr("retained"), arr("forbidden"), arr("prioritized"), arr("supplementary"), arr("dropped"), F.when(fine, F.coalesce(got["summary"], F.lit(""))).otherwise(F.lit("")).alias("summary"),
    )


@dataclass(frozen=True)
class ReplayRefiner:
    """Recorded replies (prompt_hash, reply), joined by the hash of the prompt; missing ones are
    neutral verdicts."""

    replies: DataFrame
    facts: DataFrame

    def judge(self, q: DataFrame, p0: DataFrame, gen: DataFrame, etypes: DataFrame | None = None) -> DataFrame:
        asked = prompt(q, select_paths(p0, gen), gen).join(gen.select("qid"), "qid", "left_semi").withColumn("prompt_hash", F.sha2("prompt", 256))
        return asked.join(self.replies, "prompt_hash", "left").select("qid", parse_reply(F.col("reply")).cast(VERDICT).alias("verdict"))


def pick_rounds(metrics: DataFrame) -> DataFrame:
    """One row: the number of rounds with the best dev F1; of equals the smallest."""
    return metrics.groupBy().agg(F.max(F.struct("f1", (-F.col("t")).alias("t"))).alias("best")).select((-F.col("best.t")).alias("rounds"), F.col("best.f1").alias("f1"))
