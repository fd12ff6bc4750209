"""Chat formatting by rotation of perspective, in DataFrame functions only.

For every participant the dialogue is written with that speaker as the assistant and all others as
named users. A dialogue is written in pieces of bounded length, so that no conversation, however
long, has to fit one task or one value; the pieces in order are the whole dialogue.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kgtrail.llm.common import stored, table

#: Turns of a piece at most.
PIECE = 64
#: Roles that speak to all and take no perspective.
SYSTEM = ("system",)
END = "<|end|>\n"


def _safe(c: Column) -> Column:
    """Text that holds no opening of a mark."""
    return F.regexp_replace(c, r"<\|", "< |")


def _safe_name(c: Column) -> Column:
    """A name that can neither open nor close a mark nor end its line."""
    return F.regexp_replace(F.regexp_replace(_safe(c), r"\|>", "| >"), r"[\r\n]", " ")


def _ranked(rows: DataFrame) -> DataFrame:
    """rows with nth, counted from 1 in each (conv_id, piece) by (turn, who, md5 of said).

    Turns without a number, or all of one number, make one piece of any size, so ranks are counted
    in ranges of the whole order and then shifted by what the ranges before hold."""
    rows = rows.withColumn("mark", F.md5("said")).withColumn("row", F.monotonically_increasing_id())
    order = [F.asc_nulls_first("conv_id"), F.col("piece"), F.asc_nulls_first("turn"), F.col("who"), F.col("mark"), F.col("row")]
    dealt = stored(rows.repartitionByRange(*order).withColumn("range", F.spark_partition_id()), "turns")
    inside = Window.partitionBy("range", "conv_id", "piece").orderBy(*order[2:])
    held = dealt.groupBy("conv_id", "piece", "range").agg(F.count("*").alias("held"))
    before = Window.partitionBy("conv_id", "piece").orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    # one row for each range that a piece reaches into: few, unless the piece is huge
    base = held.withColumn("base", F.coalesce(F.sum("held").over(before), F.lit(0))).filter("base > 0").select(F.col("conv_id").alias("c"), F.col("piece").alias("p"), F.col("range").alias("g"), "base")
    numbered = dealt.withColumn("local", F.row_number().over(inside))
    same = F.col("conv_id").eqNullSafe(F.col("c")) & (F.col("piece") == F.col("p")) & (F.col("range") == F.col("g"))
    return numbered.join(base, same, "left").withColumn("nth", F.col("local") + F.coalesce("base", F.lit(0))).drop("c", "p", "g", "base", "local", "mark", "row", "range")


def _head(speaker: Column, me: Column, system: tuple[str, ...]) -> Column:
    return F.when(speaker.isin(*system), F.lit("<|system|>\n")).when(speaker == me, F.lit("<|assistant|>\n")).otherwise(F.concat(F.lit("<|user name="), _safe_name(speaker), F.lit("|>\n")))


def rotate(turns: DataFrame, *, piece: int = PIECE, system: tuple[str, ...] = SYSTEM) -> DataFrame:
    """conv_id, speaker, piece, part, n_turns, text, mask, n_trained: each dialogue as seen by each
    participant. mask lists the spans (start:end in characters of the piece, end exclusive) that
    the speaker wrote, closing mark included; all else is context.

    Turns are ordered by (turn, role, md5 of the text), nulls first, so ties have one order and
    repeated rows are rendered as often as they occur; those without a number, or that share one,
    may be any number. A null role speaks as "unknown", a null text is empty, a null conv_id is a
    conversation of its own. A dialogue in which only system roles speak has no participant and
    gives no row, as does an empty table. "<|" is written "< |" inside texts and roles, and in
    roles "|>" is written "| >" and a line break as a space, so neither can forge a mark; `speaker`
    is the role as it was given. Other columns are ignored.
    """
    rows = turns.select(
        "conv_id",
        "turn",
        F.coalesce("role", F.lit("unknown")).alias("who"),
        _safe(F.coalesce("text", F.lit(""))).alias("said"),
    ).withColumn("piece", F.coalesce(F.floor(F.col("turn") / piece), F.lit(-1)).cast("long"))
    rows = _ranked(rows).withColumn("part", F.floor((F.col("nth") - 1) / piece).cast("long"))
    pieces = rows.groupBy("conv_id", "piece", "part").agg(F.sort_array(F.collect_list(F.struct("nth", "who", "said"))).alias("turns"))
    people = rows.filter(~F.col("who").isin(*system)).select(F.col("conv_id").alias("conv"), F.col("who").alias("speaker")).distinct()
    seen = pieces.join(people, F.col("conv_id").eqNullSafe(F.col("conv")))
    me = F.col("speaker")
    written = F.transform("turns", lambda t: F.struct((t["who"] == me).alias("own"), _head(t["who"], me, system).alias("head"), F.concat(t["said"], F.lit(END)).alias("body")))
    seen = seen.withColumn("written", written)
    spans = F.aggregate(
        "written",
        F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<string>").alias("spans"), F.lit(0).cast("long").alias("trained")),
        lambda acc, t: F.struct(
            (acc["at"] + F.length(t["head"]) + F.length(t["body"])).alias("at"),
            F.when(t["own"], F.concat(acc["spans"], F.array(F.concat_ws(":", (acc["at"] + F.length(t["head"])).cast("string"), (acc["at"] + F.length(t["head"]) + F.length(t["body"])).cast("string"))))).otherwise(acc["spans"]).alias("spans"),
            (acc["trained"] + F.when(t["own"], F.length(t["body"])).otherwise(F.lit(0))).alias("trained"),
        ),
    )
    seen = seen.withColumn("fold", spans)
    return seen.select(
        "conv_id",
        "speaker",
        "piece",
        "part",
        F.size("turns").cast("long").alias("n_turns"),
        F.array_join(F.transform("written", lambda t: F.concat(t["head"], t["body"])), "").alias("text"),
        F.array_join("fold.spans", ",").alias("mask"),
        F.col("fold.trained").alias("n_trained"),
    )


def op4_chat_views(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rotate(table(spark, sf_dir, "conversations"))


SQL = r"""
with t as (
  select conv_id, turn, coalesce(role, 'unknown') who, replace(coalesce(text, ''), '<|', '< |') said,
    cast(coalesce(floor(turn / 64.0), -1) as bigint) piece from conversations),
n as (select *, row_number() over (partition by conv_id, piece order by turn nulls first, who, md5(said)) nth from t),
p as (select distinct conv_id, who speaker from t where who <> 'system'),
w as (
  select n.conv_id, p.speaker, piece, cast((nth - 1) // 64 as bigint) part, nth, who = speaker own,
    case when who = 'system' then '<|system|>' || chr(10) when who = speaker then '<|assistant|>' || chr(10) else '<|user name=' || replace(replace(replace(replace(who, '<|', '< |'), '|>', '| >'), chr(13), ' '), chr(10), ' ') || '|>' || chr(10) end head,
    said || '<|end|>' || chr(10) body
  from n join p on n.conv_id is not distinct from p.conv_id),
o as (select *, coalesce(sum(length(head) + length(body)) over (partition by conv_id, speaker, piece, part order by nth rows between unbounded preceding and 1 preceding), 0) + length(head) pos from w)
select conv_id, speaker, piece, part, count(*) n_turns, string_agg(head || body, '' order by nth) as text,
  coalesce(string_agg(cast(cast(pos as bigint) as varchar) || ':' || cast(cast(pos + length(body) as bigint) as varchar), ',' order by nth) filter (own), '') mask,
  cast(coalesce(sum(length(body)) filter (own), 0) as bigint) n_trained
from o group by conv_id, speaker, piece, part
"""
