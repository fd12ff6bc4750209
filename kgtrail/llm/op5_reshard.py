"""Resharding: a minimum-cost flow decides which rows leave their shard, then files are rewritten.

Shards are folders of files. Law `rows`: the counts of the new shards differ by one at most. Among
all ways to reach that, the plan moves the fewest bytes: each shard that must give rows gives its
smallest ones, and which shards keep one row more is settled by the flow. A row is named by its file
and its place in it, so neither the plan nor the rewriting shuffles a text: only shards that lose
rows are written anew, those that gain get further files, all others keep theirs.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kgtrail.llm.common import new_path, table
from kgtrail.llm.kernels.flow import Flow
from kgtrail.llm.op2_decontaminate import sized

OLD_SHARDS, NEW_SHARDS = 16, 24
ROWS = "doc_id long, text string, size long, shard int"
#: Ranges that a range of sizes is split into when the place of a cut in it is looked for.
PARTS = 1024
#: Files up to which their first slots are broadcast (about 100 bytes each).
MANY_FILES = 2_000_000


@dataclass(frozen=True)
class Block:
    """Rows of shard `old` whose size is in lo <= size < hi."""

    old: int
    lo: int
    hi: int
    rows: int
    bytes: int


@dataclass
class Plan:
    """segments: (block, first, last, shard): of the block's rows, by file and place, those from
    first to last (counted from 1) go to `shard`. transfers: (old, shard, rows). bytes: what moves."""

    segments: list[tuple[Block, int, int, int]] = field(default_factory=list)
    transfers: list[tuple[int, int, int]] = field(default_factory=list)
    bytes: int = 0

    @property
    def losing(self) -> set[int]:
        """Shards that are written anew, or go."""
        return {a for a, *_ in self.transfers}

    @property
    def affected(self) -> set[int]:
        """Shards that are written anew or get further files."""
        return {x for a, b, *_ in self.transfers for x in (a, b)}


def lay_out(docs: DataFrame, path: str, shards: int) -> None:
    """Writes docs as the present shards: a row goes by a hash of its doc_id."""
    size = F.coalesce(F.octet_length("text"), F.lit(0)).cast("long") + 8
    shard = F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))) % shards
    docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", size.alias("size"), shard.cast("int").alias("shard")).write.partitionBy("shard").parquet(path)


def rows_of(spark: SparkSession, path: str, *columns: str) -> DataFrame:
    """The given columns with shard, file and at: the place in the file, from 0."""
    return spark.read.schema(ROWS).parquet(path).select(*columns, "shard", F.col("_metadata.file_name").alias("file"), F.col("_metadata.row_index").alias("at"))


def _blocks(rows: DataFrame, lo: Column, hi: Column) -> list[Block]:
    """A row for each shard and range of sizes: bounded, however many rows there are."""
    got = rows.groupBy("shard", lo.alias("lo"), hi.alias("hi")).agg(F.count("*").alias("n"), F.sum("size").alias("bytes")).collect()
    return sorted((Block(r["shard"], r["lo"], r["hi"], r["n"], r["bytes"]) for r in got), key=lambda b: (b.old, b.lo))


def _cuts(blocks: list[Block], new_shards: int) -> dict[int, tuple[int, int]]:
    """By shard: the least and the greatest number of rows it gives."""
    total = sum(b.rows for b in blocks)
    low, high = total // new_shards, -(-total // new_shards)
    held: dict[int, int] = {}
    for b in blocks:
        held[b.old] = held.get(b.old, 0) + b.rows
    return {j: (n, n) if j >= new_shards else (max(0, n - high), max(0, n - low)) for j, n in held.items()}


def _open(blocks: list[Block], cuts: dict[int, tuple[int, int]]) -> list[Block]:
    """The blocks that some cut may split."""
    found, before = [], dict.fromkeys(cuts, 0)
    for b in blocks:
        least, most = cuts[b.old]
        if before[b.old] < most and before[b.old] + b.rows > least:
            found.append(b)
        before[b.old] += b.rows
    return found


def measure(spark: SparkSession, path: str, new_shards: int) -> list[Block]:
    """Blocks in ascending size: within each shard one that surely leaves, one that surely stays,
    and between them the sizes at the cut, each a block of its own. Only sizes are read; a range
    that a cut may split is split PARTS times until it is one size."""
    rows = rows_of(spark, path, "size")
    least = F.pow(F.lit(2.0), F.floor(F.log2("size"))).cast("long")
    blocks = _blocks(rows, least, 2 * least)
    cuts = _cuts(blocks, new_shards)
    while wide := [b for b in _open(blocks, cuts) if b.hi - b.lo > 1]:
        ranges = spark.createDataFrame([(b.old, b.lo, b.hi, -(-(b.hi - b.lo) // PARTS)) for b in wide], "shard int, from long, to long, step long")
        inside = rows.join(F.broadcast(ranges), "shard").filter("size >= from and size < to")
        lo = F.col("from") + F.floor((F.col("size") - F.col("from")) / F.col("step")) * F.col("step")
        split = _blocks(inside.withColumn("lo", lo), F.col("lo"), F.least(F.col("lo") + F.col("step"), F.col("to")))
        blocks = sorted([b for b in blocks if b not in set(wide)] + split, key=lambda b: (b.old, b.lo))
    merged: list[tuple[str, Block]] = []
    before = dict.fromkeys(cuts, 0)
    for b in blocks:
        least, most = cuts[b.old]
        side = "leaves" if before[b.old] + b.rows <= least else "stays" if before[b.old] >= most else "cut"
        before[b.old] += b.rows
        was, last = merged[-1] if merged else ("", None)
        if last and last.old == b.old and was == side != "cut":
            merged[-1] = (side, Block(b.old, last.lo, b.hi, last.rows + b.rows, last.bytes + b.bytes))
        else:
            merged.append((side, b))
    return [b for _, b in merged]


def solve(blocks: list[Block], new_shards: int) -> Plan:
    """blocks as measure() gives them, or any whose rows are alike in size wherever a cut falls."""
    total = sum(b.rows for b in blocks)
    olds = 1 + max((b.old for b in blocks), default=-1)
    source, hub, sink, old_at = 0, 1, 2, 3
    new_at = old_at + olds
    net = Flow(new_at + new_shards)
    leaving = {}
    for i in range(olds):
        mine = [b for b in blocks if b.old == i]
        net.arc(source, old_at + i, sum(b.rows for b in mine), 0)
        if i < new_shards:
            net.arc(old_at + i, new_at + i, total, 0)
        leaving |= {b: net.arc(old_at + i, hub, b.rows, b.bytes // b.rows) for b in mine}
    arriving = [net.arc(hub, new_at + j, total, 0) for j in range(new_shards)]
    floor, must = total // new_shards, 1 << 50
    for j in range(new_shards):
        net.arc(new_at + j, sink, floor, -must)
        if total % new_shards:
            net.arc(new_at + j, sink, 1, 0)
    if net.run(source, sink, total) != total:
        raise ValueError("the capacities do not hold all rows")
    done, moved = Plan(), {}
    take = [[j, net.used(k)] for j, k in enumerate(arriving) if net.used(k)]
    for b, k in leaving.items():  # shard by shard, so each gives to few others
        at, out = 0, net.used(k)
        done.bytes += b.bytes * out // b.rows
        while at < out:
            # rows never return to the shard they leave: that would cost more than staying
            target = next(t for t in take if t[1])
            n = min(out - at, target[1])
            done.segments.append((b, at + 1, at + n, target[0]))
            moved[(b.old, target[0])] = moved.get((b.old, target[0]), 0) + n
            target[1] -= n
            at += n
    done.transfers = [(a, b, n) for (a, b), n in sorted(moved.items())]
    return done


def _bounds(spark: SparkSession, path: str, done: Plan) -> dict[tuple[Block, int], tuple[str, int]]:
    """(block, rank) -> (file, place) for every rank at which a segment ends inside its block: the
    file by counts of rows for each file, the place by the rows of that file alone."""
    inner = [(b, last) for b, _, last, _ in done.segments if last < b.rows]
    if not inner:
        return {}
    asked = spark.createDataFrame([(k, b.old, b.lo, b.hi, rank) for k, (b, rank) in enumerate(inner)], "k int, shard int, lo long, hi long, rank long")
    rows = rows_of(spark, path, "size").join(F.broadcast(asked), "shard").filter("size >= lo and size < hi")
    files = rows.groupBy("k", "rank", "file").agg(F.count("*").alias("n"))
    before = F.sum("n").over(Window.partitionBy("k").orderBy("file")) - F.col("n")
    there = files.withColumn("before", before).filter("before < rank and before + n >= rank").select("k", F.col("file").alias("f"), "before")
    found = rows.join(F.broadcast(there), "k").filter("file = f")
    nth = found.withColumn("nth", F.row_number().over(Window.partitionBy("k").orderBy("at")) + F.col("before")).filter("nth = rank")
    return {inner[r["k"]]: (r["file"], r["at"]) for r in nth.select("k", "file", "at").collect()}


def rewrite(spark: SparkSession, path: str, done: Plan, to: str) -> None:
    """Writes the rows of every shard that loses some under `to`, by their new shard, then removes
    that shard's files under `path`. Files of other shards are not touched. No row is shuffled."""
    if not done.transfers:
        return
    ends = _bounds(spark, path, done)
    segments = []
    for b, first, last, shard in done.segments:
        f0, p0 = ends[(b, first - 1)] if first > 1 else (None, None)
        f1, p1 = ends[(b, last)] if last < b.rows else (None, None)
        segments.append((b.old, b.lo, b.hi, f0, p0, f1, p1, shard))
    # bounded by the shards: a few for each old and each new one
    table_ = spark.createDataFrame(segments, "old int, lo long, hi long, f0 string, p0 long, f1 string, p1 long, to int")
    after = F.col("f0").isNull() | (F.col("file") > F.col("f0")) | ((F.col("file") == F.col("f0")) & (F.col("at") > F.col("p0")))
    until = F.col("f1").isNull() | (F.col("file") < F.col("f1")) | ((F.col("file") == F.col("f1")) & (F.col("at") <= F.col("p1")))
    mine = (F.col("shard") == F.col("old")) & (F.col("size") >= F.col("lo")) & (F.col("size") < F.col("hi")) & after & until
    rows = rows_of(spark, path, "doc_id", "text", "size").filter(F.col("shard").isin(sorted(done.losing)))
    placed = rows.join(F.broadcast(table_), mine, "left").select("doc_id", "text", "size", F.coalesce("to", "shard").alias("shard"))
    placed.write.partitionBy("shard").parquet(to)
    hadoop = spark._jvm.org.apache.hadoop.fs.Path
    for shard in sorted(done.losing):
        gone = hadoop(f"{path}/shard={shard}")
        gone.getFileSystem(spark._jsc.hadoopConfiguration()).delete(gone, True)


def read_shards(spark: SparkSession, paths: list[str]) -> DataFrame:
    """doc_id, text, size, shard, slot from the files under the paths. Slots are counted through a
    shard's files in order, so a file that stays keeps its bytes whatever comes beside it."""
    rows = None
    for k, path in enumerate(paths):
        part = rows_of(spark, path, "doc_id", "text", "size").withColumn("file", F.concat(F.lit(f"{k}/"), "file"))
        rows = part if rows is None else rows.unionByName(part)
    files = rows.groupBy("shard", "file").agg(F.count("*").alias("n"))
    base = files.select("shard", "file", (F.sum("n").over(Window.partitionBy("shard").orderBy("file")) - F.col("n")).alias("base"))
    return rows.join(sized(base, MANY_FILES), ["shard", "file"]).select("doc_id", "text", "size", "shard", (F.col("base") + F.col("at")).alias("slot"))


def reshard(docs: DataFrame, *, old_shards: int = OLD_SHARDS, new_shards: int = NEW_SHARDS) -> tuple[DataFrame, Plan]:
    """docs laid out as old_shards, brought to new_shards, read from the files; and the plan.

    Null text has size 8 and stays null; rows with a null doc_id go with hash 0; rows that repeat a
    doc_id, or all of it, are rows of their own and take different slots; an empty table gives no
    rows; other columns are left behind.
    """
    spark, path = docs.sparkSession, new_path(docs.sparkSession, "shards")
    lay_out(docs, f"{path}/old", old_shards)
    done = solve(measure(spark, f"{path}/old", new_shards), new_shards)
    rewrite(spark, f"{path}/old", done, f"{path}/new")
    left = [f"{path}/old"] + [f"{path}/new"] * bool(done.transfers)
    return read_shards(spark, left), done


def op5_reshard(spark: SparkSession, sf_dir: str) -> DataFrame:
    shards, _ = reshard(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return shards.select(
        "doc_id",
        "size",
        F.crc32(F.coalesce("text", F.lit(""))).alias("text_crc32"),
        F.lit("rows").alias("law"),
        "shard",
        "slot",
        F.lit(None).cast("int").alias("grown_shard"),
    )
