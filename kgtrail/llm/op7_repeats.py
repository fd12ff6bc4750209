"""Removal of every byte that lies in a 200-byte string which starts anywhere else too.

Prefix-free parsing over a cluster: texts are cut at rolling-hash triggers into phrases, which make a
dictionary with counts. All windows of a phrase that occurs twice repeat, so long repeats never have
to be compared. Phrases that agree only in their core (the bytes that all their windows share) are
gathered by core; there the suffix arrays of dictionary and parse are combined into the order of
all suffixes, in which equal windows are neighbours. Exact copies of whole texts are settled first
and count as one text from there on.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgtrail.llm.common import give_back, small_batches, stored, table
from kgtrail.llm.kernels import phrases as kernel
from kgtrail.llm.op2_decontaminate import sized

WIDTH = 200
#: Dictionary phrases whose suffixes are sorted at once, whole cores each time.
CHUNK = 6_000
#: Distinct phrases of one core beyond which its windows are dealt out and counted one by one.
HOT = 6_000
RESULT = "row long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"


def _cutter(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["core", "phrase", "row", "at", "lo", "hi"]
        for batch in batches:
            held, size = [], 0
            for row, text in zip(batch.column(0), batch.column(1), strict=True):
                raw = (text.as_py() or "").encode()
                if len(raw) < width:
                    continue
                core, phrase, at, lo, hi = kernel.cut(raw, width)
                held.append([core.view(np.int64), phrase.view(np.int64), np.full(len(at), row.as_py()), at.astype(np.int32), lo.astype(np.int16), hi.astype(np.int16)])
                size += len(at)
                if size >= 100_000:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*held, strict=True)], names)
                    held, size = [], 0
            if held:
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*held, strict=True)], names)
        held = batch = None
        give_back()  # the worker stays beside the joins that follow

    return run


def _fetcher(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, 64):
                rows = []
                for r in batch.slice(lo, 64).to_pylist():
                    raw = r["text"].encode()
                    rows += [(w["core"], w["phrase"], r["row"], w["at"], w["lo"], w["hi"], w["many"], raw[w["at"] - w["hi"] : w["at"] - w["lo"] + width]) for w in r["wanted"]]
                kinds = [pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int16(), pa.int16(), pa.bool_(), pa.binary()]
                cols = list(zip(*rows, strict=True)) or [[]] * 8
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["core", "phrase", "row", "at", "lo", "hi", "many", "bytes"])

    return run


FETCHED = "core long, phrase long, row long, at int, lo short, hi short, many boolean, bytes binary"


def _sorter(width: int, chunk: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[dict] = []

        def done(rows: list[dict]):
            runs = kernel.shared([r["bytes"] for r in rows], np.array([r["lo"] for r in rows]), np.array([r["hi"] for r in rows]), np.array([r["many"] for r in rows]), width)
            spans = [(r["row"], r["at"] - b, r["at"] - a + width) for r, x in zip(rows, runs, strict=True) if not r["many"] for a, b in x]
            return pa.RecordBatch.from_arrays([pa.array([s[k] for s in spans], pa.int64()) for k in range(3)], ["row", "start", "end"])

        for batch in batches:
            for r in batch.to_pylist():  # sorted by core
                if len(held) >= chunk and r["core"] != held[-1]["core"]:
                    yield done(held)
                    held = []
                held.append(r)
        if held:
            yield done(held)
        held = batch = r = None
        give_back()

    return run


def _windows(width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for r in batch.to_pylist():
                n = r["hi"] - r["lo"] + 1
                marks = [hashlib.blake2b(r["bytes"][k : k + width], digest_size=16).digest() for k in range(n)]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(marks, pa.binary()), pa.array(np.full(n, r["row"])), pa.array(r["at"] - r["hi"] + np.arange(n)), pa.array([r["many"]] * n)], ["mark", "row", "start", "many"]
                )

    return run


def repeated_spans(texts: DataFrame, *, width: int = WIDTH, chunk: int = CHUNK, hot: int = HOT) -> DataFrame:
    """row, start, end: stretches of the texts (row, text; rows unique, texts distinct) that are
    covered by strings of `width` bytes which start at another place as well. Stretches overlap."""
    small_batches(texts.sparkSession)
    half = (width - kernel.GRAM) // 2
    if half < kernel.GRAM:
        raise ValueError("width is too small for its triggers")
    cuts = stored(texts.mapInArrow(_cutter(width), "core long, phrase long, row long, at int, lo short, hi short"), "phrases")
    # a window can only occur again if the core of its half does
    # (written first: then both sides of the join are plain exchanges, and Spark splits a hot core)
    cores = stored(cuts.groupBy("core").agg(F.count("*").alias("k")).filter("k > 1").select("core"), "cores")
    # (joined by hash: sorts of all phrases, here or in the dictionary, fill an executor's heap)
    alive = stored(cuts.join(cores.hint("shuffle_hash"), "core", "left_semi"), "repeated-cores")
    # one place of each phrase: the four columns are taken from the same row, whichever it is
    words = alive.groupBy("core", "phrase").agg(F.count("*").alias("k"), *[F.first(c).alias(c) for c in ("row", "at", "lo", "hi")])
    words = stored(words.select("core", "phrase", (F.col("k") > 1).alias("many"), "row", "at", "lo", "hi"), "dictionary")
    # all windows of a phrase that occurs twice occur twice
    whole = alive.join(words.filter("many").select("core", "phrase").hint("shuffle_hash"), ["core", "phrase"], "left_semi")
    whole = whole.select("row", (F.col("at") - F.col("hi")).cast("long").alias("start"), (F.col("at") - F.col("lo") + width).cast("long").alias("end"))
    # phrases that share their core but are not all equal
    kinds = stored(words.groupBy("core").agg(F.count("*").alias("kinds")).filter("kinds > 1"), "mixed-cores")
    mixed = words.join(kinds, "core")
    wanted = mixed.groupBy("row").agg(F.collect_list(F.struct("core", "phrase", "at", "lo", "hi", "many")).alias("wanted"))
    wanted = stored(wanted, "wanted")
    needed = texts.join(sized(wanted.select("row")), "row", "left_semi").join(wanted, "row")
    fetched = needed.select("row", "text", "wanted").mapInArrow(_fetcher(width), FETCHED)
    hots = stored(kinds.filter(F.col("kinds") > hot).select("core"), "hot-cores")
    spans = whole
    if hots.isEmpty():
        cold = fetched
    else:
        fetched = stored(fetched, "fetched")
        cold = fetched.join(sized(hots), "core", "left_anti")
        marks = stored(fetched.join(sized(hots), "core", "left_semi").mapInArrow(_windows(width), "mark binary, row long, start long, many boolean"), "windows")
        often = marks.groupBy("mark").agg(F.count("*").alias("k"), F.max("many").alias("many")).filter("k > 1 or many").select("mark")
        spans = spans.unionByName(marks.filter("not many").join(often, "mark", "left_semi").select("row", "start", (F.col("start") + width).alias("end")))
    sorted_ = cold.repartition("core").sortWithinPartitions("core").mapInArrow(_sorter(width, chunk), "row long, start long, end long")
    return stored(spans.unionByName(sorted_), "spans")


def _remover(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        out = []
        for r in range(batch.num_rows):
            raw = (batch.column(1)[r].as_py() or "").encode()
            spans = kernel.union([(s["start"], s["end"]) for s in (batch.column(2)[r].as_py() or [])]) if batch.num_columns > 2 else []
            at, kept = 0, hashlib.sha256()
            for a, b in spans:
                kept.update(raw[at:a])
                at = b
            kept.update(raw[at:])
            out.append((batch.column(0)[r].as_py(), len(raw), sum(b - a for a, b in spans), len(spans), kept.hexdigest()))
        cols = list(zip(*out, strict=True)) or [[]] * 5
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, (pa.int64(),) * 4 + (pa.string(),), strict=True)], ["row", "n_bytes", "n_removed", "n_spans", "kept_sha256"])


def without_repeats(docs: DataFrame, *, width: int = WIDTH, **options) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 for every row of docs.

    A text is its UTF-8 bytes; null text is empty and, as any text under `width` bytes, loses
    nothing. Strings are judged on the input and never cross texts; the other place may be in the
    same text and may overlap. Rows that repeat a doc_id are rows of their own, so a repeated row
    of `width` bytes or more is removed whole, in each place. A null doc_id is kept. An empty table
    gives no rows; other columns are ignored. Phrases are equal if both their keys are, that of the
    core and that of all bytes (128 bits together); windows of mixed cores are compared by bytes.
    """
    given = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    twice = given.groupBy("doc_id").agg(F.count("*").alias("k")).filter("k > 1 or doc_id is null")
    if twice.isEmpty():  # doc_id names the row
        rows = given.select(F.col("doc_id").alias("row"), "doc_id", "text")
    else:
        rows = stored(given.withColumn("row", F.monotonically_increasing_id()), "rows")
    texts = rows.select("row", "text")
    marks = rows.select("row", F.md5(F.col("text").cast("binary")).alias("mark"), F.octet_length("text").cast("long").alias("n"))
    groups = marks.filter(F.col("n") >= width).groupBy("mark", "n").agg(F.count("*").alias("k"), F.min("row").alias("rep")).filter("k > 1")
    copies = stored(marks.join(groups, ["mark", "n"]).select("row", "n", "rep"), "copies")
    spans = repeated_spans(texts.join(sized(copies.filter("row <> rep").select("row")), "row", "left_anti"), width=width, **options)
    per_row = spans.join(sized(copies.select("row")), "row", "left_anti").groupBy("row").agg(F.collect_list(F.struct("start", "end")).alias("spans"))
    per_row = stored(per_row, "row-spans")
    gone = copies.select("row", F.col("n").alias("n_bytes"), F.col("n").alias("n_removed"), F.lit(1).cast("long").alias("n_spans"), F.sha2(F.lit(""), 256).alias("kept_sha256"))
    touched = sized(per_row.select("row").unionByName(copies.select("row")))
    plain = texts.join(touched, "row", "left_anti").mapInArrow(_remover, RESULT)
    some = texts.join(sized(per_row.select("row")), "row", "left_semi").join(per_row, "row").select("row", "text", "spans").mapInArrow(_remover, RESULT)
    done = gone.unionByName(plain).unionByName(some)
    if twice.isEmpty():
        return done.withColumnRenamed("row", "doc_id")
    return done.join(rows.select("row", "doc_id"), "row").select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")


def op7_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return without_repeats(table(spark, sf_dir, "documents"))
