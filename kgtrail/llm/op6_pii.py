"""Personal data: spans found, confirmed and scored in whole texts, and their redaction."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgtrail.llm.common import only, small_batches, table
from kgtrail.llm.kernels import spans as kernel

SPANS = "doc_id long, spans array<struct<kind:string,start:long,end:long,score:double>>"
BASE = ("email", "ip", "card", "phone")
DIGEST = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_added long"


def _found(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64())]))
    for batch in batches:
        rows = [[dict(zip(("kind", "start", "end", "score"), s, strict=True)) for s in kernel.spans(t.as_py() or "")] for t in batch.column(1)]
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows, kind)], ["doc_id", "spans"])


def _digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        counts, hashes, texts, added = [[], [], [], []], [], [], []
        for t in batch.column(1):
            found = kernel.spans(t.as_py() or "")
            for k, kind in enumerate(BASE):
                counts[k].append(sum(s[0] == kind for s in found))
            hashes.append(hashlib.sha256(",".join(f"{k}:{a}:{b}" for k, a, b, _ in found if k in BASE).encode()).hexdigest())
            texts.append(",".join(f"{k}:{a}:{b}" for k, a, b, _ in found))
            added.append(sum(s[0] not in BASE for s in found))
        cols = [batch.column(0), *[pa.array(c, pa.int64()) for c in counts], pa.array(hashes, pa.string()), pa.array(texts, pa.string()), pa.array(added, pa.int64())]
        yield pa.RecordBatch.from_arrays(cols, ["doc_id", *[f"n_{k}" for k in BASE], "base_sha256", "spans", "n_added"])


def find(docs: DataFrame, *, digest: bool = False) -> DataFrame:
    """doc_id and the spans (kind, start, end in code points, score) of every row's whole text.

    Null text is empty and has none; rows that repeat a doc_id give a row each; a null doc_id is
    kept; an empty table gives no rows; other columns are ignored.
    """
    small_batches(docs.sparkSession)
    rows = only(docs, "doc_id", "text").withColumn("doc_id", F.col("doc_id").cast("long"))
    return rows.mapInArrow(_digest if digest else _found, DIGEST if digest else SPANS)


def redact(docs: DataFrame) -> DataFrame:
    """docs with the spans in `text` replaced by their kind and `n_chars`, if there, counted anew.
    All rows and columns stay; a null text stays null."""

    small_batches(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            k = batch.schema.get_field_index("text")
            texts = [None if (t := x.as_py()) is None else kernel.redacted(t, kernel.spans(t)) for x in batch.column(k)]
            yield batch.set_column(k, batch.schema.field(k), pa.array(texts, batch.schema.field(k).type))

    done = docs.mapInArrow(run, docs.schema)
    if "n_chars" in docs.columns:
        kind = docs.schema["n_chars"].dataType
        done = done.withColumn("n_chars", F.when(F.col("text").isNull(), F.col("n_chars")).otherwise(F.length("text").cast(kind)))
    return done


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find(table(spark, sf_dir, "documents"), digest=True)
