"""BPE encoding and decoding with a backtracking encoder and an offset-table decoder."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgtrail.llm.common import only, small_batches, table, worker_state
from kgtrail.llm.kernels.backtrack import WordBpe

#: Documents of a batch that are held at once with their ids.
SLICE = 256


def tokenizer_file(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


SCHEMAS = {
    "texts": "doc_id long, ids array<int>, decoded string",
    "digest": "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string",
    "ids": "doc_id long, n_tokens long, ids array<int>, decoded_sha256 string",
}


def _mapper(key: str, shared, form: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = worker_state(f"bpe:{key}", lambda: WordBpe(shared.value))
        digest = lambda b: hashlib.sha256(b).hexdigest()
        for batch in batches:
            for lo in range(0, batch.num_rows, SLICE):
                part = batch.slice(lo, SLICE)
                ids = [coder.encode(t.as_py() or "") for t in part.column(1)]
                lists = lambda ids=ids: pa.array(ids, pa.list_(pa.int32()))
                counts = pa.array([len(i) for i in ids], pa.int64())
                if form == "texts":
                    cols = {"ids": lists(), "decoded": pa.array([coder.decode(i).decode() for i in ids], pa.string())}
                else:
                    first = {"ids_sha256": pa.array([digest(coder.number_table.joined(i)) for i in ids], pa.string())} if form == "digest" else {"ids": lists()}
                    cols = {"n_tokens": counts} | first | {"decoded_sha256": pa.array([digest(coder.decode(i)) for i in ids], pa.string())}
                yield pa.RecordBatch.from_arrays([part.column(0), *cols.values()], ["doc_id", *cols])

    return run


def encode_documents(docs: DataFrame, path: str, *, form: str = "texts") -> DataFrame:
    """Every row's whole text encoded and decoded with the tokenizer file at `path`.

    form: "texts" gives doc_id, ids, decoded; "ids" and "digest" give counts and hashes, the former
    with the ids. Null text counts as empty (no ids, empty decoded text); repeated rows give
    repeated results; rows with a null doc_id are kept; an empty table gives no rows; other columns
    are ignored.
    The file is read on the driver and sent to each worker once: executors need no such file, and
    its size does not grow with the documents.
    """
    small_batches(docs.sparkSession)
    with open(path, encoding="utf-8") as f:
        text = f.read()
    shared = docs.sparkSession.sparkContext.broadcast(text)
    key = hashlib.sha256(text.encode()).hexdigest()
    rows = only(docs, "doc_id", "text").withColumn("doc_id", F.col("doc_id").cast("long"))
    return rows.mapInArrow(_mapper(key, shared, form), SCHEMAS[form])


def op1_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_documents(table(spark, sf_dir, "documents"), tokenizer_file(), form="digest")
