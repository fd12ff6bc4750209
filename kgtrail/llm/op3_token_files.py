"""Token files: ids of all documents in doc_id order, packed with Simple-8b into blocks."""

from __future__ import annotations

import hashlib
import json
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from kgtrail.llm.common import new_path, only, small_batches, table, worker_state
from kgtrail.llm.kernels import simple8b
from kgtrail.llm.kernels.backtrack import WHITE, byte_letters

#: A block is closed once it holds this many ids; a document is never split.
BLOCK_IDS = 1 << 16
#: One row is one block. `first` counts ids before the block in its part, `words` are 64-bit
#: little-endian Simple-8b words, `doc_ids` and `lengths` list the block's documents in order.
BLOCKS = "part int, block int, first long, n_ids long, doc_ids array<long>, lengths array<int>, words binary"


#: Runs of white space this long are cut out before the library sees them, as its pattern steps
#: back over them one by one.
LONG_BLANK = 256


class ByteEncoder:
    """A tokenizer file's vocabulary in the fast library for byte-level BPE."""

    def __init__(self, text: str):
        import tiktoken
        from public_tokenizers import PATTERN

        spec = json.loads(text)
        back = {c: b for b, c in enumerate(byte_letters())}
        self.special = {x["content"]: x["id"] for x in spec["added_tokens"]}
        ranks = {bytes(back[c] for c in t): i for t, i in spec["model"]["vocab"].items() if t not in self.special}
        self.coder = tiktoken.Encoding("blocks", pat_str=PATTERN, mergeable_ranks=ranks, special_tokens=self.special)
        self.marks = re.compile("(" + "|".join(map(re.escape, sorted(self.special, key=len, reverse=True))) + ")") if self.special else None
        self.blank = re.compile(f"[{WHITE}]{{{LONG_BLANK},}}")

    def encode(self, text: str, allowed_special: str | set = "all") -> list[int]:
        if allowed_special != "all" or not self.blank.search(text):
            return self.coder.encode(text, allowed_special=allowed_special)
        ids: list[int] = []
        for k, part in enumerate(self.marks.split(text) if self.marks else [text]):
            if k % 2:
                ids.append(self.special[part])
                continue
            at = 0
            for m in self.blank.finditer(part):
                # the last blank of a run goes with what follows, all before it are one piece
                end = m.end() if m.end() == len(part) else m.end() - 1
                ids += self.coder.encode_ordinary(part[at : m.start()])
                ids += self.coder._encode_single_piece(part[m.start() : end])
                at = end
            ids += self.coder.encode_ordinary(part[at:])
        return ids


def byte_encoder(text: str) -> ByteEncoder:
    return ByteEncoder(text)


def _writer(key: str, shared, end_id: int, block_ids: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        coder = worker_state(f"byte:{key}", lambda: byte_encoder(shared.value))
        part, block, first = TaskContext.get().partitionId(), 0, 0
        ids, docs, lengths, held = [], [], [], 0

        def close():
            words = simple8b.pack(np.concatenate(ids))
            return pa.RecordBatch.from_arrays(
                [pa.array([part], pa.int32()), pa.array([block], pa.int32()), pa.array([first], pa.int64()), pa.array([held], pa.int64()),
                 pa.array([docs], pa.list_(pa.int64())), pa.array([lengths], pa.list_(pa.int32())), pa.array([words.astype("<u8").tobytes()], pa.binary())],
                ["part", "block", "first", "n_ids", "doc_ids", "lengths", "words"],
            )

        for batch in batches:
            for doc, text in zip(batch.column(0), batch.column(1), strict=True):
                got = coder.encode(text.as_py() or "")
                got.append(end_id)
                ids.append(np.array(got, np.uint32))
                docs.append(doc.as_py())
                lengths.append(len(got))
                held += len(got)
                if held >= block_ids:
                    yield close()
                    block, first = block + 1, first + held
                    ids, docs, lengths, held = [], [], [], 0
        if docs:
            yield close()

    return run


def write_token_files(docs: DataFrame, path: str, tokenizer: str, *, end_id: int = 0, block_ids: int = BLOCK_IDS) -> None:
    """Encodes every whole text, appends end_id, and writes blocks in ascending doc_id order.

    Null text counts as empty (the end id alone); a null doc_id sorts first; rows with the same
    doc_id stay, ordered by a hash of the text; an empty table writes no block; other columns are
    ignored. Parts are ranges of (doc_id, hash, row), so part, block and place in block give the
    global order without one task ever seeing all rows, even if all share one doc_id or text.
    Blocks hold whole documents and about block_ids ids.
    """
    small_batches(docs.sparkSession)
    with open(tokenizer, encoding="utf-8") as f:
        text = f.read()
    shared = docs.sparkSession.sparkContext.broadcast(text)
    rows = only(docs, "doc_id", "text").withColumn("doc_id", F.col("doc_id").cast("long"))
    rows = rows.withColumn("mark", F.xxhash64("text")).withColumn("nth", F.monotonically_increasing_id())
    order = [F.col("doc_id").asc_nulls_first(), F.col("mark"), F.col("nth")]
    ordered = rows.repartitionByRange(*order).sortWithinPartitions(*order)
    ordered.select("doc_id", "text").mapInArrow(_writer(hashlib.sha256(text.encode()).hexdigest(), shared, end_id, block_ids), BLOCKS).write.parquet(path)


def _reader(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for row in batch.to_pylist():
            ids = simple8b.unpack(np.frombuffer(row["words"], "<u8"), row["n_ids"]).astype("<u4")
            lengths = np.array(row["lengths"], np.int64)
            to = np.cumsum(lengths)
            crc = [zlib.crc32(ids[b - n : b]) for n, b in zip(lengths.tolist(), to.tolist(), strict=True)]
            k = len(lengths)
            yield pa.RecordBatch.from_arrays(
                [pa.array(row["doc_ids"], pa.int64()), pa.array(np.full(k, row["part"], np.int32)), pa.array(row["first"] + to - lengths), pa.array(lengths), pa.array(crc, pa.int64())],
                ["doc_id", "part", "within", "n_tokens", "ids_crc32"],
            )


def read_token_files(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start (ids of all documents before), n_tokens, ids_crc32, decoded from the files.
    What is broadcast has one row per part, a number that the writer's partitioning sets."""
    blocks = spark.read.schema(BLOCKS).parquet(path)
    parts = blocks.groupBy("part").agg(F.sum("n_ids").alias("ids"))
    bases = parts.select("part", (F.sum("ids").over(Window.orderBy("part")) - F.col("ids")).alias("base"))
    docs = blocks.mapInArrow(_reader, "doc_id long, part int, within long, n_tokens long, ids_crc32 long")
    return docs.join(F.broadcast(bases), "part").select("doc_id", (F.col("base") + F.col("within")).alias("start"), "n_tokens", "ids_crc32")


def read_ids(spark: SparkSession, path: str) -> DataFrame:
    """doc_id and its ids, decoded from the files."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                ids = simple8b.unpack(np.frombuffer(row["words"], "<u8"), row["n_ids"]).astype(np.int64)
                parts = np.split(ids, np.cumsum(row["lengths"])[:-1])
                yield pa.RecordBatch.from_arrays([pa.array(row["doc_ids"], pa.int64()), pa.array(parts, pa.list_(pa.int64()))], ["doc_id", "ids"])

    return spark.read.schema(BLOCKS).parquet(path).mapInArrow(run, "doc_id long, ids array<long>")


def op3_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    from kgtrail.llm.op1_bpe import tokenizer_file

    path = new_path(spark, "token-files")
    write_token_files(table(spark, sf_dir, "documents"), path, tokenizer_file("byte_bpe_50k.json"))
    return read_token_files(spark, path)
