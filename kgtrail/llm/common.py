"""What all operators of the subpackage share: tables, the shared folder, worker-side state."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import re
import sys
import tempfile
import types
import uuid
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A word: digits, lower-case ASCII letters and every non-ASCII character (after A-Z are lowered).
WORD = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"
#: The same words found before lowering.
WORD_ANY_CASE = r"[^\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
#: What stands between them.
BETWEEN_WORDS = r"[\x00-\x2F\x3A-\x40\x5B-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share (spark.checkpoint.dir); a local one only where
    the session names none, as in tests on one machine."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a folder that all executors share")
    store = sys.modules[__name__].__dict__
    if "_local_dir" not in store:
        store["_local_dir"] = "file://" + tempfile.mkdtemp(prefix="kgtrail-")
    return store["_local_dir"]


def new_path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/kgtrail/{name}-{uuid.uuid4().hex}"


def stored(df: DataFrame, name: str) -> DataFrame:
    """df written to the shared folder and read again: cuts the lineage, and a lost executor costs
    no recomputation of what was written. A query's result is read from such tables after the call
    returns, so they stay until the owner of the session clears the folder's `kgtrail` part."""
    path = new_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def ascii_lower(c: Column) -> Column:
    return F.translate(c, UPPER, LOWER)


def worker_state(key: str, make):
    """State that a reused Python worker keeps between tasks; only the latest is kept, and what it
    replaces is given back, so that the memory of a worker does not add up over a pipeline."""
    store = sys.modules.setdefault("_kgtrail_worker_state", types.ModuleType("_kgtrail_worker_state")).__dict__
    if store.get("key") != key:
        store.pop("value", None)
        give_back()
        store["value"], store["key"] = make(), key
    return store["value"]


def give_back() -> None:
    """Returns freed memory of this process to the machine, where its C library can."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def executors_give_back(spark: SparkSession, *, workers: bool = True) -> None:
    """Lets every idle core drop what its Python worker kept and its JVM shrink a heap that the stage
    before has grown: workers and heaps share the memory of an executor, and neither does so by itself.
    Without workers only the heaps shrink, and no Python runs. A task for each core; one that another
    executor takes instead costs memory, never rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            worker_state("", lambda: None)
            give_back()
            yield batch

    n = spark.sparkContext.defaultParallelism
    idle = spark.range(0, n, 1, n)
    if workers:
        idle = idle.mapInArrow(run, "id long")
    idle.select(F.java_method(F.lit("java.lang.System"), F.lit("gc"))).write.format("noop").mode("overwrite").save()


#: Rows and bytes that go to a Python worker at once; a batch is held whole.
BATCH_ROWS, BATCH_BYTES = 1_000, 16 << 20


def small_batches(spark: SparkSession) -> None:
    """Keeps Arrow batches at BATCH_ROWS rows and about BATCH_BYTES or under. Plans read these two
    settings when they run, after the operator has returned, so they stay set in the session."""
    for key, most in (("maxRecordsPerBatch", BATCH_ROWS), ("maxBytesPerBatch", BATCH_BYTES)):
        name = f"spark.sql.execution.arrow.{key}"
        now = re.match(r"([0-9]+)b?$", spark.conf.get(name, None) or "")
        if not now or not 0 < int(now[1]) <= most:
            spark.conf.set(name, str(most))


def only(df: DataFrame, *names: str) -> DataFrame:
    """The named columns; extra columns are left out, missing ones are an error."""
    return df.select(*[df[n] for n in names])
