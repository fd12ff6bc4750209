"""Near-duplicate texts: dart signatures, banded candidates, exact similarity, components.

Texts with the same words are one from the start. Candidates share a band. Members of a band's
bucket are first compared with its most central member, then with the next; for most buckets that
joins all that belongs together. What is left are buckets with several components: in small ones
the pairs across components are compared, large ones are compared block by block inside tasks,
which hand on no more links than members. So no link within a bucket is lost, and no list of all
pairs of a large bucket is ever made.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgtrail.llm.common import small_batches, stored, table, worker_state
from kgtrail.llm.components import components
from kgtrail.llm.kernels.darts import Darts
from kgtrail.llm.op2_decontaminate import sized

LEAST = 0.8
#: Bands and coordinates in each; a pair of similarity 0.8 shares no band once in 50,000 times.
BANDS, ROWS = 36, 6
#: Rounds in which a bucket's members are compared with one hub.
HUB_ROUNDS = 2
#: Members up to which a bucket's pairs are listed, and those in a block of a larger bucket.
SMALL, BLOCK = 24, 1024
SIGNED = "row long, doc_id long, mark long, digest binary, bands array<long>, n int, items array<long>"


def _signer(bands: int, rows: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        darts = worker_state(f"darts:{bands}:{rows}", lambda: Darts(bands * rows, rows))
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part = batch.slice(lo, 512)
                got = [darts.describe(t.as_py() or "") for t in part.column(3)]
                yield pa.RecordBatch.from_arrays(
                    [*part.columns[:3], pa.array([d for d, _, _ in got], pa.binary()), pa.array([b for _, b, _ in got], pa.list_(pa.int64())), pa.array([len(i) for _, _, i in got], pa.int32()), pa.array([i for _, _, i in got], pa.list_(pa.int64()))],
                    ["row", "doc_id", "mark", "digest", "bands", "n", "items"],
                )

    return run


def signed(docs: DataFrame, bands: int, rows: int) -> DataFrame:
    small_batches(docs.sparkSession)
    given = docs.select(F.monotonically_increasing_id().alias("row"), F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("mark"), "text")
    return stored(given.mapInArrow(_signer(bands, rows), SIGNED), "signatures")


def verified(pairs: DataFrame, texts: DataFrame, least: float) -> DataFrame:
    """The pairs (a, b) whose shingle multisets have a Jaccard similarity of at least `least`.
    Only texts that occur in a pair are joined, each by its own row."""
    needed = pairs.select(F.explode(F.array("a", "b")).alias("row")).distinct()
    sets = texts.select("row", "n", "items").join(sized(needed), "row", "left_semi")
    left = sets.select(F.col("row").alias("a"), F.col("n").alias("na"), F.col("items").alias("ia"))
    right = sets.select(F.col("row").alias("b"), F.col("n").alias("nb"), F.col("items").alias("ib"))
    both = pairs.join(right, "b").join(left, "a").filter(F.least("na", "nb") >= least * F.greatest("na", "nb"))
    common = F.size(F.array_intersect("ia", "ib"))
    return both.filter(common >= least * (F.col("na") + F.col("nb") - common)).select("a", "b")


def _linker(least: float):
    import pandas as pd

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        """Links between different components among the rows of one or two blocks."""
        m = len(pdf)
        n = pdf["n"].to_numpy(np.float64)
        who = np.repeat(np.arange(m), pdf["n"].to_numpy())
        _, item, times = np.unique(np.concatenate(pdf["items"].to_numpy()), return_inverse=True, return_counts=True)
        shared = np.flatnonzero(times > 1)
        place = np.full(len(times), -1)
        place[shared] = np.arange(len(shared))
        item = place[item]
        who, item = who[item >= 0], item[item >= 0]
        common = np.zeros((m, m), np.float32)
        for lo in range(0, len(shared), 4096):
            some = (item >= lo) & (item < lo + 4096)
            table = np.zeros((m, min(4096, len(shared) - lo)), np.float32)
            table[who[some], item[some] - lo] = 1
            common += table @ table.T
        common = common.astype(np.float64)
        comp = pdf["component"].to_numpy()
        alike = (common >= least * (n[:, None] + n[None, :] - common)) & (comp[:, None] != comp[None, :])
        rows, left, links = pdf["row"].to_numpy(), np.ones(m, bool), []
        for start in range(m):
            todo = [start] if left[start] else []
            left[start] = False
            while todo:
                k = todo.pop()
                found = np.flatnonzero(alike[k] & left)
                left[found] = False
                links += [(rows[k], rows[j]) for j in found]
                todo += found.tolist()
        return pd.DataFrame(links, columns=["a", "b"], dtype=np.int64)

    return run


def linked_in_blocks(members: DataFrame, texts: DataFrame, least: float) -> DataFrame:
    """Links (a, b) that join what all links across components in the buckets join. Blocks are made
    by a hash of the row, so each holds about BLOCK members, and each two blocks meet once."""
    sizes = _per_bucket(members.groupBy("bucket").agg(F.ceil(F.count("*") / BLOCK).cast("int").alias("blocks")))
    placed = members.join(sizes, "bucket").withColumn("b", F.pmod(F.xxhash64("row"), F.col("blocks")).cast("int"))
    placed = placed.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    placed = placed.select("bucket", "row", "component", F.least("b", "other").alias("i"), F.greatest("b", "other").alias("j"))
    needed = texts.select("row", "n", "items").join(sized(members.select("row").distinct()), "row", "left_semi")
    return placed.join(needed, "row").groupBy("bucket", "i", "j").applyInPandas(_linker(least), "a long, b long")


def _per_bucket(rows: DataFrame) -> DataFrame:
    """A table with a row for each bucket, written before it is joined: it is broadcast while it is
    small, and beyond that both sides of the join are plain exchanges, so that Spark splits the
    rows of a bucket that holds very many."""
    return sized(stored(rows, "per-bucket"))


def near_copies(docs: DataFrame, *, least: float = LEAST, bands: int = BANDS, rows: int = ROWS) -> DataFrame:
    """doc_id, mark (hash of the text), class_id, kept: one row for each row of docs.

    Two texts link if the multisets of their five-word shingles (of all their words, if fewer) have
    a Jaccard similarity of at least `least`; classes are the components, named by their smallest
    doc_id, whose row is kept. Texts with the same words always link. Null text and text without
    words link with nothing. Rows that repeat a doc_id are rows of their own; a null doc_id comes
    after all others when a class is named. An empty table gives no rows; other columns are ignored.
    Similarities are checked on 64-bit hashes of the shingles' occurrences.
    """
    texts = signed(docs, bands, rows)
    names = texts.select("row", "doc_id", "mark", "digest")
    same = names.filter("digest is not null").groupBy("digest").agg(F.min("row").alias("rep"))
    first = stored(names.join(same, "digest", "left").select("row", "doc_id", "mark", F.coalesce("rep", "row").alias("rep")), "copies")
    own = texts.join(first.filter("row = rep").select("row"), "row", "left_semi")
    members = own.select("row", F.explode("bands").alias("bucket"))
    shared = _per_bucket(members.groupBy("bucket").agg(F.count("*").alias("k")).filter("k > 1"))
    members = stored(members.join(shared, "bucket"), "buckets")
    central = members.groupBy("row").agg(F.sum("k").alias("weight"))
    members = stored(members.join(central, "row").select("bucket", "row", "weight", F.col("row").alias("component"), F.lit(False).alias("was_hub")), "buckets")
    links, tested, found = None, None, None

    def meet(pairs: DataFrame) -> None:
        """Verifies new pairs and settles the components."""
        nonlocal tested
        pairs = pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()
        pairs = stored(pairs if tested is None else pairs.join(tested, ["a", "b"], "left_anti"), "candidates")
        tested = pairs if tested is None else tested.unionByName(pairs)
        settle(stored(verified(pairs, texts, least), "links"))

    def settle(new: DataFrame) -> None:
        nonlocal links, found
        if not new.isEmpty():
            links = new if links is None else links.unionByName(new)
            found = stored(components(links), "text-components")

    def still_open(members: DataFrame) -> DataFrame:
        """Members of buckets with several components, under their present component."""
        if found is not None:
            members = members.drop("component").join(found.withColumnRenamed("id", "row"), "row", "left").withColumn("component", F.coalesce("component", "row"))
        several = members.groupBy("bucket").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).filter("lo < hi")
        return stored(members.join(_per_bucket(several.select("bucket")), "bucket", "left_semi"), "buckets")

    for _ in range(HUB_ROUNDS):
        hubs = members.filter("not was_hub").groupBy("bucket").agg(F.max(F.struct("weight", (-F.col("row")).alias("row"), "component")).alias("h"))
        hubs = _per_bucket(hubs.select("bucket", (-F.col("h.row")).alias("a"), F.col("h.component").alias("ca")))
        both = members.join(hubs, "bucket")
        meet(both.filter("component <> ca and not was_hub").select("a", F.col("row").alias("b")))
        members = still_open(both.withColumn("was_hub", F.col("was_hub") | (F.col("row") == F.col("a"))).drop("a", "ca"))
        if members.isEmpty():
            break
    rest = members.join(_per_bucket(members.groupBy("bucket").agg(F.count("*").alias("k")).filter("k > 1")), "bucket")
    few = rest.filter(F.col("k") <= SMALL).select("bucket", "row", "component")
    one = few.select("bucket", F.col("row").alias("a"), F.col("component").alias("ca"))
    meet(one.join(few, "bucket").filter("a < row and component <> ca").select("a", F.col("row").alias("b")))
    large = rest.filter(F.col("k") > SMALL).drop("k")
    if not large.isEmpty():
        settle(stored(linked_in_blocks(still_open(large).select("bucket", "row", "component"), texts, least), "links"))
    done = first
    if found is not None:
        done = done.join(found.withColumnRenamed("id", "rep"), "rep", "left").withColumn("class", F.coalesce("component", "rep"))
    else:
        done = done.withColumn("class", F.col("rep"))
    heads = done.groupBy("class").agg(F.min(F.struct(F.col("doc_id").isNull().alias("no"), "doc_id", "row")).alias("head"))
    return done.join(heads, "class").select("doc_id", "mark", F.col("head.doc_id").alias("class_id"), (F.col("row") == F.col("head.row")).alias("kept"))


def without_near_copies(docs: DataFrame, **options) -> DataFrame:
    """docs with one row of each class, all columns kept."""
    judged = stored(near_copies(docs, **options), "judged")
    keys = judged.groupBy("doc_id", "mark").agg(F.sum(F.col("kept").cast("int")).alias("kept"), F.count("*").alias("n"))
    keyed = docs.withColumn("_id", F.col("doc_id").cast("long")).withColumn("_mark", F.xxhash64("text"))
    match = F.col("_id").eqNullSafe(F.col("k_id")) & (F.col("_mark") == F.col("k_mark"))
    dropped = keys.filter("kept = 0").select(F.col("doc_id").alias("k_id"), F.col("mark").alias("k_mark"))
    kept = keyed.join(sized(dropped), match, "left_anti")
    again = keys.filter("kept > 0 and kept < n").select(F.col("doc_id").alias("k_id"), F.col("mark").alias("k_mark"))
    if not again.isEmpty():  # rows that repeat both doc_id and text; those without words are all kept
        again = sized(again)
        kept = kept.join(again, match, "left_anti").unionByName(kept.join(again, match, "left_semi").dropDuplicates(["_id", "_mark"]))
    return kept.select(*docs.columns)


def op8_near_copies(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_copies(table(spark, sf_dir, "documents")).select("doc_id", "class_id", "kept")
