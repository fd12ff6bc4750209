"""Toxicity: a lexicon learned from labels, misspellings caught by a Levenshtein automaton, and
hits in reported speech told from abuse by a window of words around them."""

from __future__ import annotations

import hashlib
import json
import logging
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgtrail.llm.common import only, small_batches, stored, table, worker_state
from kgtrail.llm.kernels.lexicon import Lexicon, fit
from kgtrail.llm.op2_decontaminate import sized

#: Labelled rows of each class that the lexicon is learned from, in expectation.
SAMPLE = 6_000
#: A term is learned if at least so many different toxic texts have it (fewer, down to 3, where
#: there are under 2,000 such texts) ...
LEAST = 10
#: ... and its share among clean texts is at most this part of its share among toxic ones.
CLEAN = 0.15
#: ... and it is in this part of the toxic texts, or in NEW of them that no commoner term explains.
COMMON, NEW = 0.015, 0.01
#: Lengths of word beginnings tried as terms; such a term needs three different words.
BEGINNINGS = (4, 5, 6, 7)
#: Copies in the sample agree in all MINIMA of one of KEYS keys, each a minimum of hashed runs of RUN words.
KEYS, MINIMA, RUN = 6, 2, 5
LOG = logging.getLogger(__name__)


@dataclass(frozen=True)
class Model:
    """terms and what each adds, weights of the bias and of the four features, and words near a
    term that the sample shows to be no misspelling."""

    terms: dict[str, float]
    weights: list[float]
    innocent: tuple[str, ...] = ()

    @property
    def key(self) -> str:
        return "toxicity:" + hashlib.sha256(json.dumps([self.terms, self.innocent]).encode()).hexdigest()

    @property
    def text(self) -> str:
        return json.dumps([self.terms, self.weights, self.innocent])


def held_out(doc_id) -> F.Column:
    return F.crc32(F.coalesce(doc_id.cast("string"), F.lit(""))) % 5 == 0


def sample_of(docs: DataFrame, labels: DataFrame, most: int = SAMPLE) -> DataFrame:
    """row, text, words, toxic of about `most` training rows of each class, one of each group of copies.

    The labels are thinned by a hash of doc_id, so what is broadcast is bounded by `most`. Copies
    would make any word of theirs look like a term: of texts of one class that agree in one of KEYS
    keys of min-hashes only the one with the least doc_id stays. Texts that share four fifths of
    their runs of words are missed once in 450 times. The sizes before and after are logged.
    """
    rows = labels.filter(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull() & ~held_out(F.col("doc_id")))
    rows = rows.groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("toxic").alias("toxic"))
    counts = {r["toxic"]: r["n"] for r in rows.groupBy("toxic").agg(F.count("*").alias("n")).collect()}
    share = F.when(F.col("toxic") == 1, F.lit(most / max(counts.get(1, 1), 1))).otherwise(F.lit(most / max(counts.get(0, 1), 1)))
    some = rows.filter(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < share * 1_000_000)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text")).join(F.broadcast(some), "doc_id")
    texts = texts.withColumn("all", F.regexp_extract_all(F.lower("text"), F.lit(r"[\p{L}\p{N}]+"), F.lit(0))).filter(F.size("all") > 0)
    runs = F.transform(F.sequence(F.lit(1), F.greatest(F.size("all") - (RUN - 1), F.lit(1))), lambda at: F.xxhash64(F.concat_ws(" ", F.slice("all", at, RUN))))
    texts = texts.withColumn("runs", F.array_distinct(runs))
    keys = F.array(*[F.xxhash64(*[_least("runs", MINIMA * k + m) for m in range(MINIMA)]) for k in range(KEYS)])
    texts = stored(texts.select(F.monotonically_increasing_id().alias("row"), "doc_id", "text", F.array_distinct("all").alias("words"), "toxic", keys.alias("keys")), "toxicity-labelled")
    left = texts.select("toxic", "doc_id", F.xxhash64("text").alias("mark"), "row", "keys")
    for k in range(KEYS):
        left = left.groupBy("toxic", F.col("keys")[k].alias("key")).agg(F.min(F.struct("doc_id", "mark", "row", "keys")).alias("first")).select("toxic", "first.*")
    some = stored(texts.join(sized(stored(left.select("row"), "toxicity-rows")), "row", "left_semi").select("row", "text", "words", "toxic"), "toxicity-sample")
    LOG.info("labelled rows by class: %s, without copies: %s", _sizes(texts), _sizes(some))
    return some


def _least(runs: str, seed: int) -> F.Column:
    # F.transform counts the parameters of its lambda: the seed must not be one of them
    return F.array_min(F.transform(runs, lambda run: F.xxhash64(run, F.lit(seed))))


def _sizes(rows: DataFrame) -> dict[int, int]:
    return {r["toxic"]: r["n"] for r in rows.groupBy("toxic").agg(F.count("*").alias("n")).collect()}


def learn(docs: DataFrame, labels: DataFrame, most: int = SAMPLE) -> Model:
    """The terms and weights. Without toxic or clean training rows the model has no terms."""
    some = sample_of(docs, labels, most)
    sizes = _sizes(some)
    if not sizes.get(0) or not sizes.get(1):
        return Model({}, [-6.0, 0.0, 0.0, 0.0, 0.0])
    ratio = sizes[0] / sizes[1]
    least = min(LEAST, max(3, sizes[1] // 200))
    words = some.select("row", "toxic", F.explode("words").alias("word")).filter(F.length("word") >= 4)
    per_word = words.groupBy("word").agg(F.sum("toxic").alias("hit"), F.sum(1 - F.col("toxic")).alias("clean"), F.collect_list(F.when(F.col("toxic") == 1, F.col("row"))).alias("rows"))
    good = (F.col("hit") >= least) & (F.col("clean") <= CLEAN * ratio * F.col("hit"))
    begin = per_word.select(F.explode(F.array(*[F.when(F.length("word") >= n, F.substring("word", 1, n)) for n in BEGINNINGS])).alias("start"), "hit", "clean", "rows").filter("start is not null")
    begin = begin.groupBy("start").agg(
        F.sum("hit").alias("hit"), F.sum("clean").alias("clean"), F.sum(F.when(F.col("hit") > 0, 1).otherwise(0)).alias("kinds"), F.max("hit").alias("top"), F.array_distinct(F.flatten(F.collect_list("rows"))).alias("rows")
    )
    # candidates and their rows are few: the sample is bounded
    starts = begin.filter(good & (F.col("kinds") >= 3) & (F.col("top") < 0.8 * F.col("hit"))).collect()
    wholes = per_word.filter(good).collect()
    terms: dict[str, float] = {}
    known: set[int] = set()
    # beginnings first, short before long; then words, common before rare
    for text, r in [(r["start"] + "*", r) for r in sorted(starts, key=lambda r: (len(r["start"]), -r["hit"], r["start"]))] + [(r["word"], r) for r in sorted(wholes, key=lambda r: (-r["hit"], r["word"]))]:
        new = len(set(r["rows"]) - known)
        if (new >= max(3, NEW * sizes[1]) or r["hit"] >= COMMON * sizes[1]) and not any(t.endswith("*") and text.startswith(t[:-1]) for t in terms):
            terms[text] = float(np.log((r["hit"] + 0.5) * ratio / (r["clean"] + 0.5)))
            known.update(r["rows"])
    innocent = _innocent(per_word, terms, ratio)
    rows = _scored(some.select(F.col("toxic").cast("long").alias("doc_id"), "text"), Model(terms, [], innocent), True).collect()
    weights = fit(np.array([list(r["features"]) for r in rows]), np.array([float(r["doc_id"]) for r in rows]))
    LOG.info("%d terms, %d words near one that are none; weights %s", len(terms), len(innocent), weights.round(3).tolist())
    return Model(terms, [float(w) for w in weights], innocent)


def _innocent(per_word: DataFrame, terms: dict[str, float], ratio: float) -> tuple[str, ...]:
    """Words of the sample one letter from a term that clean texts have as readily as toxic ones."""
    if not terms:
        return ()

    def near(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lexicon = Lexicon(terms)
        for batch in batches:
            yield batch.filter(pa.array([(lexicon.match(w.as_py()) or ("", 0))[1] > 0 for w in batch.column(0)], pa.bool_()))

    clean = per_word.filter((F.col("clean") > 0) & (F.col("clean") > CLEAN * ratio * F.col("hit"))).select("word")
    return tuple(sorted(r["word"] for r in clean.mapInArrow(near, "word string").collect()))


def _scored(docs: DataFrame, model: Model, features: bool = False) -> DataFrame:
    small_batches(docs.sparkSession)
    text, key = model.text, model.key

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        terms, weights, innocent = json.loads(text)
        lexicon = worker_state(key, lambda: Lexicon(terms, innocent))
        for batch in batches:
            rows = [lexicon.features(t.as_py() or "") for t in batch.column(1)]
            if features:
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows, pa.list_(pa.float64()))], ["doc_id", "features"])
                continue
            x = np.array(rows).reshape(-1, 4)
            score = 1 / (1 + np.exp(-np.clip(weights[0] + x @ np.array(weights[1:]), -30, 30)))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(score)], ["doc_id", "score"])

    return docs.mapInArrow(run, "doc_id long, features array<double>" if features else "doc_id long, score double")


def score(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, held_out, score, predicted for every row, from its whole text alone.

    Null text is empty and scores as any text without hits; rows that repeat a doc_id give a row
    each; a null doc_id is kept and hashed as an empty text; an empty table gives no rows; other
    columns are ignored. Labels other than 0 and 1 are not used; of several labels of one document
    toxic wins.
    """
    rows = only(docs, "doc_id", "text").withColumn("doc_id", F.col("doc_id").cast("long"))
    got = _scored(rows, model)
    return got.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def reject(docs: DataFrame, model: Model) -> DataFrame:
    """The rows of docs that score under 0.5, with all their columns."""
    small_batches(docs.sparkSession)
    text, key = model.text, model.key

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        terms, weights, innocent = json.loads(text)
        lexicon = worker_state(key, lambda: Lexicon(terms, innocent))
        for batch in batches:
            x = np.array([lexicon.features(t.as_py() or "") for t in batch.column("text")]).reshape(-1, 4)
            yield batch.filter(pa.array(weights[0] + x @ np.array(weights[1:]) < 0))

    return docs.mapInArrow(run, docs.schema)


def op10_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return score(docs, learn(docs, table(spark, sf_dir, "labels")))
