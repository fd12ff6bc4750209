"""Ranking of evidence paths (K-01 to K-07, R-18)."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kgtrail.functions import vector
from kgtrail.functions.text import path_text, relation_tokens, token_cosine, tokens

#: Encoders say by by_relations whether paths with the same relations always score the same.
#: Order of paths: score, then shorter, then key.
TIE = ("len", "path_key")


class TokenCosine:
    """Similarity of question tokens and relation tokens. A relation sequence is scored once per
    question, however many paths follow it; 'all' scores entity names too."""

    def __init__(self, score_on: str = "relations"):
        self.score_on = score_on
        self.by_relations = score_on != "all"

    def score(self, paths: DataFrame, q: DataFrame) -> DataFrame:
        if self.score_on == "all":
            asked = q.select("qid", tokens(F.col("text")).alias("_q"))
            return paths.join(asked, "qid").withColumn("score", token_cosine(F.col("_q"), tokens(path_text(F.col("rels"), F.col("nodes"))))).drop("_q")
        kinds = paths.select("qid", "rels").distinct().join(q.select("qid", tokens(F.col("text")).alias("_q")), "qid")
        scored = kinds.select("qid", "rels", token_cosine(F.col("_q"), relation_tokens(F.col("rels"))).alias("score"))
        return paths.join(scored, ["qid", "rels"])


class TfIdf:
    """Cosine of TF-IDF weights over hashed tokens; document frequencies from the path texts."""

    by_relations = True

    def __init__(self, buckets: int = 1 << 18):
        self.buckets = buckets

    def score(self, paths: DataFrame, q: DataFrame) -> DataFrame:
        bucket = lambda t: F.pmod(F.xxhash64(t), F.lit(self.buckets))
        kinds = paths.select("qid", "rels").distinct().withColumn("k", F.concat_ws(">", "rels"))
        texts = kinds.select("k", "rels").distinct()
        terms = texts.select("k", F.explode(relation_tokens(F.col("rels"))).alias("t")).groupBy("k", bucket(F.col("t")).alias("b")).agg(F.count("*").alias("tf"))
        n = texts.agg(F.count("*").alias("n"))
        idf = terms.groupBy("b").agg(F.count("*").alias("df")).crossJoin(F.broadcast(n)).select("b", F.log((F.col("n") + 1) / (F.col("df") + 1)).alias("idf"))
        w = terms.join(idf, "b").select("k", "b", (F.col("tf") * (F.col("idf") + 1)).alias("w"))
        asked = q.select("qid", F.explode(tokens(F.col("text"))).alias("t")).groupBy("qid", bucket(F.col("t")).alias("b")).agg(F.count("*").alias("tf"))
        wq = asked.join(idf, "b", "left").select("qid", "b", (F.col("tf") * (F.coalesce("idf", F.lit(0.0)) + 1)).alias("wq"))
        dots = kinds.join(w, "k").join(wq, ["qid", "b"]).groupBy("qid", "k").agg(F.sum(F.col("w") * F.col("wq")).alias("dot"))
        nk = w.groupBy("k").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("nk"))
        nq = wq.groupBy("qid").agg(F.sqrt(F.sum(F.col("wq") * F.col("wq"))).alias("nq"))
        scored = kinds.join(dots, ["qid", "k"], "left").join(nk, "k", "left").join(nq, "qid", "left")
        scored = scored.select("qid", "rels", F.coalesce(F.round(F.col("dot") / (F.col("nk") * F.col("nq")), 6), F.lit(0.0)).alias("score"))
        return paths.join(scored, ["qid", "rels"])


class HashedVector:
    """Feature hashing into `dim` signed sums, compared by cosine."""

    by_relations = True

    def __init__(self, dim: int = 64):
        self.dim = dim

    def _vec(self, toks):
        part = lambda t, a, n: F.conv(F.substring(F.md5(t), a, n), 16, 10).cast("long")
        one = lambda t: F.transform(F.sequence(F.lit(0), F.lit(self.dim - 1)), lambda i: F.when(part(t, 1, 8) % self.dim == i, F.when(part(t, 9, 1) % 2 == 0, 1.0).otherwise(-1.0)).otherwise(0.0))
        zero = F.array_repeat(F.lit(0.0), self.dim)
        return F.aggregate(toks, zero, lambda acc, t: F.zip_with(acc, one(t), lambda a, b: a + b))

    def score(self, paths: DataFrame, q: DataFrame) -> DataFrame:
        kinds = paths.select("qid", "rels").distinct().join(q.select("qid", self._vec(tokens(F.col("text"))).alias("vq")), "qid")
        kinds = kinds.withColumn("vp", self._vec(relation_tokens(F.col("rels"))))
        sim = F.coalesce(F.round(F.try_divide(vector.dot(F.col("vq"), F.col("vp")), vector.norm(F.col("vq")) * vector.norm(F.col("vp"))), 6), F.lit(0.0))
        return paths.join(kinds.select("qid", "rels", sim.alias("score")), ["qid", "rels"])


class ExternalEncoder:
    """Hook for a sentence encoder texts -> vectors, loaded once per worker; distinct texts only."""

    by_relations = True

    def __init__(self, make: Callable[[], Callable[[list[str]], np.ndarray]]):
        self.make = make

    def encode(self, texts: DataFrame) -> DataFrame:
        """text, vec for the distinct values of column text."""
        make = self.make

        def run(frames):
            encode = make()
            for f in frames:
                yield f.assign(vec=list(np.asarray(encode(f["text"].tolist()), np.float64)))

        return texts.select("text").distinct().mapInPandas(run, "text string, vec array<double>")

    def score(self, paths: DataFrame, q: DataFrame) -> DataFrame:
        kinds = paths.select("qid", "rels").distinct().withColumn("text", F.concat_ws(" ", relation_tokens(F.col("rels"))))
        vp = kinds.join(self.encode(kinds), "text").withColumnRenamed("vec", "vp").drop("text")
        vq = q.select("qid", "text").join(self.encode(q), "text").select("qid", F.col("vec").alias("vq"))
        scored = vp.join(vq, "qid").select("qid", "rels", F.coalesce(F.round(vector.cosine(F.col("vq"), F.col("vp")), 6), F.lit(0.0)).alias("score"))
        return paths.join(scored, ["qid", "rels"])


def top_k(paths: DataFrame, q: DataFrame, *, k: int = 256, encoder=None) -> DataFrame:
    """The k best paths of each question, with score and rank. The row-number filter becomes a group
    limit before and after the shuffle, so no more than k rows per question and task travel."""
    scored = (encoder or TokenCosine()).score(paths, q)
    return scored.withColumn("rank", F.row_number().over(Window.partitionBy("qid").orderBy(F.desc("score"), *TIE))).filter(F.col("rank") <= k)


def render(paths: DataFrame) -> DataFrame:
    return paths.withColumn("text", path_text(F.col("rels"), F.col("nodes")))


#: Queries that are broadcast at once.
QUERY_BLOCK = 2_000


def vector_top_k(queries: DataFrame, items: DataFrame, *, k: int, block: int = QUERY_BLOCK) -> DataFrame:
    """qid, id, score, rank: exact cosine top-k. The stated query set (qid, vec) is taken in blocks of
    about `block` rows, each broadcast; items (id, vec) are scanned once a block, and each task keeps
    k rows per query."""
    parts, out = max(1, -(-queries.count() // block)), None
    for i in range(parts):
        some = queries.filter(F.pmod(F.xxhash64("qid"), F.lit(parts)) == i).select("qid", F.col("vec").alias("_q"))
        met = items.crossJoin(F.broadcast(some)).filter("id <> qid")
        scored = met.select("qid", "id", F.round(vector.cosine(F.col("_q"), F.col("vec")), 6).alias("score"))
        order = Window.partitionBy("qid").orderBy(F.desc("score"), "id")
        top = scored.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)
        out = top if out is None else out.unionByName(top)
    return out


def lsh_top_k(queries: DataFrame, items: DataFrame, *, k: int, bits: int = 6, tables: int = 12, dim: int = 64, seed: int = 5) -> DataFrame:
    """Approximate top-k: candidates share the sign code of at least one table; codes are JVM
    expressions. Candidates are compared exactly."""
    rng = np.random.default_rng(seed)
    planes = [rng.standard_normal((bits, dim)).round(4).tolist() for _ in range(tables)]
    coded = lambda v: F.array(*[F.concat(F.lit(f"{t}:"), vector.sign_code(v, p)) for t, p in enumerate(planes)])
    a = queries.select("qid", F.col("vec").alias("_q"), F.explode(coded(F.col("vec"))).alias("code"))
    b = items.select("id", "vec", F.explode(coded(F.col("vec"))).alias("code"))
    met = a.join(b, "code").filter("id <> qid").dropDuplicates(["qid", "id"])
    scored = met.select("qid", "id", F.round(vector.cosine(F.col("_q"), F.col("vec")), 6).alias("score"))
    order = Window.partitionBy("qid").orderBy(F.desc("score"), "id")
    return scored.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)


def recall(found: DataFrame, exact: DataFrame) -> DataFrame:
    hit = exact.select("qid", "id").join(found.select("qid", "id", F.lit(1).alias("hit")), ["qid", "id"], "left")
    return hit.agg(F.count("*").alias("wanted"), F.round(F.avg(F.coalesce("hit", F.lit(0)).cast("double")), 6).alias("recall"))
