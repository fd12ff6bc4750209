"""Answer-type prediction: native models and hooks for external ones (P-05 to P-12)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from kgtrail.functions.text import token_cosine, tokens


class NaiveBayes:
    """Multinomial naive Bayes over question tokens; training pairs carry the soft target's weight."""

    def __init__(self, *, alpha: float = 1.0):
        self.alpha = alpha

    def fit(self, train: DataFrame, target: DataFrame) -> NaiveBayes:
        """train (qid, text), target (qid, etype, q). The model tables have a row per type and per
        (type, token)."""
        pairs = train.select("qid", "text").join(target.select("qid", "etype", "q"), "qid")
        self.classes = pairs.groupBy("etype").agg(F.sum("q").alias("n_c"))
        self.counts = pairs.select("etype", "q", F.explode(tokens(F.col("text"))).alias("token")).groupBy("etype", "token").agg(F.sum("q").alias("n_ct"))
        return self

    def scores(self, q: DataFrame) -> DataFrame:
        """qid, etype, logp: log posterior, normalised over the types."""
        a = self.alpha
        size = self.classes.agg(F.count("*").alias("c"), F.sum("n_c").alias("n"))
        vocab = self.counts.agg(F.countDistinct("token").alias("v"))
        mass = self.counts.groupBy("etype").agg(F.sum("n_ct").alias("m"))
        model = self.classes.join(mass, "etype", "left").fillna(0, ["m"]).crossJoin(F.broadcast(size)).crossJoin(F.broadcast(vocab))
        prior = model.select("etype", F.log((F.col("n_c") + a) / (F.col("n") + a * F.col("c"))).alias("prior"), (F.col("m") + a * F.col("v")).alias("den"))
        asked = q.select("qid", F.explode_outer(tokens(F.col("text"))).alias("token"))
        # a token that a type never had costs the same for each type and occurrence: log(a / den)
        base = asked.groupBy("qid").agg(F.count("token").alias("len")).crossJoin(F.broadcast(prior))
        base = base.select("qid", "etype", (F.col("prior") + F.col("len") * (F.log(F.lit(a)) - F.log("den"))).alias("base"))
        gain = asked.join(self.counts, "token").groupBy("qid", "etype").agg(F.sum(F.log((F.col("n_ct") + a) / F.lit(a))).alias("gain"))
        raw = base.join(gain, ["qid", "etype"], "left").select("qid", "etype", (F.col("base") + F.coalesce("gain", F.lit(0.0))).alias("raw"))
        by_q = Window.partitionBy("qid")
        top = raw.withColumn("top", F.max("raw").over(by_q))
        return top.select("qid", "etype", (F.col("raw") - F.col("top") - F.log(F.sum(F.exp(F.col("raw") - F.col("top"))).over(by_q))).alias("logp"))


class Nearest:
    """Vote of the k training questions nearest by token cosine. Training texts are deduplicated to
    (text without digits, type) prototypes, so the broadcast side grows with the number of
    phrasings, not of questions; it is counted, and more than MOST are refused."""

    MOST = 20_000

    def __init__(self, k: int = 3):
        self.k = k

    def fit(self, train: DataFrame, target: DataFrame) -> Nearest:
        pairs = train.select("qid", "text").join(target.select("qid", "etype", "q"), "qid")
        self.prototypes = pairs.groupBy(F.regexp_replace("text", "[0-9]+", "").alias("proto"), "etype").agg(F.sum("q").alias("weight"))
        if self.prototypes.limit(self.MOST + 1).count() > self.MOST:
            raise ValueError(f"more than {self.MOST} phrasings: compare them by an index of words")
        return self

    def scores(self, q: DataFrame) -> DataFrame:
        """qid, etype, logp: log share of similarity among the k nearest prototypes."""
        asked = q.select("qid", tokens(F.regexp_replace("text", "[0-9]+", "")).alias("a"))
        met = asked.crossJoin(F.broadcast(self.prototypes)).select("qid", "etype", "proto", token_cosine(F.col("a"), tokens(F.col("proto"))).alias("sim"))
        order = Window.partitionBy("qid").orderBy(F.desc("sim"), "proto", "etype")
        near = met.withColumn("k", F.row_number().over(order)).filter(F.col("k") <= self.k)
        votes = near.groupBy("qid", "etype").agg(F.sum("sim").alias("s"))
        total = F.sum("s").over(Window.partitionBy("qid"))
        return votes.select("qid", "etype", F.when(total > 0, F.log(F.col("s") / total)).otherwise(F.lit(float("-inf"))).alias("logp"))


class Oracle:
    """The gold type, as an upper bound."""

    def __init__(self, target: DataFrame):
        self.target = target

    def scores(self, q: DataFrame) -> DataFrame:
        return self.target.join(q.select("qid"), "qid", "left_semi").select("qid", "etype", F.log("q").alias("logp"))


class Null:
    """No prediction at all: every question falls back to forward search."""

    def scores(self, q: DataFrame) -> DataFrame:
        return q.select("qid", F.lit("").alias("etype"), F.lit(0.0).alias("logp")).filter(F.lit(False))


class Replay:
    """Recorded replies (prompt_hash, etype) of an external model, joined by the hash of the text."""

    def __init__(self, replies: DataFrame):
        self.replies = replies

    def scores(self, q: DataFrame) -> DataFrame:
        asked = q.select("qid", F.sha2("text", 256).alias("prompt_hash"))
        return asked.join(self.replies, "prompt_hash").select("qid", "etype", F.lit(0.0).alias("logp"))


class ExternalModel:
    """Hook for a model behind a Python function texts -> types, called on Arrow batches."""

    def __init__(self, make: Callable[[], Callable[[list[str]], list[str]]]):
        self.make = make

    def scores(self, q: DataFrame) -> DataFrame:
        make = self.make

        def run(frames):
            model = make()
            for f in frames:
                yield f[["qid"]].assign(etype=model(f["text"].tolist()), logp=0.0)

        return q.select("qid", "text").mapInPandas(run, "qid long, etype string, logp double")


def predict(scores: DataFrame, *, m: int = 1) -> DataFrame:
    """qid, etype, logp of the m best types; of equals the first name."""
    order = Window.partitionBy("qid").orderBy(F.desc(F.round("logp", 9)), "etype")
    return scores.withColumn("k", F.row_number().over(order)).filter(F.col("k") <= m).drop("k")


def chain_logp(scores: DataFrame) -> DataFrame:
    """qid, etype, logp of a prior that writes type names token by token: each token's conditional
    is the posterior mass of the names that share the prefix with it, over the mass of those that
    share the prefix. Names end in a terminator, so the chain sums to one over the names."""
    named = scores.select("qid", "etype", F.exp("logp").alias("p"), F.concat(F.split("etype", "[._:@]"), F.array(F.lit("</s>"))).alias("parts"))
    each = named.select("qid", "etype", "p", F.posexplode("parts").alias("pos", "token"), "parts")
    each = each.withColumn("prefix", F.concat_ws(" ", F.slice("parts", F.lit(1), F.col("pos")))).withColumn("longer", F.concat_ws(" ", "prefix", "token"))
    share = F.sum("p").over(Window.partitionBy("qid", "pos", "longer")) / F.sum("p").over(Window.partitionBy("qid", "pos", "prefix"))
    return each.withColumn("step", F.log(share)).groupBy("qid", "etype").agg(F.sum("step").alias("logp"))


def accuracy(pred: DataFrame, valid: DataFrame) -> DataFrame:
    """One row: questions, and the share whose first type is valid."""
    hit = pred.select("qid", "etype").join(valid.select("qid", "etype", F.lit(1).alias("ok")), ["qid", "etype"], "left")
    return hit.agg(F.count("*").alias("questions"), F.round(F.avg(F.coalesce("ok", F.lit(0)).cast("double")), 6).alias("accuracy"))


def cross_entropy(target: DataFrame, scores: DataFrame) -> DataFrame:
    """One row: mean over questions of -sum q log p."""
    per = target.join(scores, ["qid", "etype"]).groupBy("qid").agg((-F.sum(F.col("q") * F.col("logp"))).alias("h"))
    return per.agg(F.round(F.avg("h"), 6).alias("cross_entropy"))
