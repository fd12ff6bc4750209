"""The event feed as a stream of triples, and upkeep of signature counts (ST-1 to ST-9, O-16).

Each transformation takes a batch or a streaming frame alike, so a stream can be held against its
batch twin.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, *, files_per_batch: int = 1, late: str = "1 hour") -> DataFrame:
    feed = spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", files_per_batch).parquet(path)
    return feed.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def rate_events(spark: SparkSession, *, rows_per_second: int = 100, users: int = 50, late: str = "1 hour") -> DataFrame:
    """A feed without files, in the events' shape, for load tests."""
    feed = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    kind = F.element_at(F.array(*[F.lit(x) for x in ("view", "click", "purchase")]), (F.col("value") % 3 + 1).cast("int"))
    rows = feed.select(F.col("value").alias("event_id"), F.col("timestamp").alias("ts"), (F.col("value") % users).alias("user_id"), kind.alias("event_type"), F.lit(0.0).alias("value"), F.lit("{}").alias("props"))
    return rows.withWatermark("ts", late)


def dropped_rows(query: StreamingQuery) -> int:
    """Rows that came after the watermark and were left out by the query's stateful operators so far."""
    return sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])


def as_triples(events: DataFrame) -> DataFrame:
    return events.select(F.col("user_id").cast("string").alias("head"), F.lit("did").alias("rel"), F.col("event_type").alias("tail"), "ts")


def counts(events: DataFrame, width: str, slide: str | None = None) -> DataFrame:
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.groupBy(w, "event_type").agg(F.count("*").alias("n"))


def sessions(events: DataFrame, gap: str) -> DataFrame:
    return events.groupBy(F.session_window("ts", gap), "user_id").agg(F.count("*").alias("n"))


def fresh_triples(events: DataFrame) -> DataFrame:
    """Each triple once within the watermark."""
    return as_triples(events).dropDuplicatesWithinWatermark(["head", "rel", "tail"])


def view_to_purchase(views: DataFrame, purchases: DataFrame, gap: str) -> DataFrame:
    v = views.select(F.col("event_id").alias("v"), F.col("user_id").alias("vu"), F.col("ts").alias("vt"))
    p = purchases.select(F.col("event_id").alias("p"), F.col("user_id").alias("pu"), F.col("ts").alias("pt"))
    return v.join(p, F.expr(f"vu = pu and pt >= vt and pt <= vt + interval {gap}"))


def maintain_signatures(triples: DataFrame, etypes: DataFrame, path: str, checkpoint: str) -> StreamingQuery:
    """Keeps counts of (head type, rel, tail type) under path, one folder per micro-batch, written
    with the batch's id: a batch that runs again overwrites its own folder, so nothing counts
    twice. dominant() reads the present state."""

    def merge(batch: DataFrame, batch_id: int) -> None:
        h = etypes.select(F.col("entity").alias("head"), F.col("etype").alias("head_type"))
        t = etypes.select(F.col("entity").alias("tail"), F.col("etype").alias("tail_type"))
        per = batch.join(h, "head").join(t, "tail").groupBy("rel", "head_type", "tail_type").agg(F.count("*").alias("n"))
        per.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return triples.writeStream.foreachBatch(merge).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def dominant(spark: SparkSession, path: str) -> DataFrame:
    """head_type, rel, tail_type, support: the present signatures."""
    rows = spark.read.parquet(path).groupBy("rel", "head_type", "tail_type").agg(F.sum("n").alias("support"))
    best = rows.groupBy("rel").agg(F.min(F.struct((-F.col("support")).alias("s"), "head_type", "tail_type")).alias("b"))
    return best.select("b.head_type", "rel", "b.tail_type", (-F.col("b.s")).alias("support"))


def answer_stream(questions: DataFrame, retrieve_batch, path: str, checkpoint: str) -> StreamingQuery:
    """Stream-static retrieval: each micro-batch of questions is answered on the static graph by
    retrieve_batch(questions) and written under its batch id."""

    def run(batch: DataFrame, batch_id: int) -> None:
        retrieve_batch(batch).write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return questions.writeStream.foreachBatch(run).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
