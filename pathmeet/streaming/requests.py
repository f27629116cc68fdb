"""Request and edge streams over ``events``: answers per micro-batch, windows, and running degrees."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathmeet.operators import meet
from pathmeet.operators.index import Index
from pathmeet.scratch import new_path


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as a file stream with event time as a timestamp."""
    path = f"{sf_dir}/events.parquet"
    table = spark.read.parquet(path)
    reader = spark.readStream.schema(table.schema)
    if any(f.endswith("/events.parquet") for f in table.inputFiles()):  # one file: a stream reads its folder
        stream = reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir)
    else:
        stream = reader.parquet(path)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def requests(stream: DataFrame) -> DataFrame:
    """(qid, s, t, ts): each event asks for the distance from its user to the user of half its number."""
    return stream.select(F.col("event_id").alias("qid"), (F.col("user_id") * 16 + 6).alias("s"), (F.expr("user_id div 2") * 16 + 6).alias("t"), "ts")


def answer_stream(index: Index, asked: DataFrame, sink: str, checkpoint: str, **options):
    """Starts a query that answers each micro-batch against the index and appends to ``sink``.

    A batch goes to a folder of its own number, overwritten if the batch is repeated after a
    failure, so every request is answered exactly once."""

    def each(batch: DataFrame, number: int) -> None:
        found = meet.distance(index, batch.dropDuplicates(["qid"]), **options)
        found.write.mode("overwrite").parquet(f"{sink}/batch={number}")

    return asked.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def answered_requests(spark: SparkSession, index: Index, asked: DataFrame, **options) -> DataFrame:
    """Runs the stream over what is there now and returns all answers."""
    sink, checkpoint = new_path(spark, "answers-sink"), new_path(spark, "answers-checkpoint")
    answer_stream(index, asked, sink, checkpoint, **options).awaitTermination()
    return spark.read.parquet(sink).drop("batch")


def windowed_counts(stream: DataFrame, size: str, slide: str | None = None, late: str = "1 hour", by: str = "event_type") -> DataFrame:
    """(start, key, requests, total): tumbling or sliding event-time windows behind a watermark."""
    span = F.window("ts", size, slide) if slide else F.window("ts", size)
    counted = stream.withWatermark("ts", late).groupBy(span.alias("w"), by).agg(F.count("*").alias("requests"), F.round(F.sum("value"), 4).alias("total"))
    return counted.select(F.col("w.start").alias("start"), by, "requests", "total")


def session_counts(stream: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """(user_id, start, stop, requests): sessions of a user that end after ``gap`` without an event."""
    span = F.session_window("ts", gap)
    counted = stream.withWatermark("ts", late).groupBy(span.alias("w"), "user_id").agg(F.count("*").alias("requests"))
    return counted.select("user_id", F.col("w.start").alias("start"), F.col("w.end").alias("stop"), "requests")


def run_once(spark: SparkSession, streamed: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a streaming frame over what is there now and returns its result as a table."""
    checkpoint = new_path(spark, "stream-checkpoint")
    if mode == "append":
        sink = new_path(spark, "stream-sink")
        streamed.writeStream.format("parquet").option("path", sink).option("checkpointLocation", checkpoint).outputMode("append").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(streamed.schema).parquet(sink)
    sink = new_path(spark, "stream-state")

    def replace(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(sink)

    streamed.writeStream.foreachBatch(replace).option("checkpointLocation", checkpoint).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(streamed.schema).parquet(sink)


def degree_stream(edges: DataFrame) -> DataFrame:
    """(id, arrivals): running number of edge arrivals per node of a stream (src, dst)."""
    ends = edges.select(F.explode(F.array("src", "dst")).alias("id"))
    return ends.groupBy("id").agg(F.count("*").alias("arrivals"))
