"""Structured Streaming over the events table: running access counts, windows, late data, lookups."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from idfold.storage import shared_folder


def events_stream(spark: SparkSession, sf_dir: str, *, watermark: str = "1 day") -> DataFrame:
    """A stream over the events file(s), with event time as a timestamp and a watermark."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    reader = spark.readStream.schema(schema)
    raw = reader.option("pathGlobFilter", "events.parquet").parquet(sf_dir) if _is_file(spark, sf_dir) else reader.parquet(f"{sf_dir}/events.parquet")
    return raw.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", watermark)


def _is_file(spark: SparkSession, sf_dir: str) -> bool:
    """Whether the table is one file, asked of the store through Hadoop."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{sf_dir}/events.parquet")
    return path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(path).isFile()


def run_to_table(stream: DataFrame, *, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there and return what it emitted.

    Appending streams write Parquet through the transactional file sink; others replace a table per
    batch (``foreachBatch``, idempotent by overwriting), of which the last state remains.
    """
    spark = stream.sparkSession
    root = f"{shared_folder(spark)}/idfold-stream-{uuid.uuid4().hex}"
    writer = stream.writeStream.option("checkpointLocation", f"{root}/state").trigger(availableNow=True)
    if mode == "append":
        writer.outputMode("append").format("parquet").option("path", f"{root}/out").start().awaitTermination()
    else:
        writer.outputMode(mode).foreachBatch(lambda df, epoch: df.write.mode("overwrite").parquet(f"{root}/out")).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{root}/out")


def tumbling_counts(stream: DataFrame, *, width: str = "1 day") -> DataFrame:
    w = F.window("ts", width)
    return stream.groupBy(w, "user_id").agg(F.count("*").alias("n")).select(F.col("window.start").alias("window_start"), "user_id", "n")


def sliding_counts(stream: DataFrame, *, width: str = "2 days", slide: str = "1 day") -> DataFrame:
    w = F.window("ts", width, slide)
    return stream.groupBy(w, "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("window_start"), "event_type", "n")


def user_sessions(stream: DataFrame, *, gap: str = "6 hours") -> DataFrame:
    s = F.session_window("ts", gap)
    return stream.groupBy(s, "user_id").agg(F.count("*").alias("n")).select(F.col("session_window.start").alias("session_start"), F.col("session_window.end").alias("session_end"), "user_id", "n")


def running_access(stream: DataFrame) -> DataFrame:
    """(id, accesses): total uses of every user id so far (complete mode)."""
    return stream.groupBy(F.col("user_id").alias("id")).agg(F.count("*").alias("accesses"))


def stateful_access(stream: DataFrame) -> DataFrame:
    """The same counts from an explicit state per id; emits the running total of each id per batch."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def update(key, batches, state: GroupState):
        n = (state.get[0] if state.exists else 0) + sum(len(b) for b in batches)
        state.update((n,))
        yield pd.DataFrame({"id": [key[0]], "accesses": [n]})

    return stream.select("user_id").groupBy("user_id").applyInPandasWithState(update, "id long, accesses long", "accesses long", "update", GroupStateTimeout.NoTimeout)


def deduplicated(stream: DataFrame) -> DataFrame:
    return stream.dropDuplicatesWithinWatermark(["event_id"])


def with_static(stream: DataFrame, fold_map: DataFrame) -> DataFrame:
    """Stream joined with a fold map (user ids to rows)."""
    return stream.join(F.broadcast(fold_map.select(F.col("id").alias("user_id"), "row")), "user_id").select("event_id", "user_id", "row")


def clicks_with_purchases(stream_a: DataFrame, stream_b: DataFrame) -> DataFrame:
    """Clicks joined with purchases of the same user within the following hour."""
    a = stream_a.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("u"), F.col("ts").alias("click_ts"))
    b = stream_b.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("v"), F.col("ts").alias("buy_ts"))
    return a.join(b, F.expr("u = v AND buy_ts >= click_ts AND buy_ts <= click_ts + INTERVAL 1 HOUR")).select("click_id", "purchase_id", F.col("u").alias("user_id"))


def drift_alarm(stream: DataFrame, known: DataFrame, *, share: float = 0.02) -> DataFrame:
    """Per day: uses, uses of ids that the map does not know, and whether their share is over ``share``."""
    marked = stream.join(F.broadcast(known.select(F.col("id").alias("user_id"), F.lit(1).alias("known"))), "user_id", "left")
    w = F.window("ts", "1 day")
    per = marked.groupBy(w).agg(F.count("*").alias("uses"), F.sum(F.when(F.col("known").isNull(), 1).otherwise(0)).alias("unseen"))
    return per.select(F.col("window.start").alias("day_start"), "uses", "unseen", (F.col("unseen") > F.col("uses") * F.lit(share)).alias("alarm"))
