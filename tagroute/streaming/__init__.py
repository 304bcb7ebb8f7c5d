"""Streams of events: rating windows, sessions as queries, routes for queries as they come, personal profiles."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.rounds import shared_dir
from ..query import Engine

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def events(spark: SparkSession, sf_dir: str, late: str = "1 day") -> DataFrame:
    """The events as a stream, with event time (UTC) and a watermark."""
    rows = spark.readStream.schema(EVENTS).option("pathGlobFilter", "events*").parquet(sf_dir)
    return rows.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)


def tumbling(stream: DataFrame, width: str = "1 day", slide: str | None = None) -> DataFrame:
    """Mean value and count by type and window."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return stream.groupBy(w.alias("w"), "event_type").agg(F.count("*").alias("n"), F.round(F.avg("value"), 6).alias("mean_value")).select(F.col("w.start").cast("timestamp_ntz").alias("start"), "event_type", "n", "mean_value")


def sessions(stream: DataFrame, pause: str = "30 minutes") -> DataFrame:
    """Types that a user asks for within pauses, as one query's tags."""
    return stream.groupBy(F.session_window("ts", pause).alias("w"), "user_id").agg(F.count("*").alias("n"), F.array_join(F.array_sort(F.collect_set("event_type")), "|").alias("tags")).select("user_id", F.col("w.start").cast("timestamp_ntz").alias("start"), "n", "tags")


def deduplicated(stream: DataFrame) -> DataFrame:
    return stream.dropDuplicatesWithinWatermark(["event_id"])


def clicks_to_purchases(stream: DataFrame, within: str = "1 hour") -> DataFrame:
    """Interval join of a user's views with purchases soon after."""
    a = stream.filter("event_type = 'view'").select(F.col("user_id").alias("u1"), F.col("ts").alias("t1"), F.col("event_id").alias("viewed"))
    b = stream.filter("event_type = 'purchase'").select(F.col("user_id").alias("u2"), F.col("ts").alias("t2"), F.col("event_id").alias("bought"))
    return a.join(b, F.expr(f"u1 = u2 AND t2 >= t1 AND t2 <= t1 + interval {within}")).select(F.col("u1").alias("user_id"), "viewed", "bought")


def with_pois(stream: DataFrame, pois: DataFrame, poi: Column) -> DataFrame:
    """Events of POIs by tag: each micro-batch is joined with the static table."""
    return stream.withColumn("poi", poi).join(pois.select("poi", "tag"), "poi").groupBy("tag", "event_type").agg(F.count("*").alias("n"))


def late_counts(spark: SparkSession, folder: str, path: str, late: str = "1 day") -> DataFrame:
    """One row: events of a folder, a file a batch, and how many lay so far behind the newest event of the batches before.

    What was newest is written by batch, so a batch that is retried counts alike.
    """
    rows = spark.readStream.schema(EVENTS).option("recursiveFileLookup", True).option("maxFilesPerTrigger", 1).parquet(folder)

    def count(batch: DataFrame, number: int) -> None:
        before = spark.read.schema("newest timestamp_ntz").parquet(f"{path}/newest/{number - 1}").first()[0] if number else None
        behind = F.lit(False) if before is None else F.col("ts") < F.lit(before) - F.expr(f"interval {late}")
        batch.agg(F.count("*").alias("n"), F.count_if(behind).alias("late")).write.mode("overwrite").parquet(f"{path}/counts/batch={number}")
        batch.agg(F.greatest(F.max("ts"), F.lit(before).cast("timestamp_ntz")).alias("newest")).coalesce(1).write.mode("overwrite").parquet(f"{path}/newest/{number}")

    rows.writeStream.foreachBatch(count).option("checkpointLocation", f"{path}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema("n long, late long, batch int").parquet(f"{path}/counts").agg(F.sum("n").alias("n"), F.sum("late").alias("late"))


def profiles(stream: DataFrame) -> DataFrame:
    """Running preference of each user by type, kept as state with Arrow batches: (user_id, event_type, n, mean_value)."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupStateTimeout

    def update(key, batches, state):
        n, total = state.get if state.exists else (0, 0.0)
        for pdf in batches:
            n, total = n + len(pdf), total + float(pdf["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "event_type": [key[1]], "n": [n], "mean_value": [total / max(n, 1)]})

    return stream.groupBy("user_id", "event_type").applyInPandasWithState(update, "user_id long, event_type string, n long, mean_value double", "n long, total double", "update", GroupStateTimeout.NoTimeout)


def drain(result: DataFrame, mode: str = "complete") -> DataFrame:
    """Run a stream over what is there, and read its result: the last one (complete), or all rows (append, update)."""
    spark = result.sparkSession
    base = f"{shared_dir(spark).rstrip('/')}/stream-{uuid.uuid4().hex}"

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/out/{'last' if mode == 'complete' else f'batch={number}'}")

    q = result.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(result.schema).parquet(f"{base}/out/{'last' if mode == 'complete' else ''}").select(*result.columns)


def routes(stream_queries: DataFrame, engine: Engine, path: str):
    """Answer every micro-batch of queries; returns the running query. Answers of a batch are replaced if it is retried."""
    def answer(batch: DataFrame, number: int) -> None:
        engine.run_batch(batch).write.mode("overwrite").parquet(f"{path}/batch={number}")

    return stream_queries.writeStream.foreachBatch(answer).option("checkpointLocation", f"{path}-state").trigger(availableNow=True).start()
