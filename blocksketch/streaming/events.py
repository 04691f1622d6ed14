"""Block statistics, replies and sketches over streams of events."""

from __future__ import annotations

import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blocksketch.functions.core import hash_int
from blocksketch.sources.tables import scratch_path, stored, table


def read_events(spark: SparkSession, folder: str, name: str = "events.parquet", files_per_trigger: int = 4) -> DataFrame:
    """The events table as a file stream; event time as a timestamp."""
    schema = spark.read.parquet(f"{folder.rstrip('/')}/{name}").schema
    stream = spark.readStream.schema(schema).option("pathGlobFilter", name).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def finish(stream: DataFrame, mode: str = "complete") -> DataFrame:
    """Runs a stream over all that is there and returns its (bounded) result table."""
    spark = stream.sparkSession
    if mode == "append":
        path, at = scratch_path(spark, "stream"), scratch_path(spark, "stream-state")
        stream.writeStream.format("parquet").option("path", path).option("checkpointLocation", at).outputMode("append").trigger(availableNow=True).start().awaitTermination()
        return spark.read.schema(stream.schema).parquet(path)
    name = f"s{uuid.uuid4().hex}"
    at = scratch_path(spark, "stream-state")
    stream.writeStream.format("memory").queryName(name).option("checkpointLocation", at).outputMode(mode).trigger(availableNow=True).start().awaitTermination()
    return spark.table(name)


def tumbling_stats(events: DataFrame, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    """A window of event time is a block: n and the Gram entries of (1, value/100)."""
    v = F.col("value") / 100
    out = events.withWatermark("ts", late) if events.isStreaming else events
    return out.groupBy(F.window("ts", width).alias("w")).agg(F.count("*").alias("n"), F.sum(v).alias("g01"), F.sum(v * v).alias("g11")).select(F.col("w.start").alias("start"), "n", "g01", "g11")


def sliding_stats(events: DataFrame, width: str = "2 days", every: str = "1 day", late: str = "1 hour") -> DataFrame:
    """Overlapping windows."""
    out = events.withWatermark("ts", late) if events.isStreaming else events
    return out.groupBy(F.window("ts", width, every).alias("w")).agg(F.count("*").alias("n"), F.sum("value").alias("total")).select(F.col("w.start").alias("start"), "n", "total")


def session_stats(events: DataFrame, gap: str = "6 hours", late: str = "1 hour") -> DataFrame:
    """A user's session is a block; on a stream, sessions are given out when the watermark passes them."""
    out = events.withWatermark("ts", late) if events.isStreaming else events
    return out.groupBy(F.session_window("ts", gap).alias("w"), "user_id").agg(F.count("*").alias("n"), F.sum("value").alias("total")).select("user_id", F.col("w.start").alias("start"), "n", "total")


def replies_by_deadline(events: DataFrame, ending: float, late: str = "1 hour") -> DataFrame:
    """Events as worker replies taking ``value`` seconds: per day how many came in time, and how many are erasures."""
    out = events.withWatermark("ts", late) if events.isStreaming else events
    ok = (F.col("value") <= ending).cast("long")
    return out.groupBy(F.window("ts", "1 day").alias("w")).agg(F.sum(ok).alias("came"), F.sum(1 - ok).alias("late")).select(F.col("w.start").alias("start"), "came", "late")


def weighted_by_static(events: DataFrame, weights: DataFrame) -> DataFrame:
    """Stream-static join: each event's block weight (event_type is the block)."""
    return events.join(F.broadcast(weights), "event_type").groupBy("event_type").agg(F.sum(F.col("w") * F.col("value")).alias("weighted"), F.count("*").alias("n"))


def first_of_each(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Drops repeated event ids that come within the lateness bound."""
    out = events.withWatermark("ts", late)
    return out.dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else events.dropDuplicates(["event_id"])


def count_late(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """One row: events kept, and those that came after the watermark had passed them, as the state operator counts them."""
    spark, counts = events.sparkSession, {}

    def count(batch: DataFrame, number: int) -> None:
        counts[number] = batch.count()  # a batch that is run again counts once

    kept = events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
    query = kept.writeStream.foreachBatch(count).option("checkpointLocation", scratch_path(spark, "stream-state")).outputMode("append").trigger(availableNow=True).start()
    query.awaitTermination()
    dropped = sum(op["numRowsDroppedByWatermark"] for p in query.recentProgress for op in p["stateOperators"])
    return spark.createDataFrame([(sum(counts.values()), dropped)], "kept long, late long")


def replay(events: DataFrame, cuts: list[str]) -> str:
    """A folder with the events of each period as one file, written in the order given: periods may come out of order.

    All tasks read and one writes.
    """
    path = scratch_path(events.sparkSession, "replay")
    for low, high in zip(cuts[::2], cuts[1::2], strict=True):
        part = events.where((F.col("ts") >= F.lit(low).cast("timestamp")) & (F.col("ts") < F.lit(high).cast("timestamp")))
        part.repartition(1).write.mode("append").parquet(path)
    return path


def hashed_sketch(events: DataFrame, r: int = 16) -> DataFrame:
    """A hashed signed sum of rows (1, value/100): needs no scores, so it suits a fast stream."""
    bucket = (hash_int("cs0", F.col("event_id")) % r).cast("int")
    sign = F.when(hash_int("sg0", F.col("event_id")) % 2 == 0, 1.0).otherwise(-1.0)
    return events.groupBy(bucket.alias("sketch_row")).agg(F.sum(sign).alias("s0"), F.sum(sign * F.col("value") / 100).alias("s1"))


def running_gram(events: DataFrame, on_update: Callable[[int, DataFrame], None] | None = None) -> DataFrame:
    """Gram entries over all batches so far, refreshed after every batch; state is one row in the shared folder."""
    spark = events.sparkSession
    held: list[DataFrame] = []

    def add(batch: DataFrame, number: int) -> None:
        v = F.col("value") / 100
        new = batch.agg(F.count("*").alias("n"), F.coalesce(F.sum(v), F.lit(0.0)).alias("g01"), F.coalesce(F.sum(v * v), F.lit(0.0)).alias("g11"))
        total = new if not held else held[-1].unionByName(new).agg(F.sum("n").alias("n"), F.sum("g01").alias("g01"), F.sum("g11").alias("g11"))
        held.append(stored(total, "gram"))
        if on_update:
            on_update(number, held[-1])

    at = scratch_path(spark, "stream-state")
    events.writeStream.foreachBatch(add).option("checkpointLocation", at).trigger(availableNow=True).start().awaitTermination()
    return held[-1] if held else spark.createDataFrame([], "n long, g01 double, g11 double")


def batch_events(spark: SparkSession, folder: str) -> DataFrame:
    """The batch twin."""
    return table(spark, folder, "events").withColumn("ts", F.col("ts").cast("timestamp"))
