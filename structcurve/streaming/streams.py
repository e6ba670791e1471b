"""Structured Streaming over events: encoding, windows, late rows, de-duplication, upkeep of frequencies, scoring."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.encode import DimSpec, GridSpec, quantize
from ..functions.curves import morton_encode
from ..session import fresh_path
from ..sources.tables import event_points, load

EVENT_GRID = GridSpec((DimSpec("kind", 0, 16), DimSpec("hour", 0, 24), DimSpec("value", 0, 500), DimSpec("k", 0, 100)))


def stream_events(spark: SparkSession, sf_dir: str, files_per_batch: int | None = None) -> DataFrame:
    """A file stream over the events' Parquet files, with the batch table's schema."""
    reader = spark.readStream.schema(load(spark, sf_dir, "events").schema)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    # event time must be an instant; the files may hold local timestamps
    return reader.parquet(f"{sf_dir}/events.parquet*").withColumn("ts", F.col("ts").cast("timestamp"))


def encoded_events(events: DataFrame) -> DataFrame:
    q = quantize(event_points(events), EVENT_GRID)
    return q.select("event_id", "ts", "structure_id", morton_encode(["q0", "q1", "q2", "q3"], 4).alias("cell"))


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there and return its result.

    Append results go to files in shared storage; complete results are small aggregates.
    """
    spark = stream.sparkSession
    mark = fresh_path(spark, "stream")
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", f"{mark}/out").option("checkpointLocation", f"{mark}/mark").outputMode("append").trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{mark}/out")
    out = f"{mark}/out"

    def keep(batch: DataFrame, _: int) -> None:
        batch.write.mode("overwrite").parquet(out)

    q = stream.writeStream.foreachBatch(keep).option("checkpointLocation", f"{mark}/mark").outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(out)


def windowed(events: DataFrame, width: str, slide: str | None = None, delay: str = "1 hour") -> DataFrame:
    """Counts and sums by user and time window; tumbling without ``slide``."""
    w = F.window("ts", width, slide) if slide else F.window("ts", width)
    return events.withWatermark("ts", delay).groupBy("user_id", w.alias("w")).agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total")).select("user_id", F.col("w.start").alias("start_ts"), "n", "total")


def sessions(events: DataFrame, gap: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", delay).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n")).select("user_id", F.col("w.start").alias("start_ts"), F.col("w.end").alias("end_ts"), "n")


def deduplicated(events: DataFrame, delay: str = "365 days") -> DataFrame:
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id", "ts", "value")


def running_histogram(events: DataFrame) -> DataFrame:
    return encoded_events(events).groupBy("structure_id", "cell").agg(F.count("*").alias("n"))


def frequency_upkeep(spark: SparkSession, stream: DataFrame, drift: float = 0.2) -> tuple[DataFrame, DataFrame]:
    """Document frequencies merged batch by batch, and the share of cells new to each batch with an alarm.

    The table is rewritten under a new name in each batch; the last name counts.
    """
    mark = fresh_path(spark, "frequency")
    state: dict[str, DataFrame | None] = {"seen": None}
    alarms: list[tuple[int, int, int, bool]] = []

    def merge(batch: DataFrame, number: int) -> None:
        fresh = batch.select("structure_id", "cell").distinct()
        seen = state["seen"]
        all_rows = fresh if seen is None else seen.union(fresh).distinct()
        path = f"{mark}/seen-{number}"
        all_rows.write.mode("overwrite").parquet(path)
        now = spark.read.schema(fresh.schema).parquet(path)
        cells = fresh.select("cell").distinct()
        total = cells.count()
        new = total if seen is None else cells.join(seen.select("cell").distinct(), "cell", "left_anti").count()
        alarms.append((number, total, new, seen is not None and new > drift * total))
        state["seen"] = now

    q = encoded_events(stream).writeStream.foreachBatch(merge).option("checkpointLocation", f"{mark}/mark").trigger(availableNow=True).start()
    q.awaitTermination()
    return state["seen"].groupBy("cell").agg(F.count("*").alias("df")), spark.createDataFrame(alarms, "batch int, cells int, fresh int, alarm boolean")


def scored(events: DataFrame, cell_weights: DataFrame) -> DataFrame:
    """Events with a fixed model's weight of their cell: a stream joined to a table."""
    return encoded_events(events).join(cell_weights, "cell", "left").select("event_id", "cell", F.round(F.coalesce("idf", F.lit(0.0)), 6).alias("idf"))


def click_then_purchase(events: DataFrame, within: str = "1 hour") -> DataFrame:
    """Pairs of a click and a purchase of the same user within an hour after it."""
    click = events.where("event_type = 'click'").select(F.col("user_id").alias("user_id"), F.col("event_id").alias("click_id"), F.col("ts").alias("click_ts")).withWatermark("click_ts", "2 hours")
    buy = events.where("event_type = 'purchase'").select(F.col("user_id").alias("buyer"), F.col("event_id").alias("purchase_id"), F.col("ts").alias("purchase_ts")).withWatermark("purchase_ts", "2 hours")
    return click.join(buy, F.expr(f"user_id = buyer AND purchase_ts >= click_ts AND purchase_ts <= click_ts + interval {within}")).select("user_id", "click_id", "purchase_id")


def late_rows(spark: SparkSession, make: Callable[[DataFrame], DataFrame], first: DataFrame, second: DataFrame, delay: str = "1 hour") -> int:
    """Rows of the second batch that come too late after the first, as the state operator counts them."""
    path = fresh_path(spark, "late")
    first.coalesce(1).write.parquet(f"{path}/in/a")
    stream = spark.readStream.schema(first.schema).option("maxFilesPerTrigger", 1).parquet(f"{path}/in/*")
    agg = make(stream.withWatermark("ts", delay))
    sink = agg.writeStream.format("noop").outputMode("update").option("checkpointLocation", f"{path}/mark")
    sink.trigger(availableNow=True).start().awaitTermination()
    second.coalesce(1).write.parquet(f"{path}/in/b")
    q = sink.trigger(availableNow=True).start()
    q.awaitTermination()
    return sum(op.numRowsDroppedByWatermark for p in q.recentProgress for op in p.stateOperators)
