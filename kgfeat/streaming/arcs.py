"""Arcs that arrive as a stream: triples from events, activity counts, mining anew per batch."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from kgfeat.api import MiningResult, mine
from kgfeat.params import TYPE, MiningParams

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def read_events(spark: SparkSession, folder: str, files_per_trigger: int = 1) -> DataFrame:
    """Event files of a folder as a stream."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(folder)


def triples_from_events(events: DataFrame, late: str = "1 day") -> DataFrame:
    """(ts, s, p, o): an arc and a class for each event; an event that comes twice within the watermark counts once."""
    once = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
    did = F.struct(F.concat(F.lit("user:"), "user_id").alias("s"), F.lit("did").alias("p"), F.concat(F.lit("event:"), "event_id").alias("o"))
    kind = F.struct(F.concat(F.lit("event:"), "event_id").alias("s"), F.lit(TYPE).alias("p"), F.concat(F.lit("cls:Event/"), "event_type").alias("o"))
    return once.select("ts", F.explode(F.array(did, kind)).alias("t")).select("ts", "t.s", "t.p", "t.o")


def activity(events: DataFrame, kind: str = "tumbling", late: str = "1 day") -> DataFrame:
    """(start, end, user_id, n): arcs of each user by day, by day every six hours, or by session."""
    ts = events.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", late)
    w = {"tumbling": F.window("ts", "1 day"), "sliding": F.window("ts", "1 day", "6 hours"), "session": F.session_window("ts", "2 hours")}[kind]
    return ts.groupBy(w.alias("w"), "user_id").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), "user_id", "n")


def remine(stream: DataFrame, stored: str, seeds: DataFrame, params: MiningParams, done: Callable[[int, MiningResult], None]):
    """For foreachBatch: add a batch of triples to the stored ones and mine them all anew.

    A batch is a folder of its own, so one that is repeated replaces itself.
    """

    def step(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        batch.select("s", "p", "o").write.mode("overwrite").parquet(f"{stored}/batch={number}")
        done(number, mine(spark, spark.read.parquet(stored).select("s", "p", "o"), seeds, params))

    return stream.writeStream.foreachBatch(step)
