"""Streams over ``events``: windows, late rows, edge upkeep, stateful degrees, query streams and joins."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from pyspark.sql.types import IntegerType

from seedspread.runtime import discard, new_folder, scratch_path, table

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, sf_dir: str, files_per_trigger: int = 4) -> DataFrame:
    """The events table as a file stream with a fixed schema; ``ts`` is a timestamp."""
    schema = table(spark, sf_dir, "events").schema
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", "events.parquet*").parquet(sf_dir)
    return stream.withColumn("ts", F.col("ts").cast("timestamp"))


def run_to_end(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Drain a stream into Parquet (append) or its last full answer (complete, update) and return the rows.

    ``availableNow`` handles what is there in bounded batches and stops; the checkpoint and the result live in
    the shared folder.
    """
    spark = stream.sparkSession
    place, out = scratch_path(spark, "stream-state"), scratch_path(spark, "stream-out")
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", place).trigger(availableNow=True)
    if mode == "append":
        query = writer.format("parquet").start(out)
    else:
        query = writer.foreachBatch(lambda batch, n: batch.withColumn("_batch", F.lit(n)).write.mode("append").parquet(out)).start()
    query.awaitTermination()
    rows = spark.read.schema(stream.schema.add("_batch", IntegerType()) if mode != "append" else stream.schema).parquet(out)
    discard(spark, place)
    return rows


def tumbling(events: DataFrame, length: str = "1 hour", late: str = "2 hours") -> DataFrame:
    counted = events.withWatermark("ts", late).groupBy(F.window("ts", length).alias("w"), "event_type").agg(F.count("*").alias("n"))
    return counted.select(F.col("w.start").alias("start"), "event_type", "n")


def sliding(events: DataFrame, length: str = "1 hour", step: str = "15 minutes", late: str = "2 hours") -> DataFrame:
    counted = events.withWatermark("ts", late).groupBy(F.window("ts", length, step).alias("w")).agg(F.count("*").alias("n"))
    return counted.select(F.col("w.start").alias("start"), "n")


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "2 hours") -> DataFrame:
    counted = events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("n"))
    return counted.select("user_id", F.col("w.start").alias("start"), "n")


def deduplicated(events: DataFrame, late: str = "2 hours") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def new_edges(events: DataFrame) -> DataFrame:
    """User-hour edges of a batch, as in the batch builder."""
    hour = F.floor(F.unix_micros("ts") / 3_600_000_000)
    return events.select((F.col("user_id") * 2).alias("src"), (hour * 2 + 1).alias("dst")).distinct()


class EdgeUpkeep:
    """Keeps the edge set of a growing graph: each batch adds only edges that no other batch brought.

    What is there is read from storage and a batch never compares with itself, so a replayed batch, or one
    that a restarted driver repeats, leaves the same edges.
    """

    def __init__(self, spark: SparkSession, path: str | None = None):
        self.spark, self.path = spark, path or scratch_path(spark, "edges")
        new_folder(spark, self.path)

    def apply(self, batch: DataFrame, number: int) -> None:
        others = self._stored().filter(F.col("batch") != number).select("src", "dst")
        new_edges(batch).join(others, ["src", "dst"], "left_anti").write.mode("overwrite").parquet(f"{self.path}/batch={number}")

    def _stored(self) -> DataFrame:
        return self.spark.read.schema("src long, dst long, batch int").parquet(self.path)

    def edges(self) -> DataFrame:
        return self._stored().select("src", "dst").distinct()

    def run(self, stream: DataFrame) -> DataFrame:
        place = scratch_path(self.spark, "stream-state")
        stream.writeStream.foreachBatch(self.apply).option("checkpointLocation", place).trigger(availableNow=True).start().awaitTermination()
        return self.edges()


def degree_counter(events: DataFrame) -> DataFrame:
    """Running number of distinct hours per user, by a stateful operator keyed by vertex."""

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        seen = set(state.get[0]) if state.exists else set()
        for pdf in batches:
            seen.update(int(h) for h in pdf["hour"])
        state.update((sorted(seen),))
        yield pd.DataFrame({"user_id": [key[0]], "deg": [len(seen)]})

    hours = events.select("user_id", F.floor(F.unix_micros("ts") / 3_600_000_000).alias("hour"))
    return hours.groupBy("user_id").applyInPandasWithState(update, "user_id long, deg long", "hours array<long>", "update", GroupStateTimeout.NoTimeout)


def answer_queries(stream: DataFrame, answer) -> DataFrame:
    """A stream of query rows, each micro-batch answered by ``answer(batch)``; returns all answers."""
    spark = stream.sparkSession
    place, out = scratch_path(spark, "stream-state"), scratch_path(spark, "answers")
    schema = []

    def one(batch: DataFrame, number: int) -> None:
        found = answer(batch)
        schema.append(found.schema)
        found.write.mode("overwrite").parquet(f"{out}/batch={number}")

    stream.writeStream.foreachBatch(one).option("checkpointLocation", place).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(schema[0]).parquet(f"{out}/batch=*")


def with_static(events: DataFrame, static: DataFrame) -> DataFrame:
    """Stream joined with a table on user."""
    return events.join(static, "user_id")


def followed_by(events: DataFrame, minutes: int = 30) -> DataFrame:
    """Stream with stream: clicks and the same user's views at most ``minutes`` later."""
    click = events.filter("event_type = 'click'").select("user_id", F.col("event_id").alias("click"), F.col("ts").alias("t1")).withWatermark("t1", "2 hours")
    view = events.filter("event_type = 'view'").select(F.col("user_id").alias("u2"), F.col("event_id").alias("view"), F.col("ts").alias("t2")).withWatermark("t2", "2 hours")
    on = (F.col("user_id") == F.col("u2")) & (F.col("t2") >= F.col("t1")) & (F.col("t2") <= F.col("t1") + F.expr(f"INTERVAL {minutes} MINUTES"))
    return click.join(view, on).select("click", "view")
