"""Streams of events: windowed co-occurrence, the counts that similarity needs, and user state."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vpatterns.operators.prepare import shared_folder


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table read as a stream; its times have no zone and are taken as UTC."""
    schema = spark.read.parquet(f"{sf_dir}/events.parquet").schema
    stream = spark.readStream.schema(schema).option("pathGlobFilter", "*events*").option("recursiveFileLookup", "true").parquet(sf_dir)
    return stream.withColumn("ts", F.to_utc_timestamp(F.col("ts").cast("timestamp"), spark.conf.get("spark.sql.session.timeZone")))


def tumbling(stream: DataFrame, width: str = "1 day", late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", width), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sliding(stream: DataFrame, width: str = "2 days", step: str = "1 day", late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).groupBy(F.window("ts", width, step), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("window.start").alias("start"), "event_type", "n")


def sessions(stream: DataFrame, gap: str = "12 hours", late: str = "1 hour") -> DataFrame:
    got = stream.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return got.select(F.col("session_window.start").alias("start"), "user_id", "n")


def deduplicated(stream: DataFrame, late: str = "1 hour") -> DataFrame:
    return stream.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def click_to_purchase(stream: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream join: purchases within a time after a click of the same user."""
    click = stream.where("event_type = 'click'").select(F.col("user_id").alias("u"), F.col("ts").alias("t1"), F.col("event_id").alias("click")).withWatermark("t1", within)
    buy = stream.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("t2"), F.col("event_id").alias("purchase")).withWatermark("t2", within)
    return click.join(buy, F.expr(f"u = user_id and t2 >= t1 and t2 <= t1 + interval {within}")).select("click", "purchase")


def with_segment(stream: DataFrame, customers: DataFrame) -> DataFrame:
    """Stream-static join: the attributes of the event's user."""
    return stream.join(customers, stream.user_id == customers.c_custkey, "left")


#: The bit of event types that are not among the named ones.
OTHER = 62


def level_masks(stream: DataFrame, kinds: list[str], expire: str | None = None) -> DataFrame:
    """user_id, mask: the running set of event types of each user, kept as state.

    Types that are not named share one bit (OTHER). With ``expire`` (milliseconds as text
    or a number) a user not seen for so long is forgotten and begins anew.
    """
    if len(kinds) > OTHER:
        raise ValueError(f"{OTHER} kinds at most")
    bit = {k: 1 << i for i, k in enumerate(kinds)}
    wait = int(expire) if expire else 0

    def update(key, frames, state):
        if state.hasTimedOut:
            state.remove()
            return
        mask = state.get[0] if state.exists else 0
        for x in frames:
            for kind in x["event_type"].unique():
                mask |= bit.get(kind, 1 << OTHER)
        state.update((mask,))
        if wait:
            state.setTimeoutDuration(wait)
        yield pd.DataFrame({"user_id": [key[0]], "mask": [mask]})

    return stream.groupBy("user_id").applyInPandasWithState(update, "user_id long, mask long", "mask long", "update", "ProcessingTimeTimeout" if wait else "NoTimeout")


def finished(df: DataFrame, mode: str = "complete") -> DataFrame:
    """Run a stream over what is there; its result is a table in the folder that all executors share.

    Appended rows go to the file sink. Complete results replace the one before, updates are
    kept batch by batch; a batch that is run again replaces its own files.
    """
    spark, folder = df.sparkSession, shared_folder(df.sparkSession, "stream")
    out = f"{folder}/out"
    writer = df.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True)
    if mode == "append":
        writer.format("parquet").option("path", out).start().awaitTermination()
        return spark.read.schema(df.schema).parquet(out)

    def keep(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(out if mode == "complete" else f"{out}/batch={number}")

    writer.foreachBatch(keep).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(out).select(*df.columns)


class CoOccurrence:
    """Presence cells of user-days, from which joint counts are added up batch by batch.

    Rows of one user-day may come in several batches, so the cells themselves are kept. A
    batch writes only cells that are new, to files of its own, and compares with the days
    it touches; run again, it replaces its own files.
    """

    KEY = ("user_id", "day", "event_type")

    def __init__(self):
        self.folder: str | None = None
        self.batches: list[int] = []

    def cells(self, spark: SparkSession, schema, numbers) -> DataFrame | None:
        paths = [f"{self.folder}/cells/{n}" for n in numbers]
        return spark.read.schema(schema).parquet(*paths) if paths else None

    def add(self, batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        new = batch.select("user_id", F.to_date("ts").alias("day"), "event_type").distinct()
        have = self.cells(spark, new.schema, [n for n in self.batches if n < number])
        if have is not None:
            ends = new.agg(F.min("day").alias("a"), F.max("day").alias("b")).first()
            if ends["a"] is not None:
                have = have.where(F.col("day").between(F.lit(ends["a"]), F.lit(ends["b"])))
            new = new.join(have, list(self.KEY), "left_anti")
        new.write.mode("overwrite").parquet(f"{self.folder}/cells/{number}")
        if number not in self.batches:
            self.batches.append(number)

    def run(self, stream: DataFrame) -> DataFrame:
        spark = stream.sparkSession
        self.folder = shared_folder(spark, "cooccurrence")
        q = stream.writeStream.foreachBatch(self.add).option("checkpointLocation", f"{self.folder}/checkpoint").trigger(availableNow=True).start()
        q.awaitTermination()
        schema = stream.select("user_id", F.to_date("ts").alias("day"), "event_type").schema
        got = self.cells(spark, schema, self.batches)
        return got if got is not None else spark.createDataFrame([], schema)
