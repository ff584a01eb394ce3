"""Snapshot ratios from a stream of sightings.

A sighting says that a link was seen at a time. Repeated events are dropped within the watermark, windows of a
day count as snapshots, and a link's state is its first day and how many days showed it.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from relgraph.plans.iterate import shared_dir, written

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
LINKS = "src long, dst string, first_day long, days long, last_day long"
LATE = "2 hours"


def source(spark: SparkSession, path: str, per_trigger: int = 1) -> DataFrame:
    """Events as a stream of files: those of a folder, or one file alone."""
    folder, _, name = path.rstrip("/").rpartition("/")
    reader = spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", per_trigger)
    found = reader.option("pathGlobFilter", name).parquet(folder) if _is_file(spark, path) else reader.parquet(path)
    return found


def _is_file(spark: SparkSession, path: str) -> bool:
    """By the store's own listing."""
    jvm = spark.sparkContext._jvm
    place = jvm.org.apache.hadoop.fs.Path(path)
    return place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(place).isFile()


def windowed(events: DataFrame, length: str = "1 day", slide: str | None = None, late: str = LATE) -> DataFrame:
    """(start, src, dst, n): sightings in tumbling or sliding windows; rows behind the watermark are dropped."""
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    kept = events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])
    return kept.groupBy(w.alias("w"), F.col("user_id").alias("src"), F.col("event_type").alias("dst")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "src", "dst", "n")


def links(events: DataFrame, late: str = LATE) -> DataFrame:
    """(src, dst, first_day, days, last_day) of every link that gained a day in a batch; the state is a few numbers and days."""
    days = events.withWatermark("ts", late).select(F.col("user_id").alias("src"), F.col("event_type").alias("dst"), F.floor(F.unix_seconds("ts") / 86400).alias("day"))

    def follow(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        seen = set(state.get[0]) if state.exists else set()
        before = len(seen)
        for batch in batches:
            seen.update(int(d) for d in batch["day"].unique())
        state.update((sorted(seen),))
        if len(seen) > before:
            yield pd.DataFrame({"src": [key[0]], "dst": [key[1]], "first_day": [min(seen)], "days": [len(seen)], "last_day": [max(seen)]})

    return days.groupBy("src", "dst").applyInPandasWithState(follow, LINKS, "days array<long>", "update", GroupStateTimeout.NoTimeout)


def run(spark: SparkSession, stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there and return what it wrote, with the batch that wrote it."""
    place = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"

    def keep(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{place}/out/part={number}")

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{place}/log").trigger(availableNow=True).foreachBatch(keep).start()
    query.awaitTermination()
    return spark.read.schema(T.StructType([*stream.schema.fields, T.StructField("batch", T.IntegerType())])).option("recursiveFileLookup", True).parquet(f"{place}/out")


def ratios(spark: SparkSession, path: str) -> DataFrame:
    """(src, dst, prob): days seen by days from the first sighting to the last day of all, from the stream's last word on each link."""
    written = run(spark, links(source(spark, path)), "update")
    last = written.groupBy("src", "dst").agg(F.max_by(F.struct("first_day", "days", "last_day"), "batch").alias("l")).select("src", "dst", "l.*")
    end = last.agg(F.max("last_day").alias("end"))
    return last.crossJoin(F.broadcast(end)).select("src", "dst", F.round(F.col("days") / (F.col("end") - F.col("first_day") + 1), 9).alias("prob"))


def coactive(left: DataFrame, right: DataFrame, late: str = LATE, seconds: int = 300) -> DataFrame:
    """(src, dst, ts): an event of one stream and a later one of another user in a second stream, joined by a time bound.

    Streams join on an equality, here a time bucket; an event meets its own bucket and the next.
    """
    bucket = F.floor(F.unix_micros("ts") / (seconds * 1_000_000))
    a = left.withWatermark("ts", late).select(F.col("user_id").alias("src"), "ts", F.explode(F.array(bucket, bucket + 1)).alias("bucket"))
    b = right.withWatermark("ts", late).select(F.col("user_id").alias("dst"), F.col("ts").alias("ts2"), bucket.alias("bucket2"))
    bound = F.expr(f"bucket = bucket2 AND ts2 >= ts AND ts2 <= ts + INTERVAL {seconds} SECONDS AND src <> dst")
    return a.join(b, bound).select("src", "dst", "ts")


def named(events: DataFrame, nodes: DataFrame) -> DataFrame:
    """A stream with the columns of a static node table (node, ...)."""
    return events.join(nodes, F.col("user_id") == F.col("node"), "left")


def refresh_on(spark: SparkSession, stream: DataFrame, rebuild) -> int:
    """Call rebuild(batch, epoch) for each batch, so that an index follows the edges; returns the number of batches."""
    place, count = f"{shared_dir(spark)}/refresh-{uuid.uuid4().hex}", [0]

    def each(batch: DataFrame, number: int) -> None:
        count[0] += 1
        rebuild(written(batch, "batch"), number + 1)  # all of a batch is read, whatever the callback does

    stream.writeStream.outputMode("update").option("checkpointLocation", place).trigger(availableNow=True).foreachBatch(each).start().awaitTermination()
    return count[0]
