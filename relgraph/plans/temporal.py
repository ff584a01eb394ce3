"""Links in time: the last row at or before a moment, rows close in time, sessions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def asof(left: DataFrame, right: DataFrame, by: str, ts: str, value: str, tie: str) -> DataFrame:
    """left with `last_<value>`: the value of the right row of the same key that is last at or before its time.

    One union and one window instead of a range join, so a key's rows are read once.
    """
    a = left.withColumn("_right", F.lit(0)).withColumn("_value", F.lit(None).cast(right.schema[value].dataType))
    b = right.select(*(F.col(c) if c in (by, ts, tie) else F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns), F.lit(-1).alias("_right"), F.col(value).alias("_value"))
    order = Window.partitionBy(by).orderBy(ts, "_right", tie).rowsBetween(Window.unboundedPreceding, 0)
    both = a.unionByName(b).withColumn(f"last_{value}", F.last("_value", ignorenulls=True).over(order))
    return both.where("_right = 0").drop("_right", "_value")


def close_in_time(events: DataFrame, seconds: int) -> DataFrame:
    """(src, dst, meetings): users with events at most so many seconds apart, the first event giving src.

    A range join by time buckets: an event meets its own bucket and the next, so no two events farther apart
    than two buckets are paired.
    """
    events = events.withColumn("ts", F.col("ts").cast("timestamp"))
    bucket = F.floor(F.unix_micros("ts") / (seconds * 1_000_000))
    a = events.select(F.col("user_id").alias("src"), F.col("event_id").alias("id1"), F.unix_micros("ts").alias("t1"), F.explode(F.array(bucket, bucket + 1)).alias("bucket"))
    b = events.select(F.col("user_id").alias("dst"), F.col("event_id").alias("id2"), F.unix_micros("ts").alias("t2"), bucket.alias("bucket"))
    near = (F.col("t2") >= F.col("t1")) & (F.col("t2") - F.col("t1") <= seconds * 1_000_000) & (F.col("src") != F.col("dst"))
    later = (F.col("t2") > F.col("t1")) | (F.col("id2") > F.col("id1"))
    return a.join(b, "bucket").where(near & later).groupBy("src", "dst").agg(F.count("*").alias("meetings"))


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(user_id, start, events): runs of a user's events without a longer gap."""
    found = events.groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.count("*").alias("events"))
    return found.select("user_id", F.col("w.start").alias("start"), "events")
