"""Fixpoints by rounds. The state of a round is written to a shared folder, which ends its lineage."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster names for checkpoints; only a local session that names none gets one of its own."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="rounds-"))
        found = spark.sparkContext.getCheckpointDir()
    return found.rstrip("/")


class Store:
    """A growing table in the shared folder: what is added in a round is read back as that round's rows."""

    def __init__(self, spark: SparkSession, tag: str):
        self.spark, self.path, self.schema, self.rounds = spark, f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}", None, 0

    def add(self, rows: DataFrame) -> DataFrame:
        part = f"{self.path}/round={self.rounds}"
        rows.write.parquet(part)
        self.schema, self.rounds = rows.schema, self.rounds + 1
        return self.spark.read.schema(rows.schema).parquet(part)

    def all(self) -> DataFrame:
        """Rows of all rounds."""
        paths = [f"{self.path}/round={i}" for i in range(self.rounds)]
        return self.spark.read.schema(self.schema).parquet(*paths)


def written(rows: DataFrame, tag: str = "rows") -> DataFrame:
    """The rows from a written table."""
    return Store(rows.sparkSession, tag).add(rows)


def grow(start: DataFrame, step: Callable[[DataFrame, DataFrame, int], DataFrame], limit: int | None = None, tag: str = "reach") -> tuple[DataFrame, int]:
    """Add step(new rows, all rows, round) until nothing new comes or the limit of rounds is reached.

    The step itself must leave out rows that are there already. Returns all rows and the rounds taken.
    """
    store = Store(start.sparkSession, tag)
    fresh, n = store.add(start), 0
    while limit is None or n < limit:
        fresh = store.add(step(fresh, store.all(), n + 1))
        n += 1
        if fresh.isEmpty():
            break
    return store.all(), n
