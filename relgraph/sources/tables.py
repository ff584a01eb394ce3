"""Reading and writing graphs and results."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from relgraph.model import EDGES, UncertainGraph


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edges(spark: SparkSession, path: str, kind: str = "parquet", **options) -> UncertainGraph:
    """An edge list in any format Spark reads, with the schema given, not guessed."""
    return UncertainGraph.of(spark.read.format(kind).schema(EDGES).options(**options).load(path))


def read_table(spark: SparkSession, name: str) -> UncertainGraph:
    """An edge list from a table or view of the catalog."""
    return UncertainGraph.of(spark.table(name))


def literal(spark: SparkSession, rows: list[tuple[int, int, float]]) -> UncertainGraph:
    """A small graph from (src, dst, prob), numbered in order."""
    return UncertainGraph(spark.createDataFrame([(i, *r) for i, r in enumerate(rows)], EDGES))


def save_index(frame: DataFrame, name: str, buckets: int = 64, key: str = "src") -> None:
    """Keep an index as a bucketed table, so that later joins on the key need no shuffle of it."""
    frame.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(name)


def save_results(frame: DataFrame, path: str, by: str | None = None) -> None:
    (frame.write.partitionBy(by) if by else frame.write).mode("overwrite").parquet(path)


def touch(frame: DataFrame) -> None:
    """Work a frame out without keeping it, for timing."""
    frame.write.format("noop").mode("overwrite").save()
