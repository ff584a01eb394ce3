"""Uncertain graphs: directed edges that exist independently, each with a probability."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

EDGES = T.StructType(
    [
        T.StructField("edge_id", T.LongType(), False), T.StructField("src", T.LongType(), False),
        T.StructField("dst", T.LongType(), False), T.StructField("prob", T.DoubleType(), False),
    ]
)
PAIRS = "pair_id int, s long, t long, hops int"
#: Node ids below this number give edge ids that name both ends.
ID_BITS = 31


class GraphError(ValueError):
    pass


def edge_key(src: str = "src", dst: str = "dst"):
    """Edge id that names both ends; ids must be below 2 to the 31."""
    return (F.shiftleft(F.col(src).cast("long"), 32) + F.col(dst).cast("long")).alias("edge_id")


@dataclass(frozen=True)
class UncertainGraph:
    """Edges (edge_id, src, dst, prob). A link in both directions is two edges with ids of their own."""

    edges: DataFrame

    @staticmethod
    def of(edges: DataFrame) -> UncertainGraph:
        """From src, dst, prob and maybe edge_id; self loops are dropped, as they never change what is reached."""
        edges = edges.where("src <> dst")
        key = F.col("edge_id").cast("long").alias("edge_id") if "edge_id" in edges.columns else edge_key()
        return UncertainGraph(edges.select(key, F.col("src").cast("long"), F.col("dst").cast("long"), F.col("prob").cast("double")))

    @property
    def nodes(self) -> DataFrame:
        return self.edges.select(F.col("src").alias("node")).union(self.edges.select("dst")).distinct()

    def validate(self) -> UncertainGraph:
        """Raise GraphError for nulls, probabilities outside (0, 1] or repeated edge ids; two small aggregates."""
        bad = (F.isnull("edge_id") | F.isnull("src") | F.isnull("dst") | F.isnull("prob") | F.isnan("prob")).cast("int")
        out = F.coalesce((F.col("prob") <= 0) | (F.col("prob") > 1), F.lit(False)).cast("int")
        nulls, outside = self.edges.agg(F.coalesce(F.sum(bad), F.lit(0)), F.coalesce(F.sum(out), F.lit(0))).first()
        twice = self.edges.groupBy("edge_id").count().where("count > 1").limit(1).count()
        if nulls or outside or twice:
            raise GraphError(f"{nulls} edges with nulls, {outside} with a probability outside (0, 1], repeated ids: {bool(twice)}")
        return self

    def merged(self) -> UncertainGraph:
        """Parallel edges as one: it exists if any of them does."""
        miss = F.exp(F.sum(F.log1p(-F.when(F.col("prob") < 1, F.col("prob")).otherwise(0.0))))
        sure = F.max(F.col("prob") >= 1)
        edges = self.edges.groupBy("src", "dst").agg(F.min("edge_id").alias("edge_id"), F.when(sure, 1.0).otherwise(1 - miss).alias("prob"))
        return UncertainGraph(edges.select("edge_id", "src", "dst", "prob"))

    def profile(self) -> DataFrame:
        """Nodes, edges, and mean, spread and quartiles of the probabilities: one row."""
        p = self.edges.agg(
            F.count("*").alias("edges"), F.avg("prob").alias("mean"), F.stddev("prob").alias("sd"),
            F.percentile("prob", F.lit(0.25)).alias("q1"), F.percentile("prob", F.lit(0.5)).alias("q2"), F.percentile("prob", F.lit(0.75)).alias("q3"),
        )
        return self.nodes.agg(F.count("*").alias("nodes")).crossJoin(p)
