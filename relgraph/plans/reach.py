"""Reach when every edge exists: hop distances, an upper bound of any reliability, and pruning."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relgraph.model import UncertainGraph
from relgraph.plans.iterate import grow


def hops(g: UncertainGraph, sources: DataFrame, limit: int | None = None) -> DataFrame:
    """(s, node, hops): breadth-first distance of every node from each source, the source itself at 0."""
    links = g.edges.select("src", "dst").distinct()
    start = sources.select(F.col("s"), F.col("s").alias("node"), F.lit(0).alias("hops")).distinct()

    def step(fresh, seen, n):
        found = fresh.join(links, fresh.node == links.src).select("s", F.col("dst").alias("node")).distinct()
        return found.join(seen.select("s", "node"), ["s", "node"], "left_anti").withColumn("hops", F.lit(n))

    return grow(start, step, limit, "hops")[0]


def reachable(g: UncertainGraph, pairs: DataFrame) -> DataFrame:
    """(pair_id, s, t, reachable): whether any world lets s reach t."""
    found = hops(g, pairs.select("s")).select(F.col("s").alias("s2"), F.col("node").alias("t2"))
    joined = pairs.join(found, (F.col("s") == F.col("s2")) & (F.col("t") == F.col("t2")), "left")
    return joined.select("pair_id", "s", "t", F.col("t2").isNotNull().alias("reachable"))


def relevant(g: UncertainGraph, pairs: DataFrame) -> DataFrame:
    """(pair_id, edge_id, src, dst, prob): edges on some way from s to t; no other edge matters to the pair."""
    ahead = hops(g, pairs.select("s")).select("s", "node")
    back = UncertainGraph(g.edges.select("edge_id", F.col("dst").alias("src"), F.col("src").alias("dst"), "prob"))
    behind = hops(back, pairs.select(F.col("t").alias("s"))).select(F.col("s").alias("t"), F.col("node").alias("node2"))
    found = pairs.select("pair_id", "s", "t").join(ahead, "s").join(g.edges, F.col("node") == F.col("src"))
    return found.join(behind, (found.t == behind.t) & (found.dst == behind.node2)).select("pair_id", "edge_id", "src", "dst", "prob")


HOPS_SQL = """hop AS (SELECT s, s AS node, 0 AS hops FROM starts
  UNION SELECT h.s, e.dst, h.hops + 1 FROM hop h JOIN g e ON h.node = e.src WHERE h.hops < {limit}),
dist AS (SELECT s, node, min(hops) AS hops FROM hop GROUP BY ALL)"""
