"""Query sets: sources at random and for each a target at an exact distance."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from relgraph.functions.coins import rank_key, rank_key_sql
from relgraph.model import UncertainGraph
from relgraph.plans.iterate import written
from relgraph.plans.reach import hops

#: Sources looked at first for each pair that is asked for; as many more each time as pairs are still missing.
SPARE = 4


def pairs(g: UncertainGraph, n: int, at: int = 2, seed: int = 1) -> DataFrame:
    """(pair_id, s, t, hops): n pairs, the same for the same graph and seed, numbered from 1.

    Sources are taken in the order of their hash, only their neighbourhoods are searched, and more are taken until
    n of them have a node at the distance or none is left. So there are fewer pairs only if the graph has no more.
    """
    every = written(g.edges.select(F.col("src").alias("s")).distinct(), "every")
    many, asked = every.count(), SPARE * n
    while True:
        sources = every.orderBy(rank_key(seed, "s"), "s").limit(asked)
        found = hops(g, written(sources, "sources"), at).where(F.col("hops") == at)
        target = Window.partitionBy("s").orderBy(rank_key(seed, "s", "node"), "node")
        one = written(found.withColumn("i", F.row_number().over(target)).where("i = 1").select("s", "node"), "targets")
        if asked >= many or one.count() >= n:
            break
        asked *= SPARE
    order = Window.orderBy(rank_key(seed, "s"), "s")  # over at most `asked` rows
    numbered = one.select(F.row_number().over(order).cast("int").alias("pair_id"), "s", F.col("node").alias("t"), F.lit(at).alias("hops"))
    return written(numbered.where(F.col("pair_id") <= n), "pairs")


def pairs_sql(graph: str, n: int, at: int = 2, seed: int = 1) -> str:
    """CTEs g and pairs for DuckDB; distances by set recursion."""
    return f"""g AS ({graph}),
starts AS (SELECT DISTINCT src AS s FROM g),
hop AS (SELECT s, s AS node, 0 AS hops FROM starts UNION SELECT h.s, e.dst, h.hops + 1 FROM hop h JOIN g e ON h.node = e.src WHERE h.hops < {at}),
dist AS (SELECT s, node, min(hops) AS hops FROM hop GROUP BY ALL),
one AS (SELECT s, node AS t FROM dist WHERE hops = {at} QUALIFY row_number() OVER (PARTITION BY s ORDER BY {rank_key_sql(seed, "s", "node")}, node) = 1),
pairs AS (SELECT CAST(row_number() OVER (ORDER BY {rank_key_sql(seed, "s")}, s) AS INTEGER) AS pair_id, s, t, {at} AS hops FROM one QUALIFY pair_id <= {n})"""
