"""Skip sampling as sets: the worlds in which an edge exists, listed by geometric gaps.

Instead of k coins an edge takes about k times its probability. The j-th firing lies at the sum of the first
j gaps, each one more than the failures before the next success. The kernels module has the form with counters at
nodes and the uncorrected readings.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from relgraph.functions.coins import coin, coin_sql, gap_sql, geometric_gap
from relgraph.model import UncertainGraph
from relgraph.operators import mc
from relgraph.plans.iterate import written

#: Draws listed for an edge: its expected firings and ten standard deviations more.
DRAWS = "least({k}, CAST(ceil({k} * {p} + 10 * sqrt({k} * {p}) + 16) AS INT))"


def firings(g: UncertainGraph, k: int, seed: int = 1, rep: int = 0) -> DataFrame:
    """(edge_id, src, dst, world): the worlds of each edge."""
    draws = F.expr(DRAWS.format(k=k, p="prob"))
    rows = g.edges.withColumn("draw", F.explode(F.sequence(F.lit(1), draws)))
    gap = geometric_gap(coin(seed, F.lit("gap"), F.lit(rep), "edge_id", "draw"), F.col("prob"))
    order = Window.partitionBy("edge_id").orderBy("draw").rowsBetween(Window.unboundedPreceding, 0)
    rows = rows.withColumn("world", F.sum(gap + 1).over(order) - 1).where(F.col("world") < k)
    return rows.select("edge_id", "src", "dst", F.col("world").cast("int").alias("world"))


def reach(g: UncertainGraph, pairs: DataFrame, k: int, seed: int = 1, early_stop: bool = True, max_hops: int | None = None) -> DataFrame:
    """Estimates over the firing lists of one repeat."""
    drawn = firings(g, k, seed).select("src", "dst", F.col("world").alias("w"), F.lit(0).alias("r"))
    return mc.reach(g, pairs, k, seed, early_stop=early_stop, max_hops=max_hops, worlds=written(drawn, "firings"), method="skip")


def reach_sql(workload: str, k: int, seed: int = 1) -> str:
    """The same for DuckDB."""
    draws = DRAWS.format(k=k, p="prob")
    gap = gap_sql(coin_sql(seed, "'gap'", "0", "edge_id", "draw"), "prob")
    fire = f"""{workload},
drawn AS (SELECT edge_id, prob, unnest(range(1, {draws} + 1)) AS draw FROM g),
fire AS (SELECT edge_id, world FROM (SELECT edge_id, sum({gap} + 1) OVER (PARTITION BY edge_id ORDER BY draw) - 1 AS world FROM drawn) WHERE world < {k})"""
    return mc.reach_sql(fire, k, seed, method="skip", present="(e.edge_id, w.world) IN (SELECT edge_id, world FROM fire)")
