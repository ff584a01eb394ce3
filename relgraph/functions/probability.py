"""Edge-probability models."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from relgraph.functions.coins import coin

#: Digits that probabilities are rounded to, so that engines agree on them.
PLACES = 9


def rounded(prob: Column) -> Column:
    return F.round(prob, PLACES)


def inverse_outdegree(edges: DataFrame) -> DataFrame:
    """Each edge gets one over the number of edges that leave its source."""
    return edges.withColumn("prob", rounded(1.0 / F.count("*").over(Window.partitionBy("src"))))


def choice(edges: DataFrame, values: Sequence[float] = (0.1, 0.01, 0.001), seed: int = 0) -> DataFrame:
    """Each edge gets one of the values, evenly at random."""
    at = F.floor(coin(seed, "edge_id") * len(values)).cast("int")
    return edges.withColumn("prob", F.get(F.array(*map(F.lit, values)), at))


def exp_cdf(count: Column, mu: float) -> Column:
    """1 - exp(-count / mu): the more often two nodes met, the likelier their link."""
    return rounded(1 - F.exp(-count / F.lit(float(mu))))


def snapshot_ratio(seen: DataFrame, period: str = "period", keys: Sequence[str] = ("src", "dst")) -> DataFrame:
    """Share of months with the link, from the first month that shows it to the last month of all.

    seen: the keys and a date or timestamp `period`. The last month comes from one aggregate row.
    """
    month = F.trunc(F.col(period), "month")
    last = seen.agg(F.max(month).alias("last"))
    held = seen.groupBy(*keys).agg(F.count_distinct(month).alias("held"), F.min(month).alias("first"))
    held = held.crossJoin(F.broadcast(last))
    span = F.months_between("last", "first").cast("long") + 1
    return held.select(*keys, rounded(F.col("held") / span).alias("prob"))


def three_factor(relevance: Column, informativeness: Column, confidence: Column, least: float = 1e-6) -> Column:
    """Product of three criteria, kept in (0, 1]. How the three combine is a choice made here."""
    return F.least(F.lit(1.0), F.greatest(F.lit(least), relevance * informativeness * confidence))
