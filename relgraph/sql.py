"""SQL surface: views of a graph and its pairs, and table functions."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from relgraph.model import UncertainGraph
from relgraph.operators import kernels


@udtf(returnType="world: int")
class SkipFirings:
    """Worlds among k in which an edge exists, by geometric gaps; for a lateral join with the edges."""

    def eval(self, edge_id: int, prob: float, k: int, seed: int) -> Iterator[tuple[int]]:
        rng = np.random.default_rng((seed, edge_id))
        _, worlds = kernels.firing_list(np.array([prob]), k, rng)
        for w in worlds.tolist():
            yield (w,)


def publish(spark: SparkSession, g: UncertainGraph, pairs) -> None:
    """Register views edges and pairs, and the functions skip_firings(edge_id, prob, k, seed) and reliability(method, k).

    A graph of up to kernels.MOST_EDGES edges travels inside `reliability`; larger ones need the DataFrame interface.
    """
    g.edges.createOrReplaceTempView("edges")
    pairs.createOrReplaceTempView("pairs")
    spark.udtf.register("skip_firings", SkipFirings)
    if g.edges.count() > kernels.MOST_EDGES:
        raise ValueError("the graph is too large for SQL functions; use kernels.solve")
    columns = g.edges.select("src", "dst", "prob").toArrow()
    local = kernels.Local.of(*(c.to_numpy() for c in columns.columns))
    ends = [(r["pair_id"], r["s"], r["t"]) for r in pairs.select("pair_id", "s", "t").collect()]  # a query set: few rows by nature

    @udtf(returnType="pair_id: int, s: long, t: long, k: int, r_hat: double, probes: long")
    class Reliability:
        def eval(self, method: str, k: int) -> Iterator[tuple]:
            for p, s, t in ends:
                a = kernels.answer(local, method, s, t, k, (1, p), {})
                yield p, s, t, k, float(a.value), int(a.probes)

    spark.udtf.register("reliability", Reliability)
