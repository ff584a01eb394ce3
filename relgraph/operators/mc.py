"""Plain sampling: worlds by coins, answers by search; all in DataFrame operations.

Worlds are keyed by (rep, world, edge), so pairs share the worlds of a repeat. A pair with s = t has
reliability one without any search.

Searches that toss coins as they go are whole ones in the workers, to which a graph of up to kernels.MOST_EDGES edges is sent; over a
larger one, or worlds drawn before, all searches advance by a join a hop, each hop a round of jobs.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relgraph.functions.coins import coin, coin_sql, coins_of
from relgraph.model import UncertainGraph
from relgraph.operators import kernels
from relgraph.plans.iterate import grow, written


def estimates(pairs: DataFrame, hits: DataFrame, k: int, reps: int, method: str) -> DataFrame:
    """(method, pair_id, s, t, rep, k, hits, r_hat) for every pair and repeat, those without a hit too."""
    spark = pairs.sparkSession
    every = pairs.select("pair_id", "s", "t").crossJoin(spark.range(reps).select(F.col("id").cast("int").alias("rep")))
    counted = hits.groupBy("pair_id", "rep").agg(F.count("*").alias("hits"))
    found = F.when(F.col("s") == F.col("t"), F.lit(k)).otherwise(F.coalesce("hits", F.lit(0))).cast("long")
    out = every.join(counted, ["pair_id", "rep"], "left").withColumn("hits", found)
    return out.select(F.lit(method).alias("method"), "pair_id", "s", "t", "rep", F.lit(k).alias("k"), "hits", (F.col("hits") / F.lit(k)).alias("r_hat"))


def starts(pairs: DataFrame, k: int, reps: int) -> DataFrame:
    spark = pairs.sparkSession
    worlds = spark.range(k).select(F.col("id").cast("int").alias("world")).crossJoin(spark.range(reps).select(F.col("id").cast("int").alias("rep")))
    return pairs.where("s <> t").select("pair_id", "s", "t").crossJoin(worlds).select("pair_id", "rep", "world", F.col("s").alias("node"), "t")


STATE = ["pair_id", "rep", "world", "node"]


class World:
    """The edges of one world met so far; each coin is tossed once."""

    def __init__(self, g: kernels.Local, ids: np.ndarray, *key: int):
        self.g, self.ids, self.key = g, ids, key
        self.tossed, self.on = np.zeros(len(ids), bool), np.zeros(len(ids), bool)

    def open(self, e: np.ndarray) -> np.ndarray:
        """Those of the edges that exist."""
        new = e[~self.tossed[e]]
        self.on[new] = coins_of(self.ids[new].tolist(), *self.key) < self.g.prob[new]
        self.tossed[new] = True
        return e[self.on[e]]

    def hit(self, s: int, t: int, early_stop: bool, max_hops: int | None) -> bool:
        """Whether t is reached from s."""
        a, b = self.g.at(s), self.g.at(t)
        if a < 0 or b < 0:
            return False
        seen, place = np.zeros(len(self.g.names), bool), np.empty(len(self.g.names), np.int64)
        seen[a], fresh, n = True, np.array([a]), 0
        while len(fresh) and (max_hops is None or n < max_hops) and not (early_stop and seen[b]):
            found = self.g.dst[self.open(self.g.edges_of(fresh)[0])]
            fresh = kernels.once(found[~seen[found]], place)
            seen[fresh] = True
            n += 1
        return bool(seen[b])


def _sent(edges: DataFrame, tasks: DataFrame, seed: int, early_stop: bool, max_hops: int | None) -> DataFrame:
    """(pair_id, rep, world) of the searches (pair_id, rep, world, node, t) that hit, as whole searches in the workers."""
    spark = edges.sparkSession
    edge_id, src, dst, prob = (c.to_numpy() for c in edges.toArrow().columns)
    g, order = kernels.Local.placed(src, dst, prob)
    shared = spark.sparkContext.broadcast((g, edge_id[order]))

    def run(batches):
        world = None
        for batch in batches:
            hits = []
            for r in batch.to_pylist():
                if world is None or world.key != (seed, r["rep"], r["world"]):
                    world = World(*shared.value, seed, r["rep"], r["world"])
                hits.append(world.hit(r["node"], r["t"], early_stop, max_hops))
            yield batch.select(["pair_id", "rep", "world"]).filter(pa.array(hits, pa.bool_()))

    parts = spark.sparkContext.defaultParallelism * 2
    tasks = tasks.repartition(parts, F.xxhash64("rep", "world")).sortWithinPartitions("rep", "world")  # the pairs of a world one after the other
    return tasks.mapInArrow(run, tasks.select("pair_id", "rep", "world").schema)


def reach(
    g: UncertainGraph, pairs: DataFrame, k: int, seed: int = 1, reps: int = 1, mode: str = "frontier",
    early_stop: bool = True, max_hops: int | None = None, fast: bool = False, worlds: DataFrame | None = None, method: str = "mc",
) -> DataFrame:
    """Share of worlds in which t is reached from s.

    mode 'frontier' tosses a coin when the search meets an edge, 'materialised' draws whole worlds first.
    `worlds` (src, dst, w, r) are worlds drawn elsewhere. early_stop ends a world once t is reached; max_hops
    counts only ways of so many edges.
    """
    edges = g.edges.select("edge_id", "src", "dst", "prob")
    drawn = worlds
    if mode == "frontier" and worlds is None and not fast and edges.count() <= kernels.MOST_EDGES:
        return estimates(pairs, _sent(edges, starts(pairs, k, reps), seed, early_stop, max_hops), k, reps, method)
    if worlds is not None:
        mode = "given"
    elif mode == "materialised":
        spark = pairs.sparkSession
        all_ = spark.range(k).select(F.col("id").cast("int").alias("w")).crossJoin(spark.range(reps).select(F.col("id").cast("int").alias("r")))
        drawn = edges.crossJoin(all_).where(coin(seed, "r", "w", "edge_id", fast=fast) < F.col("prob")).select("src", "dst", "w", "r")
        drawn = written(drawn, "worlds")
    elif mode != "frontier":
        raise ValueError(f"unknown mode {mode}")

    def step(fresh, seen, n):
        if early_stop:
            fresh = fresh.join(seen.where("node = t").select("pair_id", "rep", "world"), ["pair_id", "rep", "world"], "left_anti")
        if mode == "frontier":
            met = fresh.join(edges, fresh.node == edges.src).where(coin(seed, "rep", "world", "edge_id", fast=fast) < F.col("prob"))
        else:
            met = fresh.join(drawn, (fresh.node == drawn.src) & (fresh.world == drawn.w) & (fresh.rep == drawn.r))
        found = met.select("pair_id", "rep", "world", F.col("dst").alias("node"), "t").distinct()
        return found.join(seen.select(*STATE), STATE, "left_anti")

    seen, _ = grow(starts(pairs, k, reps), step, max_hops, "mc")
    return estimates(pairs, seen.where("node = t").select("pair_id", "rep", "world"), k, reps, method)


def terminal_set(g: UncertainGraph, nodes: list[int] | None, k: int, seed: int = 1) -> DataFrame:
    """(terminals, k, hits, r_hat): share of worlds in which every two of the nodes reach each other; None: all nodes.

    That holds if the first of them reaches all and all reach it, so the search runs forward and backward on the same worlds.
    """
    spark = g.edges.sparkSession
    wanted = g.nodes if nodes is None else spark.createDataFrame([(n,) for n in nodes], "node long")
    wanted = written(wanted, "terminals")
    least, many = wanted.agg(F.min("node"), F.count("*")).first()
    root = least if nodes is None else nodes[0]
    pairs = spark.createDataFrame([(1, root, -1, 0)], "pair_id int, s long, t long, hops int")

    def held(edges: DataFrame) -> DataFrame:
        def step(fresh, seen, n):
            met = fresh.join(edges, fresh.node == edges.src).where(coin(seed, "rep", "world", "edge_id") < F.col("prob"))
            found = met.select("pair_id", "rep", "world", F.col("dst").alias("node"), "t").distinct()
            return found.join(seen.select(*STATE), STATE, "left_anti")

        seen, _ = grow(starts(pairs, k, 1), step, None, "terminals")
        return seen.join(wanted, "node").groupBy("world").agg(F.count("*").alias("n")).where(F.col("n") == many).select("world")

    back = g.edges.select("edge_id", F.col("dst").alias("src"), F.col("src").alias("dst"), "prob")
    both = held(g.edges).join(held(back), "world")
    return both.agg(F.count("*").alias("hits")).select(F.lit(many).cast("long").alias("terminals"), F.lit(k).alias("k"), "hits", (F.col("hits") / F.lit(k)).alias("r_hat"))


def reach_sql(workload: str, k: int, seed: int = 1, reps: int = 1, max_hops: int | None = None, method: str = "mc", present: str | None = None) -> str:
    """The same estimates for DuckDB: set recursion over the same worlds. `present` overrides the coin test."""
    test = present or f"{coin_sql(seed, 'w.rep', 'w.world', 'e.edge_id')} < e.prob"
    hop = ", 0 AS hops" if max_hops else ""
    more, cap = (", w.hops + 1", f" AND w.hops < {max_hops}") if max_hops else ("", "")
    return f"""WITH RECURSIVE {workload},
worlds AS (SELECT CAST(a.range AS INTEGER) AS world, CAST(b.range AS INTEGER) AS rep FROM range({k}) a, range({reps}) b),
walk AS (SELECT pair_id, rep, world, s AS node{hop} FROM pairs, worlds
  UNION SELECT w.pair_id, w.rep, w.world, e.dst{more} FROM walk w JOIN g e ON w.node = e.src WHERE {test}{cap}),
hit AS (SELECT DISTINCT w.pair_id, w.rep, w.world FROM walk w JOIN pairs p ON w.pair_id = p.pair_id AND w.node = p.t),
counted AS (SELECT pair_id, rep, count(*) AS hits FROM hit GROUP BY ALL)
SELECT '{method}' AS method, p.pair_id, p.s, p.t, r.rep, {k} AS k, coalesce(c.hits, 0) AS hits, coalesce(c.hits, 0) / {k}.0::DOUBLE AS r_hat
FROM pairs p CROSS JOIN (SELECT DISTINCT rep FROM worlds) r LEFT JOIN counted c ON c.pair_id = p.pair_id AND c.rep = r.rep"""
