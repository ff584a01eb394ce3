"""Width-bounded tree index: nodes of low degree are folded away, and what they carried becomes summary edges.

A round takes an independent set of eligible nodes, chosen by degree and hash, so a chain shrinks by a share in
each round instead of by a node. A folded node's bag keeps its edges; between its two neighbours a summary edge
runs in each direction that a way through the node has. The two use different edges, so they stay independent
and nothing is lost for width 2. A query opens the bags of its ends and of every bag neighbour that was folded
later, drops their summaries, and any estimator runs on what results.

Tables: bags (bag, round, degree, neighbours), bag_edges (bag, src, dst, prob, origin), root (src, dst, prob,
origin), where origin is the bag whose summary an edge is, or null for an edge of the graph.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relgraph.model import UncertainGraph
from relgraph.operators import kernels
from relgraph.plans.iterate import Store, grow, written

#: Rounds of folding. Each costs some jobs; the index is lossless after any number, later ones fold ever fewer nodes.
ROUNDS = 6


@dataclass(frozen=True)
class TreeIndex:
    bags: DataFrame
    bag_edges: DataFrame
    root: DataFrame
    rounds: int
    lossless: bool


def parallel(prob: str = "prob"):
    """Chance that at least one of independent parallel edges exists."""
    p = F.col(prob)
    some = 1 - F.exp(F.sum(F.log1p(-F.when(p < 1, p).otherwise(0.0))))
    return F.when(F.max(p) >= 1, 1.0).otherwise(some)


def spans_parallel(column: str = "within"):
    """The same for each distance: chances of a way of at most 1, 2, ... edges."""
    each = F.collect_list(column)
    miss = F.aggregate(each, F.transform(F.get(each, F.lit(0)), lambda x: F.lit(1.0)), lambda a, x: F.zip_with(a, x, lambda m, p: m * (1 - p)))
    return F.transform(miss, lambda m: 1 - m)


def spans_serial(a: str, b: str, most: int):
    """Distances add up: the chance of exactly i edges times that of at most h - i."""
    exact = lambda c, i: F.get(c, i) - F.coalesce(F.get(c, i - 1), F.lit(0.0))
    chance = lambda h: F.aggregate(
        F.sequence(F.lit(0), F.lit(most - 1)), F.lit(0.0),
        lambda s, i: s + F.when(i < h, exact(F.col(a), i) * F.coalesce(F.get(F.col(b), h - 1 - i), F.lit(0.0))).otherwise(0.0),
    )
    return F.transform(F.sequence(F.lit(0), F.lit(most - 1)), chance)


def build(g: UncertainGraph, width: int = 2, rounds: int = ROUNDS, hops: int | None = None) -> TreeIndex:
    """The index. Summaries are made for nodes of degree up to 2; a larger width leaves the others' bags without,
    so it loses ways (lossless is then False). hops keeps distance distributions up to so many edges as well.
    """
    spark = g.edges.sparkSession
    extra = ["within"] if hops else []
    live = g.edges.select("src", "dst", "prob", F.lit(None).cast("long").alias("origin"))
    if hops:
        live = live.withColumn("within", F.transform(F.sequence(F.lit(1), F.lit(hops)), lambda h: F.col("prob")))
    live = written(live, "live")
    bags, kept, n = Store(spark, "bags"), Store(spark, "bag-edges"), 0
    while n < rounds:
        both = live.select(F.col("src").alias("u"), F.col("dst").alias("v")).union(live.select("dst", "src")).distinct()
        low = both.groupBy("u").agg(F.count("*").alias("degree")).where(F.col("degree") <= width)
        low = low.join(both, "u").select("u", "degree", "v")
        low = written(low.withColumn("key", F.struct("degree", F.xxhash64("u"), "u")), "low")
        rival = low.select(F.col("u").alias("v"), F.col("key").alias("other")).distinct()
        lost = low.join(rival, "v").where(F.col("other") < F.col("key")).select("u").distinct()
        won = low.join(lost, "u", "left_anti").groupBy("u", "degree").agg(F.sort_array(F.collect_list("v")).alias("neighbours"))
        won = bags.add(won.select(F.col("u").alias("bag"), F.lit(n).alias("round"), F.col("degree").cast("int"), "neighbours"))
        if won.isEmpty():
            break
        names = won.select("bag")
        out = live.join(names, live.src == names.bag).select("bag", "src", "dst", "prob", "origin", *extra)
        into = live.join(names, live.dst == names.bag).select("bag", "src", "dst", "prob", "origin", *extra)
        taken = kept.add(out.union(into))
        agg = [parallel().alias("prob")] + ([spans_parallel().alias("within")] if hops else [])
        merged = written(taken.groupBy("bag", "src", "dst").agg(*agg), "merged")
        a = merged.where("dst = bag").select("bag", F.col("src").alias("a"), F.col("prob").alias("p"), *(F.col("within").alias("w1") for _ in extra))
        b = merged.where("src = bag").select("bag", F.col("dst").alias("b"), F.col("prob").alias("q"), *(F.col("within").alias("w2") for _ in extra))
        through = a.join(b, "bag").where("a <> b").join(won.where("degree <= 2").select("bag"), "bag", "left_semi")
        made = [F.col("a").alias("src"), F.col("b").alias("dst"), (F.col("p") * F.col("q")).alias("prob"), F.col("bag").alias("origin")]
        made += [spans_serial("w1", "w2", hops).alias("within")] if hops else []
        rest = live.join(names, live.src == names.bag, "left_anti").join(names, live.dst == names.bag, "left_anti")
        live = written(rest.unionByName(through.select(*made)), "live")
        n += 1
    return TreeIndex(bags.all(), kept.all() if kept.rounds else live.limit(0).withColumn("bag", F.lit(None).cast("long")), live, n, width <= 2)


def opened(index: TreeIndex, pairs: DataFrame) -> DataFrame:
    """(pair_id, bag): bags that a query must open, from its ends up to the root."""
    ends = pairs.select("pair_id", F.col("s").alias("node")).union(pairs.select("pair_id", "t"))
    bags = index.bags.select("bag", "neighbours")
    first = ends.join(bags, ends.node == bags.bag).select("pair_id", "bag").distinct()

    def step(fresh, seen, n):
        up = fresh.join(bags, "bag").select("pair_id", F.explode("neighbours").alias("bag"))
        up = up.join(bags.select("bag"), "bag", "left_semi").distinct()
        return up.join(seen, ["pair_id", "bag"], "left_anti").select("pair_id", "bag")

    return grow(first, step, None, "opened")[0]


def query_graph(index: TreeIndex, pairs: DataFrame) -> DataFrame:
    """(pair_id, src, dst, prob, origin): the graph that each pair's estimator runs on."""
    open_ = opened(index, pairs)
    every = pairs.select("pair_id").crossJoin(index.root.select("src", "dst", "prob", "origin"))
    inner = open_.join(index.bag_edges.select("bag", "src", "dst", "prob", "origin"), "bag").select("pair_id", "src", "dst", "prob", "origin")
    gone = open_.select("pair_id", F.col("bag").alias("origin"))
    return every.union(inner).join(gone, ["pair_id", "origin"], "left_anti").select("pair_id", "src", "dst", "prob", "origin")


def reach(index: TreeIndex, pairs: DataFrame, k: int, inner: str = "mc", reps: int = 1, seed: int = 1, **params) -> DataFrame:
    """Runs of another estimator on the query graphs, as `kernels.solve` returns them.

    A root of up to kernels.MOST_EDGES edges goes to every worker and only opened bags travel per pair; a larger
    one is cut to what each pair needs.
    """
    label = f"tree+{inner}"
    ends = written(pairs.select("pair_id", "s", "t"), "ends")

    def runs(task: pa.Table, src, dst, prob) -> pa.Table:
        local = kernels.Local.of(src, dst, prob)
        rows = [{**r, "rep": i} for r in task.select(["pair_id", "s", "t"]).to_pylist() for i in range(reps)]
        return pa.Table.from_batches([kernels._runs(local, {c: [r[c] for r in rows] for c in ("pair_id", "s", "t", "rep")}, label, inner, k, seed, params)])

    if index.root.count() <= kernels.MOST_EDGES:
        spark = pairs.sparkSession
        root = index.root.select("src", "dst", "prob", F.coalesce("origin", F.lit(-1)).alias("origin")).toArrow()
        shared = spark.sparkContext.broadcast(tuple(c.to_numpy() for c in root.columns))
        open_ = written(opened(index, pairs), "opened")
        extra = open_.join(index.bag_edges.select("bag", "src", "dst", "prob", F.coalesce("origin", F.lit(-1)).alias("origin")), "bag")
        bare = open_.select("pair_id", "bag", *(F.lit(None).cast(t).alias(c) for c, t in (("src", "long"), ("dst", "long"), ("prob", "double"), ("origin", "long"))))
        extra = extra.select("pair_id", "bag", "src", "dst", "prob", "origin").union(bare)

        def one(task: pa.Table, more: pa.Table) -> pa.Table:
            gone = np.unique(np.array(more.column("bag").to_pylist(), np.int64))
            more = more.filter(pc.is_valid(more.column("src")))
            columns = [np.concatenate([a, more.column(c).to_numpy().astype(a.dtype)]) for a, c in zip(shared.value, ("src", "dst", "prob", "origin"), strict=True)]
            hold = ~np.isin(columns[3], gone)
            return runs(task, *(c[hold] for c in columns[:3]))

        return ends.groupBy("pair_id").cogroup(extra.groupBy("pair_id")).applyInArrow(one, kernels.RUNS)
    graph = query_graph(index, pairs)
    return ends.groupBy("pair_id").cogroup(graph.groupBy("pair_id")).applyInArrow(lambda a, b: runs(a, *(b.column(c).to_numpy() for c in ("src", "dst", "prob"))), kernels.RUNS)
