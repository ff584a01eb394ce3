"""Splitting and stratified splitting, level by level, in DataFrames.

A group of worlds is a row: its pair, the edges it includes and excludes, its weight and its samples. A level
decides the groups that a way or a cut settles, sets aside the small ones as leaves, and divides the others by
edges that are still open: those met first in a search from s, or for 'depth' the deepest at the border. Weights are absolute, so the answer is one weighted sum with no way back up. Graphs that
fit in a worker are solved faster by the kernels module, which this form agrees with in law.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from relgraph.functions.coins import coin
from relgraph.model import UncertainGraph
from relgraph.plans.iterate import grow, written
from relgraph.plans.reach import relevant

GROUP = ["pair_id", "s", "t", "path", "weight", "k", "inc", "exc"]


def weights(ordered: DataFrame, by: str = "group", at: str = "ord") -> DataFrame:
    """(by, stratum, pi): stratum 0 has none of a group's edges, stratum i has edge i as the first that exists.

    ordered: the group, positions from 1, and prob. Products are sums of logarithms; certain edges are
    handled apart, as what lies behind them has weight 0.
    """
    before = Window.partitionBy(by).orderBy(at).rowsBetween(Window.unboundedPreceding, -1)
    safe = F.when(F.col("prob") < 1, F.log1p(-F.when(F.col("prob") < 1, F.col("prob")).otherwise(0.0))).otherwise(0.0)
    sure = F.coalesce(F.max((F.col("prob") >= 1).cast("int")).over(before), F.lit(0))
    none = F.exp(F.coalesce(F.sum(safe).over(before), F.lit(0.0)))
    each = ordered.select(by, F.col(at).cast("int").alias("stratum"), F.when(sure > 0, 0.0).otherwise(F.col("prob") * none).alias("pi"))
    rest = ordered.groupBy(by).agg(F.exp(F.sum(safe)).alias("none"), F.max(F.col("prob") >= 1).alias("sure"))
    return each.union(rest.select(by, F.lit(0).alias("stratum"), F.when(F.col("sure"), 0.0).otherwise(F.col("none")).alias("pi")))


def weights_sql(ordered: str) -> str:
    """For a CTE body with columns group, ord, prob (all below one)."""
    return f"""WITH o AS ({ordered}),
w AS (SELECT "group", CAST(ord AS INTEGER) AS stratum, prob * exp(coalesce(sum(ln(1 - prob)) OVER (PARTITION BY "group" ORDER BY ord ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0)) AS pi FROM o)
SELECT "group", stratum, round(pi, 9) AS pi FROM w UNION ALL SELECT "group", 0, round(exp(sum(ln(1 - prob))), 9) FROM o GROUP BY "group\""""


def _walk(groups: DataFrame, edges: DataFrame, open_) -> DataFrame:
    """(pair_id, path, node, hops) reached over the open edges of each group."""
    head = groups.select("pair_id", "path", "inc", "exc", F.col("s").alias("node"), F.lit(0).alias("hops"))

    def step(fresh, seen, n):
        met = fresh.join(edges, (fresh.pair_id == edges.pair) & (fresh.node == edges.src)).where(open_)
        found = met.select("pair_id", "path", "inc", "exc", F.col("dst").alias("node")).distinct()
        return found.join(seen.select("pair_id", "path", "node"), ["pair_id", "path", "node"], "left_anti").withColumn("hops", F.lit(n))

    return grow(head, step, None, "groups")[0].select("pair_id", "path", "node", "hops")


def reach(g: UncertainGraph, pairs: DataFrame, k: int, r: int = 50, leaf: int = 5, seed: int = 1, edge_order: str = "breadth", most_levels: int = 200) -> DataFrame:
    """(method, pair_id, s, t, k, k_used, r_hat) of every pair; r = 1 with edge_order 'depth' is edge splitting."""
    edges = written(relevant(g, pairs).withColumnRenamed("pair_id", "pair"), "relevant")
    none = F.array().cast("array<long>")
    groups = pairs.where("s <> t").select("pair_id", "s", "t", F.lit("").alias("path"), F.lit(1.0).alias("weight"), F.lit(k).alias("k"), none.alias("inc"), none.alias("exc"))
    ones, leaves = [], []
    groups = written(groups, "level")
    for _ in range(most_levels):
        if groups.isEmpty():
            break
        sure = written(_walk(groups, edges, F.array_contains("inc", F.col("edge_id"))), "sure")
        could = written(_walk(groups, edges, ~F.array_contains("exc", F.col("edge_id"))), "could")
        ends = groups.select("pair_id", "path", F.col("t").alias("node"))
        way = ends.join(sure, ["pair_id", "path", "node"], "left_semi").select("pair_id", "path")
        alive = ends.join(could, ["pair_id", "path", "node"], "left_semi").select("pair_id", "path").join(way, ["pair_id", "path"], "left_anti")
        ones.append(written(groups.join(way, ["pair_id", "path"], "left_semi").select(*GROUP), "ones"))
        open_ = written(groups.join(alive, ["pair_id", "path"], "left_semi").select(*GROUP), "open")
        small = F.col("k") < leaf
        inner = open_.where(~small)
        met = inner.join(could if edge_order == "breadth" else sure, ["pair_id", "path"]).join(edges, (F.col("pair_id") == F.col("pair")) & (F.col("node") == F.col("src")))
        met = met.where(~F.array_contains("inc", F.col("edge_id")) & ~F.array_contains("exc", F.col("edge_id")))
        if edge_order != "breadth":
            met = met.join(sure.select("pair_id", "path", F.col("node").alias("dst")), ["pair_id", "path", "dst"], "left_anti")
        first = F.col("hops") if edge_order == "breadth" else -F.col("hops")
        order = Window.partitionBy("pair_id", "path").orderBy(first, "edge_id")
        border = met.withColumn("ord", F.row_number().over(order)).where(F.col("ord") <= r).select(*GROUP, "ord", "edge_id", "prob")
        border = border.withColumn("group", F.concat_ws("|", F.col("pair_id").cast("string"), "path"))
        border = written(border, "border")
        full = border.groupBy("pair_id", "path").agg(F.count("*").alias("n")).where(F.col("n") >= r).select("pair_id", "path")
        leaves.append(written(open_.where(small).unionByName(inner.join(full, ["pair_id", "path"], "left_anti").select(*GROUP)), "leaves"))
        border = border.join(full, ["pair_id", "path"], "left_semi")
        pis = weights(border)
        chosen = border.groupBy("group").agg(F.transform(F.sort_array(F.collect_list(F.struct("ord", "edge_id"))), lambda x: x["edge_id"]).alias("chosen"))
        parent = border.where("ord = 1").select("group", *GROUP).join(chosen, "group").join(pis, "group").where("pi > 0")
        i = F.col("stratum")
        exc = F.when(i == 0, F.concat("exc", "chosen")).otherwise(F.concat("exc", F.slice("chosen", F.lit(1), F.greatest(i - 1, F.lit(0)))))
        inc = F.when(i == 0, F.col("inc")).otherwise(F.concat("inc", F.slice("chosen", F.greatest(i, F.lit(1)), F.lit(1))))
        groups = parent.select(
            "pair_id", "s", "t", F.concat_ws(".", "path", i.cast("string")).alias("path"), (F.col("weight") * F.col("pi")).alias("weight"),
            F.greatest(F.lit(1), F.floor(F.col("k") * F.col("pi") + 1e-9)).cast("int").alias("k"), inc.alias("inc"), exc.alias("exc"),
        )
        groups = written(groups, "level")
    else:
        raise RuntimeError(f"groups remain after {most_levels} levels")
    union = lambda frames: frames[0] if len(frames) == 1 else frames[0].unionByName(union(frames[1:]))
    if not ones:
        found = None
    else:
        leaf_rows = union(leaves)
        worlds = leaf_rows.withColumn("world", F.explode(F.sequence(F.lit(0), F.col("k") - 1)))
        head = worlds.select("pair_id", "path", "world", "inc", "exc", "t", F.col("s").alias("node"))

        def step(fresh, seen, n):
            met = fresh.join(edges, (fresh.pair_id == edges.pair) & (fresh.node == edges.src))
            there = F.array_contains("inc", F.col("edge_id")) | (~F.array_contains("exc", F.col("edge_id")) & (coin(seed, "path", "world", "edge_id") < F.col("prob")))
            fresh_ = met.where(there).select("pair_id", "path", "world", "inc", "exc", "t", F.col("dst").alias("node")).distinct()
            return fresh_.join(seen.select("pair_id", "path", "world", "node"), ["pair_id", "path", "world", "node"], "left_anti")

        hits = grow(head, step, None, "leaf")[0].where("node = t").groupBy("pair_id", "path").agg(F.count("*").alias("hits"))
        part = leaf_rows.join(hits, ["pair_id", "path"], "left").select("pair_id", (F.col("weight") * F.coalesce("hits", F.lit(0)) / F.col("k")).alias("part"), F.col("k").alias("used"))
        part = part.union(union(ones).select("pair_id", "weight", F.lit(0)))
        found = part.groupBy("pair_id").agg(F.sum("part").alias("r"), F.sum("used").alias("used"))
    out = pairs.select("pair_id", "s", "t")
    out = out.join(found, "pair_id", "left") if found is not None else out.withColumn("r", F.lit(None).cast("double")).withColumn("used", F.lit(0))
    value = F.when(F.col("s") == F.col("t"), 1.0).otherwise(F.coalesce("r", F.lit(0.0)))
    return out.select(F.lit("strata" if r > 1 else "split").alias("method"), "pair_id", "s", "t", F.lit(k).alias("k"), F.coalesce("used", F.lit(0)).cast("long").alias("k_used"), value.alias("r_hat"))
