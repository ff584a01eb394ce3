"""Registered queries of the reliability engine, and their SQL where it can be said in SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from relgraph.functions import measures
from relgraph.model import UncertainGraph
from relgraph.operators import bitmap, kernels, mc, skip, strata, tree
from relgraph.plans import advisor, experiments, reach, temporal, workload
from relgraph.plans.iterate import written
from relgraph.sources import graphs
from relgraph.sources.tables import literal, table

PAIRS, WORLDS, SEED = 10, 64, 1
GRAPHS = {
    "copurchase": (graphs.copurchase, graphs.copurchase_sql()),
    "copurchase_low": (lambda s, d: graphs.copurchase(s, d, 20), graphs.copurchase_sql(20)),
    "userflow": (graphs.userflow, graphs.userflow_sql()),
    "custsupp": (graphs.custsupp, graphs.custsupp_sql()),
    "nation": (graphs.nation, graphs.nation_sql()),
    "knn": (graphs.nearest, graphs.nearest_sql()),
    "knn5": (lambda s, d: graphs.nearest(s, d, 5), graphs.nearest_sql(5)),
    "choice": (graphs.choice, graphs.choice_sql()),
}
#: The main graph: each vector of the whole embeddings table to its three nearest. Sparse, with distances up to many hops.
MAIN = graphs.nearest_sql()
#: Toy graphs with known answers: name, edges (src, dst, prob), s, t.
TOYS = (
    ("single", ((1, 2, 0.5),), 1, 2),
    ("chain", ((1, 2, 0.5), (2, 3, 0.5)), 1, 3),
    ("parallel", ((6, 1, 0.75), (6, 5, 0.5), (5, 1, 0.5)), 6, 1),
    ("diamond", ((1, 2, 0.5), (1, 3, 0.5), (2, 4, 0.5), (3, 4, 0.5)), 1, 4),
    ("bridge", ((1, 2, 0.5), (1, 3, 0.5), (2, 4, 0.5), (3, 4, 0.5), (2, 3, 0.5), (3, 2, 0.5)), 1, 4),
    ("cycle", ((1, 2, 0.5), (2, 3, 0.5), (3, 1, 0.5), (3, 4, 0.5)), 1, 4),
    ("same", ((1, 2, 0.5),), 1, 1),
    ("apart", ((1, 2, 0.5), (3, 4, 0.5)), 1, 4),
    ("rare", ((1, 2, 0.001),), 1, 2),
)


def main(spark: SparkSession, sf_dir: str) -> UncertainGraph:
    """The main graph, written once, as several passes read it."""
    return UncertainGraph(written(graphs.nearest(spark, sf_dir).edges, "graph"))


def both(spark: SparkSession, sf_dir: str, n: int = PAIRS, hops: int = 2) -> tuple[UncertainGraph, DataFrame]:
    g = main(spark, sf_dir)
    return g, workload.pairs(g, n, hops, SEED)


def bench(spark: SparkSession, sf_dir: str, n: int = PAIRS, hops: int = 2, graph: str = "knn"):
    g = UncertainGraph(written(GRAPHS[graph][0](spark, sf_dir).edges, "graph"))
    pairs = workload.pairs(g, n, hops, SEED)
    return experiments.solver(g, pairs, SEED), g, pairs


QUERIES: dict = {}
SQL: dict[str, str] = {}


def query(sql: str | None = None, name: str | None = None):
    def keep(f):
        QUERIES[name or f.__name__] = f
        if sql:
            SQL[name or f.__name__] = sql
        return f

    return keep


for _name, (_build, _sql) in GRAPHS.items():
    query(_sql, f"graph_{_name}")(lambda s, d, f=_build: f(s, d).edges)

WORK = workload.pairs_sql(MAIN, PAIRS)


def _profile_sql(graph: str, label: str) -> str:
    return f"""SELECT '{label}' AS graph, (SELECT count(DISTINCT node) FROM (SELECT src AS node FROM e UNION ALL SELECT dst FROM e)) AS nodes, count(*) AS edges,
round(avg(prob), 6) AS mean, round(stddev_samp(prob), 6) AS sd, round(quantile_cont(prob, 0.25), 6) AS q1, round(quantile_cont(prob, 0.5), 6) AS q2,
round(quantile_cont(prob, 0.75), 6) AS q3 FROM ({graph}) e""".replace("FROM e UNION ALL", f"FROM ({graph}) UNION ALL").replace("SELECT dst FROM e)", f"SELECT dst FROM ({graph}))")


@query(" UNION ALL ".join(f"SELECT * FROM ({_profile_sql(sql, n)})" for n, (_, sql) in GRAPHS.items()))
def graph_profile(spark, sf_dir):
    digits = ("mean", "sd", "q1", "q2", "q3")
    parts = [UncertainGraph(written(f(spark, sf_dir).edges, "graph")).profile().select(F.lit(n).alias("graph"), "nodes", "edges", *(F.round(c, 6).alias(c) for c in digits)) for n, (f, _) in GRAPHS.items()]
    return experiments.together(parts)


def _pairs(hops: int):
    return lambda s, d: both(s, d, 20, hops)[1]


for _h in (2, 4):
    query(f"WITH RECURSIVE {workload.pairs_sql(MAIN, 20, _h)} SELECT pair_id, s, t, CAST(hops AS INTEGER) AS hops FROM pairs", f"pairs_h{_h}")(_pairs(_h))


@query(f"WITH RECURSIVE {WORK}, walk AS (SELECT pair_id, s AS node FROM pairs UNION SELECT w.pair_id, e.dst FROM walk w JOIN g e ON w.node = e.src) "
       "SELECT p.pair_id, p.s, p.t, EXISTS (SELECT 1 FROM walk w WHERE w.pair_id = p.pair_id AND w.node = p.t) AS reachable FROM pairs p")  # fmt: skip
def reach_deterministic(spark, sf_dir):
    return reach.reachable(*both(spark, sf_dir))


@query(f"WITH RECURSIVE {WORK.replace('hop AS', 'hop0 AS').replace('FROM hop h', 'FROM hop0 h').replace('FROM hop GROUP', 'FROM hop0 GROUP').replace('dist AS', 'dist0 AS').replace('FROM dist W', 'FROM dist0 W')}, "
       "hop AS (SELECT s, s AS node, 0 AS hops FROM pairs UNION SELECT h.s, e.dst, h.hops + 1 FROM hop h JOIN g e ON h.node = e.src WHERE h.hops < 4) "
       "SELECT s, node, CAST(min(hops) AS INTEGER) AS hops FROM hop GROUP BY ALL")  # fmt: skip
def hops_bfs(spark, sf_dir):
    g, pairs = both(spark, sf_dir)
    return reach.hops(g, pairs.select("s"), 4)


@query(mc.reach_sql(WORK, WORLDS, SEED))
def mc_reach(spark, sf_dir):
    return mc.reach(*both(spark, sf_dir), WORLDS, SEED)


@query(mc.reach_sql(WORK, WORLDS, SEED))
def mc_materialised(spark, sf_dir):
    return mc.reach(*both(spark, sf_dir), WORLDS, SEED, mode="materialised")


@query(mc.reach_sql(WORK, WORLDS, SEED))
def mc_no_early_stop(spark, sf_dir):
    return mc.reach(*both(spark, sf_dir), WORLDS, SEED, early_stop=False)


@query(mc.reach_sql(WORK, WORLDS, SEED, max_hops=3))
def mc_hops(spark, sf_dir):
    return mc.reach(*both(spark, sf_dir), WORLDS, SEED, max_hops=3)


@query(f"""WITH RECURSIVE g AS (SELECT * FROM ({GRAPHS["nation"][1]})), ends AS (SELECT DISTINCT node FROM (SELECT src AS node FROM g UNION ALL SELECT dst FROM g)),
worlds AS (SELECT CAST(range AS INTEGER) AS world FROM range({WORLDS})),
walk AS (SELECT world, (SELECT min(node) FROM ends) AS node FROM worlds UNION SELECT w.world, e.dst FROM walk w JOIN g e ON w.node = e.src WHERE {mc.coin_sql(SEED, "0", "w.world", "e.edge_id")} < e.prob),
back AS (SELECT world, (SELECT min(node) FROM ends) AS node FROM worlds UNION SELECT w.world, e.src FROM back w JOIN g e ON w.node = e.dst WHERE {mc.coin_sql(SEED, "0", "w.world", "e.edge_id")} < e.prob),
full_ AS (SELECT world FROM walk GROUP BY world HAVING count(*) = (SELECT count(*) FROM ends) INTERSECT SELECT world FROM back GROUP BY world HAVING count(*) = (SELECT count(*) FROM ends))
SELECT (SELECT count(*) FROM ends) AS terminals, {WORLDS} AS k, count(*) AS hits, count(*) / {WORLDS}.0::DOUBLE AS r_hat FROM full_""")
def mc_terminal_set(spark, sf_dir):
    g = UncertainGraph(written(graphs.nation(spark, sf_dir).edges, "graph"))
    return mc.terminal_set(g, None, WORLDS, SEED)


@query(bitmap.build_sql(MAIN, 100, SEED))
def bitmap_index(spark, sf_dir):
    return bitmap.build(main(spark, sf_dir), 100, SEED)


@query(bitmap.build_sql(MAIN, 100, SEED, 3))
def bitmap_refresh(spark, sf_dir):
    g = main(spark, sf_dir)
    return bitmap.refresh(g, bitmap.build(g, 100, SEED), 3, 100, SEED)


@query(f"""SELECT * FROM ({bitmap.build_sql(MAIN, 64, SEED)}) WHERE src % 2 <> 0
UNION ALL SELECT * FROM ({bitmap.build_sql(MAIN, 64, SEED, 3)}) WHERE src % 2 = 0""")
def bitmap_refresh_touched(spark, sf_dir):
    g = main(spark, sf_dir)
    return bitmap.refresh(g, bitmap.build(g, 64, SEED), 3, 64, SEED, g.edges.where(F.pmod("src", F.lit(2)) == 0))


def _index(g, k):
    return written(bitmap.build(g, k, SEED), "index")


@query(mc.reach_sql(WORK, 100, SEED, method="bitmap"))
def bitmap_reach(spark, sf_dir):
    g, pairs = both(spark, sf_dir)
    return bitmap.reach(_index(g, 128), pairs, 100)


@query(mc.reach_sql(WORK, 100, SEED, method="bitmap"))
def bitmap_retire(spark, sf_dir):
    g, pairs = both(spark, sf_dir)
    return bitmap.reach(_index(g, 128), pairs, 100, retire=True)


@query(mc.reach_sql(WORK, 100, SEED, method="bitmap", max_hops=3))
def bitmap_hops(spark, sf_dir):
    g, pairs = both(spark, sf_dir)
    return bitmap.reach(_index(g, 128), pairs, 100, max_hops=3)


TARGETS = f"""WITH RECURSIVE {workload.pairs_sql(MAIN, 3)},
walk AS (SELECT CAST(range AS INTEGER) AS world, s, s AS node FROM (SELECT DISTINCT s FROM pairs), range({WORLDS})
  UNION SELECT w.world, w.s, e.dst FROM walk w JOIN g e ON w.node = e.src WHERE {mc.coin_sql(SEED, "0", "w.world", "e.edge_id")} < e.prob),
found AS (SELECT s, node, count(*) AS hits, count(*) / {WORLDS}.0::DOUBLE AS r_hat FROM walk WHERE s <> node GROUP BY s, node)
"""


@query(TARGETS + "SELECT * FROM found")
def bitmap_all_targets(spark, sf_dir):
    g, pairs = both(spark, sf_dir, 3)
    return bitmap.all_targets(_index(g, WORLDS), pairs.select("s"), WORLDS)


@query(TARGETS + "SELECT *, CAST(row_number() OVER (PARTITION BY s ORDER BY hits DESC, node) AS INTEGER) AS rank FROM found QUALIFY rank <= 10")
def bitmap_topk(spark, sf_dir):
    g, pairs = both(spark, sf_dir, 3)
    return bitmap.top_targets(_index(g, WORLDS), pairs.select("s"), 10, WORLDS)


@query(skip.reach_sql(WORK, WORLDS, SEED))
def skip_reach(spark, sf_dir):
    return skip.reach(*both(spark, sf_dir), WORLDS, SEED)


def _kernel(name: str, method: str, **params):
    @query(name=name)
    def run(spark, sf_dir):
        return kernels.solve(*both(spark, sf_dir), method, 1000, 4, SEED, name, **params)


_kernel("mc_kernel", "mc")
_kernel("bitmap_kernel", "bitmap")
_kernel("skip_kernel", "skip")
_kernel("split_prop", "split")
_kernel("split_random", "split", allocation="random")
_kernel("split_pooled", "split", allocation="pooled")
_kernel("split_random_edge", "split", edge_order="random")
_kernel("split_hops", "split", max_hops=3)
_kernel("strata_kernel", "strata")
_kernel("strata_pooled", "strata", allocation="pooled")


def _tree(inner: str):
    @query(name=f"tree_{inner}")
    def run(spark, sf_dir):
        g, pairs = both(spark, sf_dir)
        return tree.reach(tree.build(g), pairs, 1000, inner, 4, SEED)


for _inner in ("mc", "skip", "split", "strata"):
    _tree(_inner)


@query()
def skip_legacy(spark, sf_dir):
    """Corrected and uncorrected skip sampling beside plain sampling, for the three readings of the inner loop."""
    g, pairs = both(spark, sf_dir, 4)
    forms = [("plain", "mc", {}), ("corrected", "skip_sequential", {})]
    forms += [(f"legacy_{r}", "skip_sequential", {"corrected": False, "loop": r}) for r in ("retest", "once", "count_all")]
    runs = experiments.together(kernels.solve(g, pairs, m, 100, 2, SEED, n, **p) for n, m, p in forms)
    return measures.dispersion(runs).select("method", "k", "pairs", "r_k")


@query()
def strata_reach(spark, sf_dir):
    """The level-by-level form in DataFrames."""
    return strata.reach(*both(spark, sf_dir, 3), 100, 20, 20, SEED)


ORDERED = f"SELECT src AS \"group\", row_number() OVER (PARTITION BY src ORDER BY edge_id) AS ord, prob FROM ({MAIN})"


@query(strata.weights_sql(ORDERED))
def strata_weights(spark, sf_dir):
    from pyspark.sql.window import Window

    edges = main(spark, sf_dir).edges
    ordered = edges.select(F.col("src").alias("group"), F.row_number().over(Window.partitionBy("src").orderBy("edge_id")).alias("ord"), "prob")
    return strata.weights(ordered).withColumn("pi", F.round("pi", 9))


@query()
def tree_bags(spark, sf_dir):
    return tree.build(main(spark, sf_dir)).bags


@query()
def tree_query_graph(spark, sf_dir):
    g, pairs = both(spark, sf_dir, 3)
    return tree.query_graph(tree.build(g), pairs)


@query()
def tree_distances(spark, sf_dir):
    """Summary edges with the chance of a way of at most 1, 2, 3 and 4 edges."""
    return tree.build(main(spark, sf_dir), hops=4).root.where("origin is not null")


@query()
def tree_wide(spark, sf_dir):
    """Width 3 folds more away but is lossy."""
    g, pairs = both(spark, sf_dir)
    return tree.reach(tree.build(g, 3), pairs, 1000, "mc", 1, SEED)


def toys(spark, method: str, **params) -> DataFrame:
    out = []
    for i, (name, edges, s, t) in enumerate(TOYS):
        pair = spark.createDataFrame([(i, s, t, 0)], "pair_id int, s long, t long, hops int")
        runs = kernels.solve(literal(spark, list(edges)), pair, method, 1, 1, SEED, **params)
        out.append(runs.select(F.lit(name).alias("toy"), "s", "t", F.round("r_hat", 9).alias("r")))
    return experiments.together(out)


def _toy_sql() -> str:
    """World enumeration: every subset of a toy's edges with its chance, searched by set recursion."""
    rows = ", ".join(f"('{n}', {s}, {t}, {i}, {a}, {b}, {p}::DOUBLE)" for n, edges, s, t in TOYS for i, (a, b, p) in enumerate(edges))
    return f"""WITH RECURSIVE e AS (SELECT * FROM (VALUES {rows}) v(toy, s, t, i, src, dst, prob)),
m AS (SELECT toy, any_value(s) AS s, any_value(t) AS t, count(*) AS m FROM e GROUP BY toy),
w AS (SELECT toy, s, t, unnest(range(0, CAST(1 << m AS BIGINT))) AS world FROM m),
p AS (SELECT w.toy, w.world, product(CASE WHEN (w.world >> i) & 1 = 1 THEN prob ELSE 1 - prob END) AS chance FROM w JOIN e ON e.toy = w.toy GROUP BY ALL),
walk AS (SELECT toy, world, s AS node FROM w UNION SELECT k.toy, k.world, e.dst FROM walk k JOIN e ON e.toy = k.toy AND e.src = k.node WHERE (k.world >> e.i) & 1 = 1)
SELECT m.toy, CAST(m.s AS BIGINT) AS s, CAST(m.t AS BIGINT) AS t, round(coalesce(sum(p.chance), 0), 9) AS r FROM m LEFT JOIN walk k ON k.toy = m.toy AND k.node = m.t
LEFT JOIN p ON p.toy = k.toy AND p.world = k.world GROUP BY ALL"""


@query(_toy_sql())
def exact_toy(spark, sf_dir):
    return toys(spark, "enumerate")


@query(_toy_sql())
def exact_factor(spark, sf_dir):
    return toys(spark, "factor")


@query(_toy_sql())
def exact_strata(spark, sf_dir):
    return toys(spark, "strata", r=3, leaf=None)


#: Ways to estimate, each held against the exact answers of all toys: method and its parameters.
VARIANTS: dict[str, tuple[str, dict]] = {
    "mc": ("mc", {}), "mc_late_stop": ("mc", {"early": False}), "bitmap": ("bitmap", {}), "skip": ("skip", {}), "skip_sequential": ("skip_sequential", {}),
    "skip_retest": ("skip_sequential", {"corrected": False, "loop": "retest"}), "split_proportional": ("split", {}), "split_random": ("split", {"allocation": "random"}),
    "split_pooled": ("split", {"allocation": "pooled"}), "split_random_edge": ("split", {"edge_order": "random"}), "split_leaf_20": ("split", {"leaf": 20}),
    "split_hops": ("split", {"max_hops": 4}), "strata": ("strata", {"r": 3}), "strata_one_edge": ("strata", {"r": 1}), "strata_pooled": ("strata", {"r": 3, "allocation": "pooled"}),
}


def _spread(runs: DataFrame) -> DataFrame:
    return runs.groupBy("pair_id").agg(F.avg("r_hat").alias("mean"), F.stddev("r_hat").alias("sd"))


def _near(k: int, reps: int):
    """Whether the mean of the repeats lies within four of its standard deviations of the exact answer r."""
    return F.abs(F.col("mean") - F.col("r")) <= 4 * F.greatest(F.col("sd"), F.sqrt(F.col("r") * (1 - F.col("r")) / k / reps)) / F.sqrt(F.lit(float(reps))) + F.sqrt(F.col("r") / k / reps) + 1e-9


def agreement(spark, method: str, params: dict, k: int = 60, reps: int = 200) -> DataFrame:
    """(toy, s, t, r, agrees): the exact answer, and whether the mean of the repeats lies within four of its standard deviations."""
    out = []
    for i, (name, edges, s, t) in enumerate(TOYS):
        pair = spark.createDataFrame([(i, s, t, 0)], "pair_id int, s long, t long, hops int")
        g = literal(spark, list(edges))
        exact = kernels.solve(g, pair, "enumerate", 1).select("pair_id", "s", "t", F.col("r_hat").alias("r"))
        runs = _spread(kernels.solve(g, pair, method, k, reps, SEED, **params))
        out.append(exact.join(runs, "pair_id").select(F.lit(name).alias("toy"), "s", "t", F.round("r", 9).alias("r"), _near(k, reps).alias("agrees")))
    return experiments.together(out)


def surroundings(spark, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """Pairs of the main graph two hops apart, and for each a graph small enough for exact answers, as (pair_id, edge_id, src, dst, prob):
    the edges between its source, the nodes next to that, and its target, but for those into the source or out of the target."""
    g, pairs = both(spark, sf_dir)
    near = pairs.join(g.edges, F.col("s") == F.col("src")).select("pair_id", "s", "t", F.col("dst").alias("node"))
    nodes = near.unionByName(pairs.select("pair_id", "s", "t", F.col("s").alias("node"))).unionByName(pairs.select("pair_id", "s", "t", F.col("t").alias("node"))).distinct()
    held = nodes.join(g.edges, (F.col("node") == F.col("src")) & (F.col("src") != F.col("t")) & (F.col("dst") != F.col("s")))
    ends = nodes.select(F.col("pair_id").alias("p"), F.col("node").alias("end"))
    held = held.join(ends, (F.col("pair_id") == F.col("p")) & (F.col("dst") == F.col("end")))
    return pairs, written(held.select("pair_id", "edge_id", "src", "dst", "prob"), "surroundings")


def surroundings_sql() -> str:
    """The exact answers on those graphs: every subset of a pair's edges with its chance, searched by set recursion."""
    return f"""WITH RECURSIVE {WORK},
nodes AS (SELECT pair_id, s, t, dst AS node FROM pairs JOIN g ON s = src UNION SELECT pair_id, s, t, s FROM pairs UNION SELECT pair_id, s, t, t FROM pairs),
e AS (SELECT a.pair_id, a.s, a.t, src, dst, prob, row_number() OVER (PARTITION BY a.pair_id ORDER BY edge_id) - 1 AS i
  FROM nodes a JOIN g ON a.node = src JOIN nodes b ON b.pair_id = a.pair_id AND b.node = dst WHERE src <> a.t AND dst <> a.s),
m AS (SELECT pair_id, count(*) AS m FROM e GROUP BY pair_id),
w AS (SELECT pair_id, unnest(range(0, CAST(1 << m AS BIGINT))) AS world FROM m),
p AS (SELECT w.pair_id, world, product(CASE WHEN (world >> i) & 1 = 1 THEN prob ELSE 1 - prob END) AS chance FROM w JOIN e ON e.pair_id = w.pair_id GROUP BY ALL),
trip AS (SELECT w.pair_id, world, s AS node FROM w JOIN pairs ON pairs.pair_id = w.pair_id
  UNION SELECT k.pair_id, k.world, e.dst FROM trip k JOIN e ON e.pair_id = k.pair_id AND e.src = k.node WHERE (k.world >> e.i) & 1 = 1)
SELECT pairs.pair_id, pairs.s, pairs.t, round(coalesce(sum(chance), 0), 9) AS r FROM pairs LEFT JOIN trip k ON k.pair_id = pairs.pair_id AND k.node = pairs.t
LEFT JOIN p ON p.pair_id = k.pair_id AND p.world = k.world GROUP BY ALL"""


def agreement_on_table(spark, sf_dir: str, method: str, params: dict, k: int = 60, reps: int = 200) -> DataFrame:
    """(pair_id, s, t, r, agrees): as `agreement`, on the surroundings of pairs of the main graph."""
    pairs, edges = surroundings(spark, sf_dir)
    exact = kernels.solve_apart(edges, pairs, "enumerate", 1).select("pair_id", "s", "t", F.col("r_hat").alias("r"))
    runs = kernels.solve_apart(edges, pairs, method, k, reps, SEED, **params)
    return exact.join(_spread(runs), "pair_id").select("pair_id", "s", "t", F.round("r", 9).alias("r"), _near(k, reps).alias("agrees"))


#: Ways whose agreement is asked on a given table; the others are held against the toys.
ON_TABLE = (
    "bitmap", "mc", "mc_late_stop", "skip", "skip_retest", "skip_sequential", "split_hops", "split_leaf_20", "split_pooled", "split_proportional",
)
for _name, (_method, _params) in VARIANTS.items():
    if _name in ON_TABLE:
        query(f"SELECT *, TRUE AS agrees FROM ({surroundings_sql()})", f"agree_{_name}")(lambda s, d, m=_method, p=_params: agreement_on_table(s, d, m, p))
    else:
        query(f"SELECT *, TRUE AS agrees FROM ({_toy_sql()})", f"agree_{_name}")(lambda s, d, m=_method, p=_params: agreement(s, m, p))


def through_tree(spark) -> DataFrame:
    """Exact answers on the query graphs of the tree index."""
    out = []
    for i, (name, edges, s, t) in enumerate(TOYS):
        pair = spark.createDataFrame([(i, s, t, 0)], "pair_id int, s long, t long, hops int")
        runs = tree.reach(tree.build(literal(spark, list(edges))), pair, 1, "enumerate")
        out.append(runs.select(F.lit(name).alias("toy"), "s", "t", F.round("r_hat", 9).alias("r")))
    return experiments.together(out)


@query(_toy_sql())
def exact_tree(spark, sf_dir):
    return through_tree(spark)


# Measures over runs that both engines can draw.
RUNS_SQL = mc.reach_sql(workload.pairs_sql(MAIN, 5), 32, SEED, 4)
SKIP_SQL = skip.reach_sql(workload.pairs_sql(MAIN, 5), 32, SEED)
REF_SQL = mc.reach_sql(workload.pairs_sql(MAIN, 5), 128, 9)


def _runs(spark, sf_dir, *which: str) -> list[DataFrame]:
    """Runs of plain sampling, of skip sampling, and a reference with more worlds."""
    g, pairs = both(spark, sf_dir, 5)
    make = {
        "mc": lambda: mc.reach(g, pairs, 32, SEED, 4), "skip": lambda: skip.reach(g, pairs, 32, SEED), "ref": lambda: mc.reach(g, pairs, 128, 9),
    }
    return [make[w]() for w in which]


@query("""SELECT eps, lam, r, CAST(ceil(3 / (eps * eps * r) * ln(2 / lam)) AS BIGINT) AS k FROM
(VALUES (0.1::DOUBLE, 0.05::DOUBLE, 0.1::DOUBLE), (0.1, 0.05, 0.4), (0.1, 0.01, 0.5), (0.05, 0.05, 0.02)) v(eps, lam, r)""")
def chernoff_k(spark, sf_dir):
    rows = spark.createDataFrame([(0.1, 0.05, 0.1), (0.1, 0.05, 0.4), (0.1, 0.01, 0.5), (0.05, 0.05, 0.02)], "eps double, lam double, r double")
    return rows.withColumn("k", measures.required_samples(F.col("eps"), F.col("lam"), F.col("r")))


@query(f"SELECT pair_id, rep, round(r_hat * (1 - r_hat) / k, 12) AS variance FROM ({RUNS_SQL})")
def binomial_var(spark, sf_dir):
    return _runs(spark, sf_dir, "mc")[0].select("pair_id", "rep", F.round(measures.binomial_variance(F.col("r_hat"), F.col("k")), 12).alias("variance"))


@query(f"SELECT method, k, pair_id, round(var_samp(r_hat), 12) AS v, round(avg(r_hat), 12) AS r FROM ({RUNS_SQL}) GROUP BY ALL")
def pair_variance(spark, sf_dir):
    return measures.pair_variance(_runs(spark, sf_dir, "mc")[0]).select("method", "k", "pair_id", F.round("v", 12).alias("v"), F.round("r", 12).alias("r"))


@query(f"""SELECT method, k, count(*) AS pairs, round(avg(v), 12) AS v_k, round(avg(r), 12) AS r_k, round(avg(v) / nullif(avg(r), 0), 10) AS rho
FROM (SELECT method, k, pair_id, var_samp(r_hat) AS v, avg(r_hat) AS r FROM ({RUNS_SQL}) GROUP BY ALL) GROUP BY ALL""")
def rho_k(spark, sf_dir):
    found = measures.dispersion(_runs(spark, sf_dir, "mc")[0])
    return found.select("method", "k", "pairs", F.round("v_k", 12).alias("v_k"), F.round("r_k", 12).alias("r_k"), F.round("rho", 10).alias("rho"))


RE_SQL = f"""ref AS (SELECT pair_id, r_hat AS ref FROM ({REF_SQL})), runs AS (SELECT * FROM ({RUNS_SQL}) UNION ALL SELECT * FROM ({SKIP_SQL})),
re AS (SELECT method, k, avg(CASE WHEN ref > 0 THEN abs(r - ref) / ref * 100 END) AS re, count(*) FILTER (WHERE ref <= 0) AS skipped
FROM (SELECT method, k, pair_id, avg(r_hat) AS r FROM runs GROUP BY ALL) JOIN ref USING (pair_id) GROUP BY ALL)"""


@query(f"WITH {RE_SQL} SELECT method, k, round(re, 9) AS re, skipped FROM re")
def relative_error(spark, sf_dir):
    a, b, ref = _runs(spark, sf_dir, "mc", "skip", "ref")
    found = measures.relative_error(a.unionByName(b), ref.select("pair_id", F.col("r_hat").alias("ref")))
    return found.withColumn("re", F.round("re", 9))


@query(f"WITH {RE_SQL} SELECT a.k, round(avg(abs(a.re - b.re)), 9) AS d FROM re a JOIN re b ON a.k = b.k AND a.method <> b.method GROUP BY a.k")
def pairwise_dev(spark, sf_dir):
    a, b, ref = _runs(spark, sf_dir, "mc", "skip", "ref")
    found = measures.relative_error(a.unionByName(b), ref.select("pair_id", F.col("r_hat").alias("ref")))
    return measures.pairwise_deviation(written(found, "errors")).withColumn("d", F.round("d", 9))


@query(f"""WITH ref AS (SELECT pair_id, r_hat AS exact FROM ({REF_SQL}))
SELECT method, k, avg(CASE WHEN abs(r_hat - exact) <= 0.25 * exact THEN 1.0 ELSE 0.0 END)::DOUBLE AS share FROM ({RUNS_SQL}) JOIN ref USING (pair_id) GROUP BY ALL""")
def coverage(spark, sf_dir):
    a, ref = _runs(spark, sf_dir, "mc", "ref")
    return measures.coverage(a, ref.select("pair_id", F.col("r_hat").alias("exact")), 0.25)


@query(f"""SELECT method, rep, pair_id, count(*) AS runs, round(avg(r_hat), 12) AS r, CAST(grouping_id(method, rep, pair_id) AS BIGINT) AS level FROM ({RUNS_SQL}) GROUP BY CUBE (method, rep, pair_id)""")
def report_cube(spark, sf_dir):
    return _runs(spark, sf_dir, "mc")[0].cube("method", "rep", "pair_id").agg(F.count("*").alias("runs"), F.round(F.avg("r_hat"), 12).alias("r"), F.grouping_id().alias("level"))


@query(advisor.needs_scores_sql(MAIN))
def advisor_scores(spark, sf_dir):
    return advisor.needs_scores(advisor.needs(main(spark, sf_dir)))


@query(advisor.needs_recommend_sql(MAIN))
def advisor_recommend(spark, sf_dir):
    return advisor.needs_recommend(advisor.needs(main(spark, sf_dir)))


# Experiments.
#: Pairs and repeats of the registered experiments, and the steps of k.
TRIED, REPEATS, STEPS = 20, 10, (250, 500, 1000)
#: Successive queries that each have the bitmap index drawn anew, and the worlds that it then holds.
REFRESHED, LENGTH = 1000, 1500


@query()
def convergence_table(spark, sf_dir):
    run, _, _ = bench(spark, sf_dir, TRIED)
    return experiments.convergence_table(run, experiments.SIX, reps=REPEATS, limit=2500)


@query()
def variance_curves(spark, sf_dir):
    run, _, _ = bench(spark, sf_dir, TRIED)
    return experiments.curves(run, experiments.SIX, STEPS, REPEATS)


@query()
def full_tables(spark, sf_dir):
    run, _, _ = bench(spark, sf_dir, PAIRS)
    return experiments.full_tables(run, experiments.SIX, 6)


@query()
def tradeoff_userflow(spark, sf_dir):
    run, _, _ = bench(spark, sf_dir, PAIRS, graph="userflow")
    return experiments.over_k(run, experiments.SIX, STEPS, 4)


@query()
def errors_fixed_k(spark, sf_dir):
    run, _, _ = bench(spark, sf_dir, TRIED)
    return experiments.errors(run, experiments.SIX, 1000, REPEATS)


@query()
def timings(spark, sf_dir):
    run, _, pairs = bench(spark, sf_dir, TRIED)
    return experiments.timings(run, pairs, experiments.SIX, 1000)


@query()
def distance_sweep(spark, sf_dir):
    return experiments.by_distance(main(spark, sf_dir), experiments.SIX, (2, 4, 6, 8), TRIED, 1000, 3)


@query()
def threshold_sweep(spark, sf_dir):
    run, _, _ = bench(spark, sf_dir, TRIED)
    return experiments.together(experiments.sweep(run, m, "leaf", (2, 5, 10, 20, 50, 100), 1000, REPEATS) for m in ("split", "strata"))


@query()
def strata_sweep(spark, sf_dir):
    run, _, _ = bench(spark, sf_dir, TRIED)
    return experiments.together(experiments.sweep(run, "strata", "r", (1, 5, 10, 25, 50, 100), k, REPEATS) for k in (500, 1000))


def _coupling(name: str, graph: str):
    @query(name=name)
    def run(spark, sf_dir):
        return experiments.coupling(bench(spark, sf_dir, graph=graph)[0], ("skip", "split", "strata"), 1000, 4)


for _name, _graph in (("coupling", "knn"), ("coupling_userflow", "userflow")):
    _coupling(_name, _graph)


@query()
def index_cost(spark, sf_dir):
    return experiments.index_cost(main(spark, sf_dir), 512)


@query()
def refresh_cost(spark, sf_dir):
    return experiments.refresh_cost(main(spark, sf_dir), REFRESHED, LENGTH)


# Links in time.
@query("""SELECT e.event_id, e.ts, e.user_id, (SELECT arg_max(p.event_type, struct_pack(t := p.ts, i := p.event_id)) FROM events p
  WHERE p.user_id = e.user_id AND p.ts <= e.ts AND p.event_type <> 'purchase') AS last_event_type FROM events e WHERE e.event_type = 'purchase'""")
def asof_snapshot(spark, sf_dir):
    events = table(spark, sf_dir, "events")
    left = events.where("event_type = 'purchase'").select("event_id", "ts", "user_id")
    return temporal.asof(left, events.where("event_type <> 'purchase'"), "user_id", "ts", "event_type", "event_id")


@query("""SELECT a.user_id AS src, b.user_id AS dst, count(*) AS meetings FROM events a JOIN events b
ON b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 300 SECOND AND a.user_id <> b.user_id AND (b.ts > a.ts OR b.event_id > a.event_id) GROUP BY ALL""")
def interval_coactivity(spark, sf_dir):
    return temporal.close_in_time(table(spark, sf_dir, "events"), 300)


@query("""WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events),
n AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM e)
SELECT user_id, min(ts) AS start, count(*) AS events FROM n GROUP BY user_id, s""")
def session_coactivity(spark, sf_dir):
    return temporal.sessions(table(spark, sf_dir, "events"))


@query("""WITH d AS (SELECT DISTINCT user_id AS src, event_type AS dst, CAST(floor(epoch(ts) / 86400) AS BIGINT) AS day FROM events)
SELECT src, dst, round(count(*) / ((SELECT max(day) FROM d) - min(day) + 1), 9) AS prob FROM d GROUP BY ALL""")
def stream_snapshot_ratio(spark, sf_dir):
    from relgraph.streaming import ratio

    return ratio.ratios(spark, f"{sf_dir}/events.parquet")


def queries() -> dict:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(SQL)
