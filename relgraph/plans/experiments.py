"""The experiments: fixed numbers of samples, convergence, sweeps, coupling, index cost."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relgraph.functions import measures
from relgraph.model import UncertainGraph
from relgraph.operators import bitmap, kernels, tree
from relgraph.plans import workload
from relgraph.plans.iterate import written
from relgraph.sources.tables import touch

SIX = ("mc", "bitmap", "tree", "skip", "split", "strata")


def together(frames: Iterable[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def solver(g: UncertainGraph, pairs: DataFrame, seed: int = 1, held: dict[str, tree.TreeIndex] | None = None) -> Callable[..., DataFrame]:
    """run(method, k, reps, **parameters): any of the six methods or 'tree+inner'; the tree is built once, and kept in `held` for other pairs."""
    held = {} if held is None else held

    def run(method: str, k: int, reps: int = 1, **params) -> DataFrame:
        if not method.startswith("tree"):
            return kernels.solve(g, pairs, method, k, reps, seed, **params)
        if "tree" not in held:
            held["tree"] = tree.build(g)
        runs = tree.reach(held["tree"], pairs, k, method.partition("+")[2] or "mc", reps, seed, **params)
        return runs.withColumn("method", F.lit(method))

    return run


def fixed(run, methods: Iterable[str], k: int, reps: int) -> DataFrame:
    """Runs of every method with the same number of samples."""
    return together(run(m, k, reps) for m in methods)


def curves(run, methods: Iterable[str], ks: Iterable[int], reps: int) -> DataFrame:
    """(method, k, pairs, v_k, r_k, rho, probes, k_used, depth) for each method and number of samples; repeats are independent at each k."""
    runs = written(together(run(m, k, reps) for m in methods for k in ks), "runs")
    return measures.dispersion(runs).join(measures.cost(runs), ["method", "k"])


def searched(run, method: str, start: int = 250, step: int = 250, limit: int = 2500, reps: int = 100, rho: float = 0.001) -> tuple[int | None, list[DataFrame]]:
    """The first k whose dispersion ratio is below rho (None: not up to the limit), and the runs of each k tried."""
    tried = []
    for k in range(start, limit + 1, step):
        tried.append(written(run(method, k, reps), "converge"))
        found = measures.dispersion(tried[-1]).first()
        if found is not None and found["rho"] is not None and found["rho"] < rho:
            return k, tried
    return None, tried


def converge(run, method: str, *args, **params) -> tuple[int | None, DataFrame]:
    """As `searched`, with the table of all k tried."""
    k, tried = searched(run, method, *args, **params)
    return k, together(measures.dispersion(x) for x in tried)


def convergence_table(run, methods: Iterable[str], **params) -> DataFrame:
    """(method, k, pairs, v_k, r_k, rho, converged) of every k tried for every method."""
    out = []
    for m in methods:
        k, rows = converge(run, m, **params)
        out.append(rows.withColumn("converged", F.lit(k is not None) & (F.col("k") == (k or -1))))
    return together(out)


def errors(run, methods: Iterable[str], k: int, reps: int, reference_k: int = 10_000, reference: str = "mc") -> DataFrame:
    """(method, k, r_k, re, skipped, d, d_without): error against plain sampling at a large k, and how far methods differ."""
    base = run(reference, reference_k, 1).select("pair_id", F.col("r_hat").alias("ref"))
    runs = written(fixed(run, methods, k, reps), "runs")
    found = written(measures.relative_error(runs, written(base, "reference")), "errors")
    both = measures.pairwise_deviation(found).withColumnRenamed("d", "d_all").join(measures.pairwise_deviation(found, reference).withColumnRenamed("d", "d_without"), "k")
    return found.join(measures.dispersion(runs).select("method", "k", "r_k"), ["method", "k"]).join(both, "k")


def over_k(run, methods: Iterable[str], ks: Iterable[int], reps: int, reference_k: int = 10_000) -> DataFrame:
    """(method, k, pairs, r_k, rho, ref, re, skipped, ms, probes, k_used, bytes): reliability, error, time and memory as k grows.

    The reference is plain sampling at a large k; ref is its mean over the pairs.
    """
    methods, ks = list(methods), list(ks)
    base = written(run("mc", reference_k, 1).select("pair_id", F.col("r_hat").alias("ref")), "reference")
    runs = written(together(run(m, k, reps, watch=True) for m in methods for k in ks), "runs")
    found = measures.dispersion(runs).select("method", "k", "pairs", "r_k", "rho").join(measures.relative_error(runs, base), ["method", "k"]).join(_cost(runs), ["method", "k"])
    return found.crossJoin(base.agg(F.avg("ref").alias("ref")))


def _cost(runs: DataFrame) -> DataFrame:
    """(method, k, ms, ms_per_sample, probes, k_used, bytes): mean cost of a run; see `kernels.solve` on ms and bytes."""
    mean = (F.avg(c).alias(c) for c in ("ms", "probes", "k_used", "bytes"))
    return runs.groupBy("method", "k").agg(*mean).withColumn("ms_per_sample", F.col("ms") / F.col("k"))


def full_tables(run, methods: Iterable[str], reps: int, k: int = 1000, limit: int = 2500, rho: float = 0.001) -> DataFrame:
    """(at, method, k, converged, pairs, r_k, rho, re, skipped, d, d_without, ms, ms_per_sample, probes, k_used, bytes) of every
    method at its own convergence and at one k. Errors are against plain sampling at its convergence; a method
    that does not converge up to the limit is shown there, with converged false."""
    methods, step = list(methods), 250
    watched = lambda *a: run(*a, watch=True)
    runs, ends = {"convergence": [], "fixed": []}, {}
    for m in methods:
        end, tried = searched(watched, m, step, step, limit, reps, rho)
        ends[m] = (step * len(tried), end is not None)
        runs["convergence"].append(tried[-1])
        runs["fixed"].append(tried[k // step - 1] if k % step == 0 and len(tried) >= k // step else written(watched(m, k, reps), "fixed"))
    plain = runs["convergence"][methods.index("mc")]
    base = written(plain.groupBy("pair_id").agg(F.avg("r_hat").alias("ref")), "reference")
    met = base.sparkSession.createDataFrame([(m, *e) for m, e in ends.items()], "method string, end int, settled boolean")
    out = []
    for at, parts in runs.items():
        every = together(parts)
        errors_ = written(measures.relative_error(every, base), "errors")
        apart = [measures.pairwise_deviation(errors_.withColumn("k", F.lit(0)), leave).agg(F.max("d").alias(name)) for name, leave in (("d", None), ("d_without", "mc"))]
        found = measures.dispersion(every).select("method", "k", "pairs", "r_k", "rho").join(errors_, ["method", "k"]).join(_cost(every), ["method", "k"])
        found = found.crossJoin(apart[0]).crossJoin(apart[1])  # one row each, null for too few methods
        found = found.join(met, "method").withColumn("converged", F.col("settled") & (F.col("k") == F.col("end"))).drop("settled", "end")
        out.append(found.withColumn("at", F.lit(at)))
    return together(out)


def by_distance(g: UncertainGraph, methods: Iterable[str], hops: Iterable[int], n: int, k: int, reps: int, seed: int = 1) -> DataFrame:
    """(hops, method, k, pairs, v_k, r_k, rho, ...): the same methods for pairs farther and farther apart; distances without pairs are absent."""
    out, held = [], {}
    for h in hops:
        pairs = workload.pairs(g, n, h, seed)
        if not pairs.isEmpty():
            out.append(curves(solver(g, pairs, seed, held), methods, [k], reps).withColumn("hops", F.lit(h)))
    return together(out)


def sweep(run, method: str, name: str, values: Iterable[int], k: int, reps: int) -> DataFrame:
    """(value, method, k, ...): one parameter of a method over a range."""
    return together(curves(lambda m, k_, reps_, v=v: run(m, k_, reps_, **{name: v}), [method], [k], reps).withColumn("value", F.lit(v)) for v in values)


def coupling(run, inners: Iterable[str], k: int, reps: int) -> DataFrame:
    """Each inner method alone and on the tree's query graphs: reliability and probes."""
    return curves(run, [m for i in inners for m in (i, f"tree+{i}")], [k], reps)


def timed(frame: DataFrame) -> float:
    """Seconds to work a frame out."""
    began = time.perf_counter()
    touch(frame)
    return time.perf_counter() - began


def timings(run, pairs: DataFrame, methods: Iterable[str], k: int, reps: int = 1) -> DataFrame:
    """(method, k, seconds_per_query, ms_per_sample): wall time of a batch, by its queries. Of this engine only."""
    spark, n = pairs.sparkSession, max(1, pairs.count())
    rows = []
    for m in methods:
        s = timed(run(m, k, reps)) / (n * reps)
        rows.append((m, k, s, s / k * 1000))
    return spark.createDataFrame(rows, "method string, k int, seconds_per_query double, ms_per_sample double")


def index_cost(g: UncertainGraph, worlds: int = 1536, hops: int | None = None) -> DataFrame:
    """(index, rows, build_s, load_s, bytes) of the bitmap index and of the tree with and without distance distributions."""
    spark = g.edges.sparkSession
    rows = []

    def kept(label: str, make: Callable[[], Iterable[DataFrame]], build_more: float = 0) -> None:
        began = time.perf_counter()
        frames = [written(f, "index") for f in make()]
        built = time.perf_counter() - began
        began = time.perf_counter()
        counts = [f.count() for f in frames]
        for f in frames:
            touch(f)
        rows.append((label, sum(counts), built + build_more, time.perf_counter() - began, sum(_bytes(spark, f) for f in frames)))

    kept("bitmap", lambda: [bitmap.build(g, worlds, fast=True)])
    for label, h in (("tree", None), ("tree with distances", hops or 8)):
        kept(label, lambda h=h: (lambda i: (i.bags, i.bag_edges, i.root))(tree.build(g, hops=h)))
    return spark.createDataFrame(rows, "index string, rows long, build_s double, load_s double, bytes long")


def _bytes(spark, frame: DataFrame) -> int:
    """Size of a written table's files, by the store's own listing."""
    jvm, total = spark.sparkContext._jvm, 0
    for name in frame.inputFiles():
        path = jvm.org.apache.hadoop.fs.Path(name)
        total += path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(path).getLen()
    return total


def refresh_cost(g: UncertainGraph, queries: int = 1000, worlds: int = 1500) -> DataFrame:
    """(queries, worlds, seconds_per_refresh) of redrawing the whole bitmap index before each of successive queries, one refresh after
    the other. As every edge is drawn anew, the cost does not depend on the queries, which are not answered here."""
    spark = g.edges.sparkSession
    even = UncertainGraph(written(g.edges.repartition(spark.sparkContext.defaultParallelism), "edges"))
    total = sum(timed(bitmap.build(even, worlds, epoch=e, fast=True)) for e in range(1, queries + 1))
    return spark.createDataFrame([(queries, worlds, total / queries)], "queries int, worlds int, seconds_per_refresh double")
