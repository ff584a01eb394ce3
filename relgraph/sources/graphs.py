"""Uncertain graphs built from the given tables, each with the SQL that gives the same edges in DuckDB."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from relgraph.functions import probability
from relgraph.functions.coins import coin_sql
from relgraph.model import UncertainGraph, edge_key
from relgraph.sources.tables import table

KEY_SQL = "CAST(src * 4294967296 + dst AS BIGINT) AS edge_id"
#: Customers and suppliers share one id space; suppliers start here.
SUPPLIERS = 1_000_000_000


def copurchase(spark: SparkSession, sf_dir: str, mu: float = 5, first: str | None = None, last: str | None = None) -> UncertainGraph:
    """Parts bought in the same order, in both directions; probability from the number of orders they share.

    All orders count, or those of a range of dates, which reaches the scan of orders. An order's parts meet in one row, so one shuffle by order and one
    by pair do, and the lines are not joined with themselves.
    """
    orders = table(spark, sf_dir, "orders")
    if first:
        orders = orders.where(F.col("o_orderdate") >= F.lit(first).cast("timestamp"))
    if last:
        orders = orders.where(F.col("o_orderdate") < F.lit(last).cast("timestamp"))
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey")
    held = lines.join(orders.select("o_orderkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    sets = held.groupBy("l_orderkey").agg(F.collect_set("l_partkey").alias("parts"))  # the few lines of an order
    pairs = sets.select(F.explode("parts").alias("src"), "parts").select("src", F.explode("parts").alias("dst")).where("src <> dst")
    counts = pairs.groupBy("src", "dst").agg(F.count("*").alias("c"))
    return UncertainGraph.of(counts.select("src", "dst", probability.exp_cdf(F.col("c"), mu).alias("prob")))


def copurchase_sql(mu: float = 5) -> str:
    return f"""WITH held AS (SELECT DISTINCT l_orderkey AS k, l_partkey AS p FROM lineitem JOIN orders ON l_orderkey = o_orderkey),
met AS (SELECT a.p AS src, b.p AS dst, count(*) AS c FROM held a JOIN held b ON a.k = b.k AND a.p <> b.p GROUP BY ALL)
SELECT {KEY_SQL}, src, dst, round(1 - exp(-c / {float(mu)!r}), 9) AS prob FROM met"""


def userflow(spark: SparkSession, sf_dir: str) -> UncertainGraph:
    """From the user of an event to the user of the next event; probability is one over the out-degree.

    The order of events is global. Each day's events are ordered on their own, and the first event of the
    next day that has any is attached, so no task orders the whole table.
    """
    events = table(spark, sf_dir, "events").select("event_id", "ts", "user_id").withColumn("part", F.date_trunc("day", "ts"))
    own = Window.partitionBy("part").orderBy("ts", "event_id")
    heads = events.groupBy("part").agg(F.min_by("user_id", F.struct("ts", "event_id")).alias("head"))  # a row a day
    heads = heads.select("part", F.lead("head").over(Window.orderBy("part")).alias("head"))
    events = events.withColumn("after", F.lead("user_id").over(own)).join(heads, "part")
    links = events.select(F.col("user_id").alias("src"), F.coalesce("after", "head").alias("dst")).where("src <> dst").distinct()
    return UncertainGraph.of(probability.inverse_outdegree(links.where("dst is not null")))


def userflow_sql() -> str:
    return f"""WITH links AS (SELECT DISTINCT src, dst FROM (SELECT user_id AS src, lead(user_id) OVER (ORDER BY ts, event_id) AS dst FROM events)
  WHERE src <> dst)
SELECT {KEY_SQL}, src, dst, round(1.0 / count(*) OVER (PARTITION BY src), 9) AS prob FROM links"""


def custsupp(spark: SparkSession, sf_dir: str) -> UncertainGraph:
    """Customers and suppliers that traded in a month, in both directions; probability is the share of months."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", F.trunc("o_orderdate", "month").alias("period"))
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    seen = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey"))
    seen = seen.select(F.col("o_custkey").alias("src"), (F.col("l_suppkey") + SUPPLIERS).alias("dst"), "period").distinct()
    ratio = probability.snapshot_ratio(seen)
    return UncertainGraph.of(ratio.union(ratio.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "prob")))


def custsupp_sql() -> str:
    return f"""WITH seen AS (SELECT DISTINCT o_custkey AS a, l_suppkey + {SUPPLIERS} AS b, date_trunc('month', o_orderdate) AS m
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey),
ratio AS (SELECT a, b, round(count(*) / (datediff('month', min(m), (SELECT max(m) FROM seen)) + 1), 9) AS prob FROM seen GROUP BY a, b),
both_ways AS (SELECT a AS src, b AS dst, prob FROM ratio UNION ALL SELECT b, a, prob FROM ratio)
SELECT {KEY_SQL}, src, dst, prob FROM both_ways"""


def nation(spark: SparkSession, sf_dir: str) -> UncertainGraph:
    """From a customer's nation to a supplier's other nation, by the share of months with such a trade."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", F.trunc("o_orderdate", "month").alias("period"))
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    customers = table(spark, sf_dir, "customer").select("c_custkey", F.col("c_nationkey").cast("long").alias("src"))
    suppliers = table(spark, sf_dir, "supplier").select("s_suppkey", F.col("s_nationkey").cast("long").alias("dst"))
    seen = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customers, F.col("o_custkey") == F.col("c_custkey"))
    seen = seen.join(suppliers, F.col("l_suppkey") == F.col("s_suppkey")).where("src <> dst").select("src", "dst", "period").distinct()
    return UncertainGraph.of(probability.snapshot_ratio(seen))


def nation_sql() -> str:
    return f"""WITH seen AS (SELECT DISTINCT CAST(c_nationkey AS BIGINT) AS src, CAST(s_nationkey AS BIGINT) AS dst, date_trunc('month', o_orderdate) AS m
  FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey
  WHERE c_nationkey <> s_nationkey)
SELECT {KEY_SQL}, src, dst, round(count(*) / (datediff('month', min(m), (SELECT max(m) FROM seen)) + 1), 9) AS prob FROM seen GROUP BY src, dst"""


#: Most vectors of a group, two of which meet in a task, and the side of a tile of cosines within it.
GROUP, TILE = 1 << 15, 1 << 10


class Vectors:
    """Some vectors with their ids and lengths, and as unit vectors of single precision."""

    def __init__(self, names: np.ndarray, v: np.ndarray):
        self.names, self.v, self.norm = names, v, np.sqrt((v * v).sum(1))
        self.unit = (v / np.where(self.norm > 0, self.norm, 1)[:, None]).astype(np.float32)


class Nearest:
    """The k nearest that some vectors have met so far, by cosine and then by the lesser id."""

    def __init__(self, own: Vectors, k: int):
        self.own, self.cosine, self.near = own, np.full((len(own.names), k), -1.0), np.zeros((len(own.names), k), np.int64)

    def meet(self, rough: np.ndarray, others: Vectors, slice_: int = 1 << 16) -> None:
        """Meet others, whose cosines are known in single precision; what these leave possible is worked out in double."""
        (n, k), m = self.cosine.shape, len(others.names)
        slack = np.float32((self.own.v.shape[1] + 8) * 2.0**-23 + 10.0**-probability.PLACES)
        on = rough > (np.maximum(self.cosine[:, -1], 0).astype(np.float32) - slack)[:, None]
        if m > k and np.count_nonzero(on) > 8 * k * n:
            on &= rough > (np.partition(rough, m - k, axis=1)[:, m - k] - 2 * slack)[:, None]
        rows, columns = np.nonzero(on)
        for a in range(0, len(rows), slice_):
            row, at = rows[a : a + slice_], columns[a : a + slice_]
            value = np.einsum("ij,ij->i", self.own.v[row], others.v[at]) / np.maximum(self.own.norm[row] * others.norm[at], 1e-300)
            value = np.round(value, probability.PLACES)
            new = (value > 0) & (self.own.names[row] != others.names[at])
            row = np.concatenate([np.repeat(np.arange(n), k), row[new]])
            value, near = np.concatenate([self.cosine.ravel(), value[new]]), np.concatenate([self.near.ravel(), others.names[at[new]]])
            order = np.lexsort((near, -value, row))
            best = order[np.searchsorted(row[order], np.arange(n))[:, None] + np.arange(k)]  # each row has at least its former k
            self.cosine, self.near = value[best], near[best]

    def rows(self) -> pa.Table:
        on = self.cosine > 0
        return pa.table({"src": np.repeat(self.own.names, on.sum(1)), "dst": self.near[on], "cosine": self.cosine[on]})


def _nearest_of(met: pa.Table, k: int) -> pa.Table:
    """The k nearest of each vector of two groups in the other group, or of one group in itself; tile by tile."""
    group, names = met.column("part").to_numpy(), met.column("vec_id").to_numpy()
    v = met.column("v").combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(names), -1).astype(float)
    v[~np.isfinite(v).all(1)] = 0  # such vectors, like zero ones, have no nearest and are nobody's
    low, high = int(group.min()), int(group.max())
    tiles = [[Vectors(names[i[a : a + TILE]], v[i[a : a + TILE]]) for a in range(0, len(i), TILE)] for i in (np.flatnonzero(group == low), np.flatnonzero(group == high))]
    ahead, out = [Nearest(own, k) for own in tiles[0]], []
    for others in tiles[1]:
        back = Nearest(others, k)
        for mine in ahead:
            rough = mine.own.unit @ others.unit.T
            if low == high:
                rough[mine.own.names[:, None] == others.names] = -1
            else:
                back.meet(np.ascontiguousarray(rough.T), mine.own)
            mine.meet(rough, others)
        out.append(back.rows())
    return pa.concat_tables([*out, *(mine.rows() for mine in ahead)])


def nearest(spark: SparkSession, sf_dir: str, k: int = 3, blocks: int = 8) -> UncertainGraph:
    """Each vector to its k nearest by cosine, if that is positive; the cosine is the confidence factor.

    Exact search, so its work is quadratic: vectors are dealt to groups by hash, `blocks` of them or as many as keep a group
    to GROUP vectors, every two groups meet once in some task in tiles of TILE by TILE cosines, and each vector
    keeps its k best of each group. So a task's memory has a bound whatever the table; each vector is sent once to every group.
    Null vectors have no edges.
    """
    vectors = table(spark, sf_dir, "embeddings").where("embedding is not null").select("vec_id", F.col("embedding").alias("v"))
    groups = max(blocks, -(-vectors.count() // GROUP))
    dealt = vectors.withColumn("part", F.pmod(F.xxhash64("vec_id"), F.lit(groups)))
    dealt = dealt.withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(groups - 1)).cast("array<long>")))
    dealt = dealt.select((F.least("part", "other") * groups + F.greatest("part", "other")).alias("two"), "part", "vec_id", "v")
    near = dealt.repartition(groups * (groups + 1) // 2, "two").groupBy("two").applyInArrow(lambda met: _nearest_of(met, k), "src long, dst long, cosine double")
    order = Window.partitionBy("src").orderBy(F.desc("cosine"), "dst")
    near = near.withColumn("n", F.row_number().over(order)).where(F.col("n") <= k)
    return UncertainGraph.of(near.select("src", "dst", probability.three_factor(F.lit(1.0), F.lit(1.0), F.col("cosine")).alias("prob")))


def nearest_sql(k: int = 3) -> str:
    return f"""WITH v AS (SELECT vec_id, CAST(embedding AS DOUBLE[]) AS v FROM embeddings),
c AS (SELECT a.vec_id AS src, b.vec_id AS dst,
  round(list_dot_product(a.v, b.v) / (sqrt(list_dot_product(a.v, a.v)) * sqrt(list_dot_product(b.v, b.v))), 9) AS cosine FROM v a JOIN v b ON a.vec_id <> b.vec_id)
SELECT {KEY_SQL}, src, dst, cosine AS prob FROM c WHERE cosine > 0
QUALIFY row_number() OVER (PARTITION BY src ORDER BY cosine DESC, dst) <= {k}"""


def choice(spark: SparkSession, sf_dir: str, seed: int = 17) -> UncertainGraph:
    """The edges of `copurchase` with one of three probabilities at random."""
    return UncertainGraph.of(probability.choice(copurchase(spark, sf_dir).edges.drop("prob"), seed=seed))


def choice_sql(seed: int = 17) -> str:
    return f"""WITH g AS ({copurchase_sql()})
SELECT edge_id, src, dst, [0.1::DOUBLE, 0.01::DOUBLE, 0.001::DOUBLE][CAST(floor({coin_sql(seed, "edge_id")} * 3) AS BIGINT) + 1] AS prob FROM g"""
