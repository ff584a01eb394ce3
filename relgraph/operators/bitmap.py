"""World-bitmap index: 64 worlds of an edge in one long, and one traversal for all of them.

The index holds (edge_id, src, dst, word, bits, epoch). A traversal keeps the worlds that reach each node and
sends on only those that are new, until nothing changes; as a node may gain worlds several times, no order of
visits is assumed. Worlds come from the same coins as plain sampling, so both count the same hits.

An index of up to kernels.MOST_EDGES lines is sent to the workers, each of which takes a start from its first hop to its last; over a
larger one all starts advance by a join a hop, each hop a round of jobs.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from relgraph.functions.coins import coin, coin_sql, fast_words
from relgraph.model import UncertainGraph
from relgraph.operators import kernels
from relgraph.plans.iterate import Store, written

WORD = 64


def build(g: UncertainGraph, worlds: int = 1536, seed: int = 1, epoch: int = 0, fast: bool = False) -> DataFrame:
    """The index of so many worlds. The epoch is part of the coins' key, as a repeat is in plain sampling."""
    if fast:
        return _drawn(g, worlds, seed, epoch)
    words = -(-worlds // WORD)
    rows = g.edges.withColumn("word", F.explode(F.sequence(F.lit(0), F.lit(words - 1)))).withColumn("epoch", F.lit(epoch))

    def bit(i):
        here = F.col("word") * WORD + i
        on = (here < worlds) & (coin(seed, "epoch", here, "edge_id") < F.col("prob"))
        return F.when(on, F.call_function("shiftleft", F.lit(1).cast("long"), i)).otherwise(F.lit(0).cast("long"))

    bits = F.aggregate(F.sequence(F.lit(0), F.lit(WORD - 1)), F.lit(0).cast("long"), lambda a, i: a.bitwiseOR(bit(i)))
    return rows.select("edge_id", "src", "dst", "word", bits.alias("bits"), "epoch")


def _drawn(g: UncertainGraph, worlds: int, seed: int, epoch: int) -> DataFrame:
    """The index from the xxhash64 coins, worked out in the workers."""
    names = ["edge_id", "src", "dst", "word", "bits", "epoch"]

    def run(batches):
        for batch in batches:
            ends = [batch.column(c) for c in names[:3]]
            prob = batch.column("prob").fill_null(0).to_numpy(zero_copy_only=False)
            epochs = pa.array(np.full(len(prob), epoch, np.int32))
            for word, bits in enumerate(fast_words(ends[0].to_numpy(zero_copy_only=False), prob, worlds, seed, epoch)):
                yield pa.RecordBatch.from_arrays([*ends, pa.array(np.full(len(prob), word, np.int32)), pa.array(bits), epochs], names)

    return g.edges.select(*names[:3], "prob").mapInArrow(run, "edge_id long, src long, dst long, word int, bits long, epoch int")


def refresh(g: UncertainGraph, index: DataFrame, epoch: int, worlds: int, seed: int = 1, touched: DataFrame | None = None) -> DataFrame:
    """The index of a new epoch; with `touched` (edge_id), only those edges are drawn anew and others keep their bits."""
    if touched is None:
        return build(g, worlds, seed, epoch)
    some = UncertainGraph(g.edges.join(touched.select("edge_id").distinct(), "edge_id", "left_semi").select("edge_id", "src", "dst", "prob"))
    return index.join(touched.select("edge_id").distinct(), "edge_id", "left_anti").unionByName(build(some, worlds, seed, epoch))


def mask(k: int, word=None):
    """Bits of a word that belong to the first k worlds."""
    word = F.col("word") if word is None else word
    left = F.lit(k) - word * WORD
    part = F.call_function("shiftleft", F.lit(1).cast("long"), F.greatest(F.lit(0), F.least(left, F.lit(WORD - 1))).cast("int")) - 1
    return F.when(left >= WORD, F.lit(-1).cast("long")).when(left <= 0, F.lit(0).cast("long")).otherwise(part)


def _sent(lines: DataFrame, first: DataFrame, max_hops: int | None, retire: bool) -> DataFrame:
    """(start, node, word, bits) of each of the first rows (start, node, word, bits, t), from whole traversals in the workers."""
    spark = lines.sparkSession
    src, dst, word, have = (c.to_numpy() for c in lines.select("src", "dst", "word", "have").toArrow().columns)
    held = {}
    for w in np.unique(word).tolist():
        on = np.flatnonzero(word == w)
        g, order = kernels.Local.placed(src[on], dst[on], np.zeros(len(on)))
        held[w] = g, have[on[order]]
    shared = spark.sparkContext.broadcast(held)
    names = ["start", "node", "word", "bits"]
    kind = ", ".join(f"{c} {first.schema[c].dataType.simpleString()}" for c in names)

    def run(batches):
        for batch in batches:
            for row in batch.to_pylist():
                if row["word"] in shared.value:
                    node, bits = _spread(*shared.value[row["word"]], row["node"], row["bits"], row["t"] if retire else None, max_hops)
                else:
                    node, bits = np.array([row["node"]]), np.array([row["bits"]])
                for a in range(0, len(node), 1 << 16):
                    n = len(node[a : a + (1 << 16)])
                    start, word = (pa.array([row[c]] * n, batch.schema.field(c).type) for c in ("start", "word"))
                    yield pa.RecordBatch.from_arrays([start, pa.array(node[a : a + n]), word, pa.array(bits[a : a + n])], names)

    tasks = first.repartition(spark.sparkContext.defaultParallelism * 2, F.xxhash64("start", "word"))
    return tasks.mapInArrow(run, kind)


def _spread(g: kernels.Local, have: np.ndarray, start: int, bits: int, t: int | None, max_hops: int | None) -> tuple[np.ndarray, np.ndarray]:
    """The nodes that the start reaches in some world of a word, and in which; worlds that have reached t go no further."""
    at, end = g.at(start), g.at(t) if t is not None else -1
    if at < 0:
        return np.array([start]), np.array([bits])
    known = np.zeros(len(g.names), np.int64)
    known[at] = bits
    fresh, new, n = np.array([at]), np.array([bits]), 0
    while len(fresh) and (max_hops is None or n < max_hops):
        if end >= 0:
            new = new & ~known[end]
        e, which = g.edges_of(fresh)
        got, dst = new[which] & have[e], g.dst[e]
        dst, got = dst[got != 0], got[got != 0]
        order = np.argsort(dst, kind="stable")
        fresh, first = np.unique(dst[order], return_index=True)
        new = (np.bitwise_or.reduceat(got[order], first) if len(first) else got) & ~known[fresh]
        fresh, new = fresh[new != 0], new[new != 0]
        known[fresh] |= new
        n += 1
    on = np.flatnonzero(known)
    return g.names[on], known[on]


def traverse(index: DataFrame, starts: DataFrame, k: int, max_hops: int | None = None, retire: bool = False) -> DataFrame:
    """(start, node, word, bits): the first k worlds in which each start (start, node, t) reaches each node.

    retire drops worlds that have reached t already; answers for other nodes are then too low.
    """
    words = -(-k // WORD)
    lines = index.where(F.col("word") < words).select("src", "dst", "word", F.col("bits").bitwiseAND(mask(k)).alias("have")).where("have <> 0")
    first = starts.withColumn("word", F.explode(F.sequence(F.lit(0), F.lit(words - 1)))).select("start", "node", "word", mask(k).alias("bits"), "t")
    if lines.count() <= kernels.MOST_EDGES:
        return _sent(lines, first, max_hops, retire).groupBy("start", "node", "word").agg(F.bit_or("bits").alias("bits"))
    store = Store(starts.sparkSession, "bitmap")
    fresh, n = store.add(first), 0
    while max_hops is None or n < max_hops:
        if retire:
            done = store.all().where("node = t").groupBy("start", "word").agg(F.bit_or("bits").alias("done"))
            fresh = fresh.join(done, ["start", "word"], "left").withColumn("bits", F.col("bits").bitwiseAND(F.bitwise_not(F.coalesce("done", F.lit(0).cast("long"))))).drop("done")
        sent = fresh.withColumnRenamed("word", "word2").join(lines, (F.col("node") == F.col("src")) & (F.col("word2") == F.col("word")))
        sent = sent.select("start", F.col("dst").alias("node"), "word", F.col("bits").bitwiseAND(F.col("have")).alias("bits"), "t").where("bits <> 0")
        sent = sent.groupBy("start", "node", "word", "t").agg(F.bit_or("bits").alias("bits"))
        known = store.all().groupBy("start", "node", "word").agg(F.bit_or("bits").alias("known"))
        gained = F.col("bits").bitwiseAND(F.bitwise_not(F.coalesce("known", F.lit(0).cast("long"))))
        fresh = store.add(sent.join(known, ["start", "node", "word"], "left").select("start", "node", "word", gained.alias("bits"), "t").where("bits <> 0"))
        n += 1
        if fresh.isEmpty():
            break
    return store.all().groupBy("start", "node", "word").agg(F.bit_or("bits").alias("bits"))


def reach(index: DataFrame, pairs: DataFrame, k: int, max_hops: int | None = None, retire: bool = False) -> DataFrame:
    """(method, pair_id, s, t, rep, k, hits, r_hat) by one shared traversal of the index."""
    starts = pairs.where("s <> t").select(F.col("pair_id").alias("start"), F.col("s").alias("node"), "t")
    seen = traverse(index, starts, k, max_hops, retire)
    hits = seen.groupBy(F.col("start").alias("pair_id"), F.col("node").alias("t")).agg(F.sum(F.bit_count("bits")).alias("hits"))
    found = F.when(F.col("s") == F.col("t"), F.lit(k)).otherwise(F.coalesce("hits", F.lit(0))).cast("long")
    out = pairs.select("pair_id", "s", "t").join(hits, ["pair_id", "t"], "left").withColumn("hits", found)
    return out.select(F.lit("bitmap").alias("method"), "pair_id", "s", "t", F.lit(0).alias("rep"), F.lit(k).alias("k"), "hits", (F.col("hits") / F.lit(k)).alias("r_hat"))


def all_targets(index: DataFrame, sources: DataFrame, k: int) -> DataFrame:
    """(s, node, hits, r_hat): reliability from each source to every node it reaches, itself left out."""
    starts = sources.select(F.col("s").alias("start"), F.col("s").alias("node"), F.lit(-1).cast("long").alias("t")).distinct()
    seen = traverse(index, starts, k).where("start <> node")
    counted = seen.groupBy(F.col("start").alias("s"), "node").agg(F.sum(F.bit_count("bits")).cast("long").alias("hits"))
    return counted.withColumn("r_hat", F.col("hits") / F.lit(k))


def top_targets(index: DataFrame, sources: DataFrame, n: int, k: int) -> DataFrame:
    """The n most reliable targets of each source, ties by node, with their rank."""
    order = Window.partitionBy("s").orderBy(F.desc("hits"), "node")
    return all_targets(index, sources, k).withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= n)


def build_sql(graph: str, worlds: int, seed: int = 1, epoch: int = 0) -> str:
    """The index for DuckDB. Bit 63 is the sign."""
    words = -(-worlds // WORD)
    return f"""WITH g AS ({graph}),
drawn AS (SELECT edge_id, src, dst, w.range AS world FROM g, range({words * WORD}) w
  WHERE w.range < {worlds} AND {coin_sql(seed, str(epoch), "w.range", "edge_id")} < prob),
folded AS (SELECT edge_id, world // {WORD} AS word, sum(1::HUGEINT << CAST(world % {WORD} AS INTEGER)) AS bits FROM drawn GROUP BY ALL)
SELECT edge_id, src, dst, CAST(w.range AS INTEGER) AS word,
  CAST(CASE WHEN coalesce(bits, 0) >= 9223372036854775808 THEN bits - 18446744073709551616 ELSE coalesce(bits, 0) END AS BIGINT) AS bits, {epoch} AS epoch
FROM g CROSS JOIN range({words}) w LEFT JOIN folded f ON f.edge_id = g.edge_id AND f.word = w.range""".replace("SELECT edge_id, src, dst, CAST(w", "SELECT g.edge_id, src, dst, CAST(w")
