"""Embedding near-duplicates by product quantisation.

Vectors, scaled to length one, fall into coarse lists; within a list their residuals become codes, a code
word for each subspace, along with the distance that the code is off by. Lists have two levels, a coarse centre and one
of a second set of centres for what is left over, so that their number grows with the table although both sets are
fitted on a bounded sample: a list holds about PER_LIST vectors up to MOST_CENTRES^2 lists. A query visits the lists
nearest to it, except those whose side of a bisector, on either level, lies beyond the linking distance; it sums table
entries to get its distance from each code, keeps what the code's own error could bring within reach, and takes the
exact cosine in double precision of these. Coarse centres and code words are fitted on a bounded sample
(SAMPLE); every vector is indexed and every vector is a query.

A pair is counted once, for both ends, whichever of them finds it. Equal vectors are merged before the
search and counted by their number; a list with many rows or queries, as of vectors too alike to part, is dealt to
blocks, each pair of which meets in one task. Groups return sums and a spanning forest, never pairs.

Null vectors, zero vectors, those with null or non-finite components, and those whose length is not the
table's most frequent one link with nothing. Rows that repeat a vec_id count as vectors of their own; a null
vec_id is left out. The least vec_id names a component, so ties cannot be. Very long vectors only make batches larger. Other
columns are left out, so names cannot clash. Empty tables: no rows.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relgraph.llm.common import components, local_roots, staged

COSINE, SAMPLE, PER_LIST, MOST_CENTRES, PROBES = 0.95, 16_384, 128, 4096, 16
PARTS, WORDS, BLOCK = 8, 256, 8192


def kmeans(x: np.ndarray, k: int, rounds: int, rng: np.random.Generator) -> np.ndarray:
    centres = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        near = (x @ centres.T - 0.5 * (centres**2).sum(1)).argmax(1)
        count = np.bincount(near, minlength=len(centres))
        order = np.argsort(near, kind="stable")
        full = np.flatnonzero(count)
        starts = (np.cumsum(count) - count)[full]
        centres[full] = np.add.reduceat(x[order], starts, axis=0) / count[full, None]
    return centres


@dataclass
class Quantiser:
    """Coarse centres, second centres of what is left over, code words of each subspace, and the distance at which vectors link."""

    centres: np.ndarray
    second: np.ndarray
    words: list[np.ndarray]
    reach: float
    probes: int

    def borders(self) -> np.ndarray:
        n = self.centres.shape[1]
        return np.array([n * i // len(self.words) for i in range(len(self.words) + 1)])

    def centre(self, home: np.ndarray) -> np.ndarray:
        """The place that a list's residuals are counted from."""
        return self.centres[home // len(self.second)] + self.second[home % len(self.second)]

    def probe(self, x: np.ndarray) -> np.ndarray:
        """Lists that each vector visits, its own first, then the nearest; -1 fills up."""
        near, own = visited(x, self.centres, self.probes, self.reach)
        if len(self.second) == 1:
            return near
        found, apart = [], []
        for j in range(near.shape[1]):
            left = x - self.centres[np.maximum(near[:, j], 0)]
            lists, d2 = visited(left, self.second, self.probes, self.reach)
            there = (lists >= 0) & (near[:, j] >= 0)[:, None]
            found.append(np.where(there, near[:, j, None] * len(self.second) + lists, -1))
            apart.append(np.where(there, d2, np.inf))
        found, apart = np.concatenate(found, 1), np.concatenate(apart, 1)
        apart[:, 0] = -1  # the own list: nearest centre, then nearest second centre
        order = np.argsort(apart, axis=1, kind="stable")[:, : 2 * self.probes]
        return np.take_along_axis(found, order, 1)

    def encode(self, x: np.ndarray, home: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Codes of the residuals, and by how much each code is off."""
        left = x - self.centre(home)
        codes, off = np.zeros((len(x), len(self.words)), np.uint8), np.zeros(len(x))
        b = self.borders()
        for m, words in enumerate(self.words):
            part = left[:, b[m] : b[m + 1]]
            codes[:, m] = (part @ words.T - 0.5 * (words**2).sum(1)).argmax(1)
            off += ((part - words[codes[:, m]]) ** 2).sum(1)
        return codes, np.sqrt(off)

    def distances(self, x: np.ndarray, home: int, codes: np.ndarray) -> np.ndarray:
        """Squared distance of each query from each code of a list, by sums over lookup tables."""
        left, b = x - self.centre(np.array([home])), self.borders()
        total = np.zeros((len(x), len(codes)), np.float32)
        for m, words in enumerate(self.words):
            part = left[:, b[m] : b[m + 1]]
            lookup = ((part**2).sum(1)[:, None] - 2 * part @ words.T + (words**2).sum(1)).astype(np.float32)
            total += lookup[:, codes[:, m]]
        return np.maximum(total, 0)


def visited(x: np.ndarray, centres: np.ndarray, probes: int, reach: float) -> tuple[np.ndarray, np.ndarray]:
    """The nearest centres of each vector, -1 for those in whose cell nothing can be within reach of it, and their squared distances."""
    d2 = np.maximum((x**2).sum(1)[:, None] - 2 * x @ centres.T + (centres**2).sum(1), 0)
    k = min(probes, len(centres))
    near = np.argpartition(d2, k - 1, axis=1)[:, :k]
    own = np.take_along_axis(d2, near, 1)
    order = np.argsort(own, axis=1, kind="stable")
    near, own = np.take_along_axis(near, order, 1), np.take_along_axis(own, order, 1)
    apart = np.linalg.norm(centres[near] - centres[near[:, :1]], axis=2)
    behind = (own - own[:, :1]) / np.maximum(2 * apart, 1e-12)
    return np.where(behind <= reach + 1e-6, near, -1), own


def fit(sample: np.ndarray, rows: int, cosine: float, probes: int, seed: int = 3, most: int = MOST_CENTRES) -> Quantiser:
    """most: centres on each level; the second level has one centre, nothing, until the first is full."""
    rng = np.random.default_rng(seed)
    lists = max(1, rows // PER_LIST)
    centres = kmeans(sample, max(1, min(most, lists, len(sample) // 4)), 10, rng)
    left = sample - centres[(sample @ centres.T - 0.5 * (centres**2).sum(1)).argmax(1)]
    second = np.zeros((1, sample.shape[1]))
    if lists > len(centres) == most:
        second = kmeans(left, max(1, min(most, -(-lists // len(centres)), len(sample) // 4)), 10, rng)
        left = left - second[(left @ second.T - 0.5 * (second**2).sum(1)).argmax(1)]
    parts = min(PARTS, sample.shape[1])
    b = [sample.shape[1] * i // parts for i in range(parts + 1)]
    words = [kmeans(np.ascontiguousarray(left[:, x:y]), WORDS, 8, rng) for x, y in zip(b, b[1:], strict=False)]
    return Quantiser(centres, second, words, float(np.sqrt(2 - 2 * cosine)), probes)


def unit(packed: list[bytes]) -> np.ndarray:
    x = np.frombuffer(b"".join(packed), "<f8").reshape(len(packed), -1)
    return x / np.sqrt((x * x).sum(1))[:, None] if len(packed) else x


def _vectors(df: DataFrame, key: str, vector: str) -> DataFrame:
    """(vec_id, v): the components as packed doubles, scaled by a power of two; null if the vector links with nothing."""

    def run(batches):
        for batch in batches:
            out = []
            for x in batch.column(1).to_pylist():
                packed = None
                if x and None not in x:
                    a = np.array(x, "<f8")
                    if np.isfinite(a).all() and (top := np.abs(a).max()) > 0:
                        packed = np.ldexp(a, -int(np.frexp(top)[1])).tobytes()
                out.append(packed)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], ["vec_id", "v"])

    return df.select(F.col(key).cast("long").alias("vec_id"), F.col(vector)).where("vec_id is not null").mapInArrow(run, "vec_id long, v binary")


def search(stored: pa.Table, asked: pa.Table, model: Quantiser, cosine: float, chunk: int = 256) -> pa.Table:
    """Links between a block of stored vectors and a block of queries of one list: (node, root, n)."""
    empty = pa.table({"node": pa.array([], pa.int64()), "root": pa.array([], pa.int64()), "n": pa.array([], pa.int64())})
    if not stored.num_rows or not asked.num_rows:
        return empty
    get = lambda t, c: t.column(c).combine_chunks().to_numpy(zero_copy_only=False)
    home = int(get(stored, "list")[0])
    t_id, t_size, t_off = get(stored, "id"), get(stored, "size"), get(stored, "off")
    codes = np.frombuffer(b"".join(stored.column("code").to_pylist()), np.uint8).reshape(len(t_id), -1)
    visits = np.frombuffer(b"".join(stored.column("visits").to_pylist()), "<i4").reshape(len(t_id), -1)
    q_id, q_size, q_home = get(asked, "id"), get(asked, "size"), get(asked, "home")
    t, q = unit(stored.column("v").to_pylist()), unit(asked.column("v").to_pylist())
    limit = ((model.reach + t_off) ** 2 * (1 + 1e-5) + 1e-5).astype(np.float32)
    left, right = [], []
    for a in range(0, len(q_id), chunk):
        own = q[a : a + chunk]
        near = model.distances(own, home, codes) <= limit
        rows, cols = np.flatnonzero(near.any(1)), np.flatnonzero(near.any(0))
        if not len(rows):
            continue
        exact = own[rows] @ t[cols].T
        i, j = np.nonzero((exact >= cosine) & near[np.ix_(rows, cols)])
        i, j = a + rows[i], cols[j]
        other = np.zeros(len(i), bool)
        for s in range(0, len(i), 1 << 18):
            part = slice(s, s + (1 << 18))
            other[part] = (visits[j[part]] == q_home[i[part]][:, None]).any(1)
        keep = (q_id[i] < t_id[j]) | ~other & (q_id[i] != t_id[j])
        left.append(i[keep])
        right.append(j[keep])
    if not sum(map(len, left)):
        return empty
    i, j = np.concatenate(left), np.concatenate(right)
    nodes, place = np.unique(np.concatenate([q_id, t_id]), return_inverse=True)
    p, r = place[i], place[len(q_id) + j]
    n = np.bincount(p, t_size[j], len(nodes)) + np.bincount(r, q_size[i], len(nodes))
    root = local_roots(len(nodes), p, r)
    seen = np.flatnonzero(n)
    return pa.table({"node": nodes[seen], "root": nodes[root[seen]], "n": n[seen].astype(np.int64)})


def near_duplicates(df: DataFrame, key: str = "vec_id", vector: str = "embedding", cosine: float = COSINE, probes: int = PROBES, most: int = MOST_CENTRES, block: int = BLOCK) -> DataFrame:
    """(vec_id, n_links, component_id, kept) of every vector; most and block: centres on a level, rows of a block."""
    spark = df.sparkSession
    vectors = staged(_vectors(df, key, vector), "vectors")
    sized = vectors.where("v is not null").groupBy(F.octet_length("v").alias("size")).count()
    usual = sized.orderBy(F.desc("count"), "size").first()
    usual = usual["size"] if usual else 0
    fit_ = vectors.where(F.octet_length("v") == usual)
    classes = staged(fit_.groupBy("v").agg(F.min("vec_id").alias("id"), F.count("*").alias("size")), "classes")
    rows = classes.count()
    if rows:
        taken = [bytes(r["v"]) for r in classes.orderBy(F.xxhash64("v"), "id").limit(SAMPLE).select("v").collect()]  # at most SAMPLE vectors
        model = fit(unit(taken), rows, cosine, probes, most=most)
    else:
        model = Quantiser(np.zeros((1, 1)), np.zeros((1, 1)), [np.zeros((1, 1))], 0.0, 1)
    shared = spark.sparkContext.broadcast(model)

    def index(batches):
        m = shared.value
        for batch in batches:
            if not batch.num_rows:
                continue
            x = unit(batch.column(0).to_pylist())
            visits = m.probe(x)
            codes, off = m.encode(x, visits[:, 0])
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column(1), batch.column(2), batch.column(0), pa.array(visits[:, 0].astype(np.int32)), pa.array(off),
                    pa.array([c.tobytes() for c in codes], pa.binary()), pa.array([v.astype("<i4").tobytes() for v in visits], pa.binary()),
                    pa.array([v[v >= 0].tolist() for v in visits], pa.list_(pa.int32())),
                ],
                ["id", "size", "v", "home", "off", "code", "visits", "lists"],
            )

    indexed = staged(classes.select("v", "id", "size").mapInArrow(index, "id long, size long, v binary, home int, off double, code binary, visits binary, lists array<int>"), "index")
    asked = indexed.select("id", "size", "v", "home", F.explode("lists").alias("list"))
    # How many blocks a list's rows and its queries are dealt to, where that is more than one.
    held = indexed.groupBy(F.col("home").alias("list")).agg(F.ceil(F.count("*") / block).cast("int").alias("blocks"))
    wanted = asked.groupBy("list").agg(F.ceil(F.count("*") / block).cast("int").alias("shares"))
    # Only lists of more than a block are broadcast: one for each `block` rows or visits at most.
    deal = staged(held.join(wanted, "list").where("blocks > 1 or shares > 1").withColumnRenamed("list", "crowded"), "deal")
    one = lambda c: F.coalesce(F.col(c), F.lit(1))
    stored = indexed.join(F.broadcast(deal), indexed.home == deal.crowded, "left").select(
        F.col("home").alias("list"), F.pmod(F.xxhash64("id"), one("blocks")).cast("int").alias("block"), F.explode(F.sequence(F.lit(0), one("shares") - 1)).alias("share"),
        "id", "size", "v", "off", "code", "visits",
    )
    again = F.broadcast(staged(deal, "deal"))
    asked = staged(indexed, "queries").select("id", "size", "v", "home", F.explode("lists").alias("list"))
    asked = asked.join(again, F.col("list") == F.col("crowded"), "left").select(
        "list", F.explode(F.sequence(F.lit(0), one("blocks") - 1)).alias("block"), F.pmod(F.xxhash64("id", F.lit(5)), one("shares")).cast("int").alias("share"),
        "id", "size", "v", "home",
    )
    keys = ["list", "block", "share"]
    found = stored.groupBy(*keys).cogroup(asked.groupBy(*keys)).applyInArrow(lambda a, b: search(a, b, shared.value, cosine), "node long, root long, n long")
    found = staged(found, "found")
    sums = found.groupBy("node").agg(F.sum("n").alias("n"))
    joined = components(found.select(F.col("node").alias("a"), F.col("root").alias("b"))).select(F.col("node").alias("id"), "component")
    named = classes.join(sums.withColumnRenamed("node", "id"), "id", "left").join(joined, "id", "left")
    named = named.select("v", (F.coalesce("n", F.lit(0)) + F.col("size") - 1).alias("n_links"), F.coalesce("component", "id").alias("component_id"))
    alone = F.octet_length("v").isNull() | (F.octet_length("v") != usual)  # link with nothing, so they need not be dealt by their vector
    rest = vectors.where(alone).select("vec_id", F.lit(None).cast("long").alias("n_links"), F.lit(None).cast("long").alias("component_id"))
    return vectors.where(~alone).join(named, "v", "left").select("vec_id", "n_links", "component_id").union(rest).select(
        "vec_id",
        F.coalesce("n_links", F.lit(0).cast("long")).alias("n_links"),
        F.coalesce("component_id", "vec_id").alias("component_id"),
        (F.col("vec_id") == F.coalesce("component_id", "vec_id")).alias("kept"),
    )
