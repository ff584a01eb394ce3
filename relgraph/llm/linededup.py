"""Line dedup against sharded minimal perfect hashes.

Lines that stand in several documents form a dictionary. Its 128-bit line hashes are dealt to shards, and
each shard becomes a minimal perfect hash: levels of bit arrays, where hashes that collide at one level move
on to the next, and a line's place is the number of set bits before its own. At that place lie arrays with
the line's fingerprint, its document count and the largest document that holds it. A shard is built once and
written as one row of packed arrays. Documents send their line hashes to the shards and probe the arrays; no line
text is joined. Line hashes are dealt to salted groups by the number of probes that their shard gets, whether these
are of common lines or of lines that no shard knows, and each group gets the shard's packed arrays.

Null or empty texts are one empty line. A row without doc_id is no document to count and keeps its lines. A document
that repeats a line counts once for it. Rows that repeat a doc_id count as one document and each loses the same lines, so
the largest doc_id is never tied. Very long texts are split and hashed as wholes, one text at a time. Extra columns stay
where `clean` is used and are left out elsewhere; columns named like the operator's own are no problem, as it
works on positions. Empty tables: no rows.
"""

from __future__ import annotations

import hashlib
import pickle
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relgraph.llm.common import BLANKS, LOWER, slices, staged, texts, width

LEAST, OFTEN = 20, 3
#: Probes that one group of a shard should get, and lines of the dictionary that a shard should hold, about.
SHARE, SHARD = 200_000, 100_000


def line_key(line: bytes) -> bytes:
    return line.strip(BLANKS).translate(LOWER)


def line_hash(key: bytes) -> tuple[int, int]:
    from xxhash import xxh3_128_intdigest

    h = xxh3_128_intdigest(key)
    return (h >> 64) - (1 << 63), (h & (1 << 64) - 1) - (1 << 63)


def long_enough(key: bytes, least: int) -> bool:
    """At least `least` code points: bytes that do not continue a character."""
    return len(key) >= least and (key.isascii() or sum(b & 0xC0 != 0x80 for b in key) >= least)


@cache
def _mixers() -> tuple[np.uint64, ...]:
    return tuple(np.uint64(x) for x in (0xFF51AFD7ED558CCD, 0xC4CEB9FE1A85EC53))


def mixed(h: np.ndarray, level: int) -> np.ndarray:
    a, b = _mixers()
    x = h ^ np.uint64(0x9E3779B97F4A7C15 * (level + 1) & 0xFFFFFFFFFFFFFFFF)
    x = (x ^ x >> np.uint64(33)) * a
    x = (x ^ x >> np.uint64(33)) * b
    return x ^ x >> np.uint64(33)


class PerfectHash:
    """Minimal perfect hash over distinct 64-bit hashes, two bits a key and level."""

    def __init__(self, hashes: np.ndarray, load: float = 2.0):
        self.levels: list[tuple[np.ndarray, np.ndarray]] = []
        left, base = hashes.astype(np.uint64), 0
        while len(left):
            size = max(64, int(load * len(left)) + 63 & ~63)
            slot = mixed(left, len(self.levels)) % np.uint64(size)
            count = np.bincount(slot.astype(np.int64), minlength=size)
            alone = count == 1
            ranks = base + np.cumsum(alone) - alone
            self.levels.append((alone, ranks))
            base += int(alone.sum())
            left = left[~alone[slot.astype(np.int64)]]
            if len(self.levels) > 200:
                raise ValueError("hashes are not distinct")

    def place(self, hashes: np.ndarray) -> np.ndarray:
        """Place of each known hash; some place or -1 for others."""
        out = np.full(len(hashes), -1)
        open_ = np.arange(len(hashes))
        for n, (alone, ranks) in enumerate(self.levels):
            slot = (mixed(hashes[open_].astype(np.uint64), n) % np.uint64(len(alone))).astype(np.int64)
            hit = alone[slot]
            out[open_[hit]] = ranks[slot[hit]]
            open_ = open_[~hit]
        return out


class Shard:
    """Arrays at the places of a perfect hash: fingerprint, documents, largest document."""

    def __init__(self, high: np.ndarray, low: np.ndarray, count: np.ndarray, largest: np.ndarray):
        self.hash = PerfectHash(high.view(np.uint64))
        at = self.hash.place(high.view(np.uint64))
        self.print, self.count, self.largest = np.empty_like(low), np.empty_like(count), np.empty_like(largest)
        self.print[at], self.count[at], self.largest[at] = low, count, largest

    def packed(self) -> bytes:
        """The arrays as bytes; ranks are left out, as they are counted again."""
        bits = [(len(alone), np.packbits(alone).tobytes()) for alone, _ in self.hash.levels]
        return pickle.dumps((bits, self.print.tobytes(), self.count.tobytes(), self.largest.tobytes()))

    @staticmethod
    def unpacked(body: bytes) -> Shard:
        bits, *arrays = pickle.loads(body)
        own = Shard.__new__(Shard)
        own.hash = PerfectHash(np.zeros(0, np.uint64))
        base = 0
        for size, level in bits:
            alone = np.unpackbits(np.frombuffer(level, np.uint8), count=size).astype(bool)
            own.hash.levels.append((alone, base + np.cumsum(alone) - alone))
            base += int(alone.sum())
        own.print, own.count, own.largest = (np.frombuffer(a, np.int64) for a in arrays)
        return own

    def probe(self, high: np.ndarray, low: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Which hashes are known, and their places."""
        at = self.hash.place(high.view(np.uint64))
        known = at >= 0
        known[known] = self.print[at[known]] == low[known]
        return known, at


def line_hashes(df: DataFrame, least: int) -> DataFrame:
    """(doc_id, high, low) for each distinct line key of at least `least` code points in a document."""

    def run(batches):
        for batch in slices(batches, "text"):
            ids, high, low = [], [], []
            for k, raw in zip(batch.column(0).to_pylist(), texts(batch.column(1)), strict=True):
                for key in {key for line in raw.split(b"\n") if long_enough(key := line_key(line), least)}:
                    a, b = line_hash(key)
                    ids.append(k)
                    high.append(a)
                    low.append(b)
            yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in (ids, high, low)], ["doc_id", "high", "low"])

    return df.mapInArrow(run, "doc_id long, high long, low long")


def drops(df: DataFrame, key: str = "doc_id", text: str = "text", least: int = LEAST, often: int = OFTEN, share: int = SHARE, shard_lines: int = SHARD) -> DataFrame:
    """(doc_id, gone: low hashes of the line keys that this document loses), only documents that lose lines."""
    spark = df.sparkSession
    rows = df.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text")).where("doc_id is not null")
    found = staged(line_hashes(rows, least).distinct(), "lines")
    counted = found.groupBy("high", "low").agg(F.count("*").alias("n"), F.max("doc_id").alias("largest")).where(F.col("n") >= often)
    known = staged(counted, "dictionary")
    shards = max(width(spark), known.count() // shard_lines + 1)
    shard = F.pmod(F.xxhash64("high"), F.lit(shards)).cast("int")

    def build(lines: pa.Table) -> pa.Table:
        high, low, n, largest = (lines.column(c).combine_chunks().to_numpy() for c in ("high", "low", "n", "largest"))
        return pa.table({"shard": lines.column("shard")[:1], "arrays": pa.array([Shard(high, low, n, largest).packed()], pa.binary())})

    arrays = staged(known.withColumn("shard", shard).groupBy("shard").applyInArrow(build, "shard int, arrays binary"), "shards")
    load = found.groupBy(shard.alias("shard")).agg(F.ceil(F.count("*") / share).cast("int").alias("salts"))
    load = staged(load.join(arrays.select("shard"), "shard"), "load")  # a row a shard, of which there are few
    salted = arrays.join(F.broadcast(load), "shard").withColumn("salt", F.explode(F.sequence(F.lit(0), F.col("salts") - 1))).select("shard", "salt", "arrays")
    again = F.broadcast(staged(load, "load"))  # read apart, as both sides of the cogroup derive from it
    probes = found.withColumn("shard", shard).join(again, "shard").withColumn("salt", F.pmod(F.xxhash64("doc_id", F.lit(7)), F.col("salts")).cast("int"))

    def probe(lines: pa.Table, arrays: pa.Table) -> pa.Table:
        if not lines.num_rows or not arrays.num_rows:
            return pa.table({"doc_id": pa.array([], pa.int64()), "low": pa.array([], pa.int64())})
        index = Shard.unpacked(arrays.column("arrays")[0].as_py())
        doc, high, low = (lines.column(c).combine_chunks().to_numpy() for c in ("doc_id", "high", "low"))
        hit, at = index.probe(high, low)
        hit[hit] = index.largest[at[hit]] != doc[hit]
        return pa.table({"doc_id": doc[hit], "low": low[hit]})

    probes = probes.select("shard", "salt", "doc_id", "high", "low")
    gone = probes.groupBy("shard", "salt").cogroup(salted.groupBy("shard", "salt")).applyInArrow(probe, "doc_id long, low long")
    return gone.groupBy("doc_id").agg(F.collect_list("low").alias("gone"))  # lines of one document


def _kept(raw: bytes, gone: set[int]) -> tuple[list[bytes], int]:
    lines = raw.split(b"\n")
    if not gone:
        return lines, len(lines)
    kept = []
    for line in lines:
        key = line_key(line)
        if len(key) < 1 or line_hash(key)[1] not in gone:
            kept.append(line)
    return kept, len(lines)


def clean(df: DataFrame, key: str = "doc_id", text: str = "text", least: int = LEAST, often: int = OFTEN) -> DataFrame:
    """The frame with repeated lines taken out of its text column; other columns as they are.

    A document whose lines all go keeps an empty text.
    """
    names, at = df.columns, df.columns.index(text)
    lost = drops(df, key, text, least, often)
    plain = [f"c{i}" for i in range(len(names))]
    own = df.toDF(*plain)
    joined = own.join(lost, F.col(f"c{names.index(key)}").cast("long") == F.col("doc_id"), "left").drop("doc_id")

    def run(batches):
        for batch in slices(batches, f"c{at}"):
            out = []
            for raw, gone, absent in zip(texts(batch.column(at)), batch.column(len(names)).to_pylist(), batch.column(at).is_null().to_pylist(), strict=True):
                out.append(None if absent else b"\n".join(_kept(raw, set(gone or ()))[0]).decode("utf-8", "replace"))
            columns = [batch.column(i) for i in range(len(names))]
            columns[at] = pa.array(out, pa.string())
            yield pa.RecordBatch.from_arrays(columns, plain)

    return joined.mapInArrow(run, own.schema).toDF(*names)


def digest(df: DataFrame, key: str = "doc_id", text: str = "text", least: int = LEAST, often: int = OFTEN) -> DataFrame:
    """(doc_id, n_lines, n_dropped, kept_sha256) of every document."""
    lost = drops(df, key, text, least, often)
    base = df.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text"))
    joined = base.join(lost, "doc_id", "left").select("doc_id", "text", "gone")

    def run(batches):
        for batch in slices(batches, "text"):
            total, dropped, sums = [], [], []
            for raw, gone in zip(texts(batch.column(1)), batch.column(2).to_pylist(), strict=True):
                kept, n = _kept(raw, set(gone or ()))
                total.append(n)
                dropped.append(n - len(kept))
                sums.append(hashlib.sha256(b"\n".join(kept)).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(total, pa.int64()), pa.array(dropped, pa.int64()), pa.array(sums, pa.string())], ["doc_id", "n_lines", "n_dropped", "kept_sha256"])

    return joined.mapInArrow(run, "doc_id long, n_lines long, n_dropped long, kept_sha256 string")
