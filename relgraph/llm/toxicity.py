"""Toxicity by a factorization machine over hashed terms.

Terms are the distinct words of a text and their first five bytes, hashed; the machine adds a weight for
each and, by factors, one for each pair, so an insult beside a group mention can count for more than both.
It learns from a bounded sample of labelled rows (SAMPLE, the rows with the least hash) and scores every
whole text in Arrow batches, with array operations on bytes only.

Null or empty texts have no terms and get the score of the bias; very long texts are scored whole, one at a time. Null
labels are left out of training; a doc_id labelled more than once is toxic if any label says so, and one that repeats
with different texts is learned from once. Rows that repeat a doc_id are scored each; a score of 0.5 counts as 1. Extra columns
are left out, so names cannot clash. No usable labels: the score is 0. Empty tables: no rows.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relgraph.llm.common import as_bytes, slices

BUCKETS, FACTORS, STEM = 1 << 18, 4, 5
#: Most labelled rows that training uses.
SAMPLE = 10_000
_M1, _M2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_WORD = np.zeros(256, bool)
_WORD[[*range(48, 58), *range(97, 123), *range(128, 256)]] = True
_MASK = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)


def _mix(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    x = (a ^ a >> np.uint64(32)) * _M1 + b
    return (x ^ x >> np.uint64(29)) * _M2


def terms(raw: np.ndarray, borders: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct hashed terms of texts side by side: (text number, bucket), sorted. Borders part words."""
    low = np.concatenate([_LOWER[raw], np.zeros(24, np.uint8)])
    inside = _WORD[low]
    n = len(raw)
    before = np.concatenate([[False], inside[: n - 1]]) if n else np.zeros(0, bool)
    cut = np.zeros(n + 1, bool)
    cut[borders] = True
    start = np.flatnonzero(inside[:n] & (~before | cut[:n]))
    after = ~inside[1 : n + 1] | cut[1:]
    end = np.flatnonzero(inside[:n] & after) + 1
    size = end - start
    doc = np.searchsorted(borders, start, side="right") - 1
    view = np.ndarray((n + 16,), "<u8", low.tobytes(), strides=(1,))
    head = view[start] & _MASK[np.minimum(size, 8)]
    more = view[start + 8] & _MASK[np.clip(size - 8, 0, 8)]
    tail = np.where(size > 16, view[np.maximum(end - 8, 0)], np.uint64(0)) + size.astype(np.uint64)
    word = _mix(_mix(head, more), tail)
    long = size > STEM
    stem = _mix(head[long] & _MASK[STEM], np.uint64(77))
    shift = np.uint64(64 - BUCKETS.bit_length() + 1)
    key = np.concatenate([doc << 18 | (word >> shift).astype(np.int64), doc[long] << 18 | (stem >> shift).astype(np.int64)])
    key = np.unique(key)
    return key >> 18, key & BUCKETS - 1


@dataclass
class Machine:
    """Bias, weights and factors; the sums over a text's terms give its score."""

    bias: float
    weight: np.ndarray
    factor: np.ndarray

    def raw_scores(self, doc: np.ndarray, bucket: np.ndarray, texts: int) -> np.ndarray:
        v = self.factor[bucket]
        total = np.bincount(doc, self.weight[bucket] - 0.5 * (v * v).sum(1), texts).astype(float)  # of no terms it is whole numbers
        for f in range(v.shape[1]):
            total += 0.5 * np.bincount(doc, v[:, f], texts) ** 2
        return total + self.bias

    def scores(self, doc: np.ndarray, bucket: np.ndarray, texts: int) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.raw_scores(doc, bucket, texts), -30, 30)))


def train(docs: list[np.ndarray], labels: np.ndarray, epochs: int = 8, steps: int = 1000, batch: int = 64, rate: float = 0.5, decay: float = 1e-3, apart: float = 3.5, calm: float = 0.01, seed: int = 7) -> Machine:
    """Logistic loss, AdaGrad steps over shuffled batches, on all terms.

    Noise is held down by decay, no term is left out: that of a weight grows as the term's toxic share comes
    within `apart` standard deviations of the overall share, and is the plain one for factors, as words that
    are harmless alone can matter in pairs. Steps of rare terms are small, as their sums start at `calm`."""
    rng = np.random.default_rng(seed)
    if not len(docs) or labels.min() == labels.max():
        return Machine(-30.0 if not len(docs) or not labels.max() else 30.0, np.zeros(BUCKETS), np.zeros((BUCKETS, FACTORS)))
    spread = np.bincount(np.concatenate(docs), minlength=BUCKETS)
    share = labels.mean()
    bad = np.bincount(np.concatenate(docs), np.repeat(labels, [len(d) for d in docs]), BUCKETS)
    z = np.abs(bad - share * spread) / np.sqrt(np.maximum(spread, 1) * share * (1 - share))
    shrink = decay * (apart / np.clip(z, 0.1 * apart, apart)) ** 2
    weight = np.zeros(BUCKETS)
    factor = rng.normal(0, 0.01, (BUCKETS, FACTORS)) * (spread > 0)[:, None]
    seen_w, seen_f = np.full(BUCKETS, calm), np.full((BUCKETS, FACTORS), calm)
    bias, seen_b = float(np.log(share / (1 - share))), 1e-8
    for _ in range(max(epochs, -(-steps * batch // len(docs)))):
        order = rng.permutation(len(docs))
        for at in range(0, len(order), batch):
            own = order[at : at + batch]
            sizes = np.array([len(docs[i]) for i in own])
            if not sizes.sum():
                continue
            bucket = np.concatenate([docs[i] for i in own])
            doc = np.repeat(np.arange(len(own)), sizes)
            m = Machine(bias, weight, factor)
            gap = (m.scores(doc, bucket, len(own)) - labels[own]) / len(own)
            v = factor[bucket]
            sums = np.stack([np.bincount(doc, v[:, f], len(own)) for f in range(FACTORS)], 1)
            each, place = np.unique(bucket, return_inverse=True)
            g = gap[doc]
            gw = np.bincount(place, g, len(each)) + shrink[each] * weight[each]
            gv = np.stack([np.bincount(place, g * (sums[doc, f] - v[:, f]), len(each)) for f in range(FACTORS)], 1) + decay * factor[each]
            seen_w[each] += gw * gw
            seen_f[each] += gv * gv
            weight[each] -= rate * gw / np.sqrt(seen_w[each])
            factor[each] -= 0.2 * rate * gv / np.sqrt(seen_f[each])
            gb = float(gap.sum())
            seen_b += gb * gb
            bias -= rate * gb / np.sqrt(seen_b)
    return Machine(bias, weight.astype(np.float32), factor.astype(np.float32))


def fold(key: str, parts: int):
    """crc32 of the key as text, modulo `parts`; a null key counts as empty text."""
    return F.pmod(F.crc32(F.coalesce(F.col(key).cast("string"), F.lit("")).cast("binary")), F.lit(parts))


def labelled(docs: DataFrame, labels: DataFrame, label: str, parts: int, held: int, most: int, longest: int | None = None) -> DataFrame:
    """(doc_id, text, label) of at most `most` labelled doc_ids outside the held-out fold, by least hash; of a doc_id
    with several texts the one of least hash. Texts of more than `longest` bytes are left out."""
    chosen = labels.where(F.col(label).isNotNull() & F.col("doc_id").isNotNull()).where(fold("doc_id", parts) != held)
    chosen = chosen.groupBy("doc_id").agg(F.max(label).cast("int").alias("label"))
    chosen = chosen.orderBy(F.xxhash64("doc_id"), "doc_id").limit(most)
    text = F.coalesce("text", F.lit(""))
    own = docs.select(F.col("doc_id").cast("long"), text.alias("text"))
    if longest:
        own = own.where(F.octet_length("text") <= longest)
    found = own.join(F.broadcast(chosen), "doc_id")  # at most `most` rows of two numbers
    return found.groupBy("doc_id").agg(F.min(F.struct(F.xxhash64("text"), "text")).alias("t"), F.first("label").alias("label")).select("doc_id", "t.text", "label")


def fit(docs: DataFrame, labels: DataFrame, parts: int = 5, held: int = 0, most: int = SAMPLE) -> Machine:
    def run(batches):
        for part in slices(batches, "text"):
            raw, borders = as_bytes(part.column(1))
            doc, bucket = terms(raw, borders)
            ends = np.searchsorted(doc, np.arange(part.num_rows + 1))
            packed = [bucket[a:b].astype("<i4").tobytes() for a, b in zip(ends, ends[1:], strict=False)]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(packed, pa.binary()), part.column(2)], ["doc_id", "terms", "label"])

    found = labelled(docs, labels, "toxic", parts, held, most).mapInArrow(run, "doc_id long, terms binary, label int").toArrow()
    found = found.sort_by([("doc_id", "ascending"), ("terms", "ascending")])
    return train([np.frombuffer(x, "<i4") for x in found.column("terms").to_pylist()], np.array(found.column("label").to_pylist(), float))


def score(docs: DataFrame, machine: Machine, parts: int = 5, held: int = 0) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every document."""
    shared = docs.sparkSession.sparkContext.broadcast(machine)

    def run(batches):
        m = shared.value
        for part in slices(batches, "text"):
            raw, borders = as_bytes(part.column(1))
            doc, bucket = terms(raw, borders)
            found = m.scores(doc, bucket, part.num_rows)
            kept = [zlib.crc32(b"" if k is None else str(k).encode()) % parts == held for k in part.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(kept), pa.array(found), pa.array((found >= 0.5).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def toxicity(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Learn from the labelled rows outside the held-out fold and score every document."""
    return score(docs, fit(docs, labels))
