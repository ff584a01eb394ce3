"""Text quality by a byte-level convolutional network, written with numpy.

Each byte becomes a learned vector, with one more input that tells whether the four bytes before it stood a
short way earlier as well. Filters slide over overlapping chunks of bytes, over the whole text with its end
padded; each filter's largest response anywhere in the text is kept, and a logistic unit combines these into one
probability. The network learns from a bounded sample of labelled rows (SAMPLE, the rows with the least
hash) by whole texts of up to SAMPLE_BYTES bytes, so what the driver holds is bounded by their product.

Null or empty texts are one chunk of padding; very long texts are scored whole, one at a time. Null labels are left out of
training; a doc_id labelled more than once is good if any label says so, and one that repeats with different texts is
learned from once. Rows that repeat a doc_id are scored each; a score of 0.5 counts as 1. Extra columns are left out (`accepted` keeps
them), so names cannot clash. No usable labels: the score is 1, as nothing speaks against a text. Empty tables: no rows.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relgraph.llm.common import as_bytes, slices
from relgraph.llm.toxicity import labelled

CHUNK, STRIDE, FILTERS, DIM = 16, 4, 16, 8
ECHO = range(3, 25)
#: Most labelled rows that training uses.
SAMPLE = 4_000
#: Most bytes of a text that training uses; longer ones are not learned from.
SAMPLE_BYTES = 1 << 15


def symbols(raw: np.ndarray, borders: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Texts side by side as symbols (byte, plus 256 where the last four bytes are an echo), each padded to whole
    chunks; and the borders of the texts in chunks."""
    sizes = np.diff(borders)
    chunks = np.maximum(0, -(-(sizes - CHUNK) // STRIDE)) + 1
    room = (chunks - 1) * STRIDE + CHUNK
    ends = np.cumsum(room)
    out = np.zeros(int(ends[-1]) if len(ends) else 0, np.int16)
    at = np.arange(len(raw)) + np.repeat(ends - room - borders[:-1], sizes)
    out[at] = raw
    if len(raw) > 4:
        view = np.ndarray((len(raw) - 3,), "<u4", raw.tobytes(), strides=(1,))
        echo = np.zeros(len(view), bool)
        for lag in ECHO:
            echo[lag:] |= view[lag:] == view[:-lag]
        within = np.arange(len(raw)) - np.repeat(borders[:-1], sizes)
        echo &= within[3:] >= 3 + ECHO[0]
        out[at[3:][echo]] += 256
    return out, np.concatenate([[0], np.cumsum(chunks)])


@dataclass
class Network:
    """Byte vectors, filters, their thresholds, and the weights of the pooled responses."""

    byte: np.ndarray
    kernel: np.ndarray
    threshold: np.ndarray
    weight: np.ndarray
    bias: float

    def tables(self) -> np.ndarray:
        """What each symbol adds to each filter at each place of a chunk."""
        both = np.zeros((512, DIM + 1), np.float32)
        both[:256, :DIM] = both[256:, :DIM] = self.byte
        both[256:, DIM] = 1
        return np.einsum("sd,wdf->wsf", both, self.kernel).astype(np.float32)

    def responses(self, found: np.ndarray, borders: np.ndarray, tables: np.ndarray) -> np.ndarray:
        """Filter responses of each chunk, before pooling."""
        chunks = int(borders[-1])
        first = np.arange(chunks) * STRIDE + np.repeat(np.arange(len(borders) - 1) * (CHUNK - STRIDE), np.diff(borders))
        total = np.empty((chunks, FILTERS), np.float32)
        for a in range(0, chunks, 1 << 14):
            own = first[a : a + (1 << 14)]
            part = tables[0][found[own]]
            for w in range(1, CHUNK):
                part += tables[w][found[own + w]]
            total[a : a + (1 << 14)] = part
        return total

    def scores(self, raw: np.ndarray, borders: np.ndarray, tables: np.ndarray) -> np.ndarray:
        found, edges = symbols(raw, borders)
        if len(edges) < 2:
            return np.zeros(0)
        top = np.maximum.reduceat(self.responses(found, edges, tables), edges[:-1], axis=0)
        z = np.tanh(np.maximum(top + self.threshold, 0)) @ self.weight + self.bias
        return 1 / (1 + np.exp(-np.clip(z.astype(float), -30, 30)))


def train(docs: list[bytes], labels: np.ndarray, epochs: int = 12, steps: int = 500, batch: int = 64, rate: float = 0.01, seed: int = 11) -> Network:
    """Logistic loss by Adam; gradients pass through the chunk that gave each filter its largest response.
    A small sample is gone through more often, until `steps` batches are done."""
    rng = np.random.default_rng(seed)
    net = Network(rng.normal(0, 0.5, (256, DIM)), rng.normal(0, 0.25, (CHUNK, DIM + 1, FILTERS)), np.zeros(FILTERS), rng.normal(0, 0.5, FILTERS), 0.0)
    if not len(docs) or labels.min() == labels.max():
        net.weight[:] = 0
        net.bias = 30.0 if not len(docs) or labels.max() else -30.0
        return net
    prior = labels.mean()
    net.bias = float(np.log(prior / (1 - prior)))
    names = ("byte", "kernel", "threshold", "weight", "bias")
    first = {n: np.zeros_like(np.asarray(getattr(net, n), float)) for n in names}
    second = {n: np.zeros_like(first[n]) for n in names}
    step = 0
    epochs = max(epochs, -(-steps * batch // len(docs)))
    pull = np.where(labels > 0, 0.5 / prior, 0.5 / (1 - prior)) ** 0.5
    for epoch in range(epochs):
        order = rng.permutation(len(docs))
        pace = rate * (1 - 0.8 * epoch / epochs)
        for at in range(0, len(order), batch):
            own = order[at : at + batch]
            borders = np.concatenate([[0], np.cumsum([len(docs[i]) for i in own])])
            found, edges = symbols(np.frombuffer(b"".join(docs[i] for i in own), np.uint8), borders)
            response = net.responses(found, edges, net.tables())
            best = np.stack([a + response[a:b].argmax(0) for a, b in zip(edges, edges[1:], strict=False)])
            top = np.take_along_axis(response, best, 0) + net.threshold
            act = np.tanh(np.maximum(top, 0))
            p = 1 / (1 + np.exp(-np.clip(act @ net.weight + net.bias, -30, 30)))
            gap = (p - labels[own]) * pull[own] / len(own)
            back = gap[:, None] * net.weight * (1 - act**2) * (top > 0)
            start = best * STRIDE + np.arange(len(own))[:, None] * (CHUNK - STRIDE)
            seen = found[start[:, :, None] + np.arange(CHUNK)]
            value, echo = seen & 255, seen >> 8
            inputs = np.concatenate([net.byte[value], echo[..., None]], 3)
            grads = {
                "kernel": np.einsum("bf,bfwd->wdf", back, inputs),
                "threshold": back.sum(0),
                "weight": act.T @ gap + 1e-4 * net.weight,
                "bias": np.asarray(gap.sum()),
            }
            into = np.einsum("bf,wdf->bfwd", back, net.kernel[:, :DIM])
            grads["byte"] = np.zeros((256, DIM))
            np.add.at(grads["byte"], value.ravel(), into.reshape(-1, DIM))
            step += 1
            for n in names:
                first[n] = 0.9 * first[n] + 0.1 * grads[n]
                second[n] = 0.999 * second[n] + 0.001 * grads[n] ** 2
                move = pace * (first[n] / (1 - 0.9**step)) / (np.sqrt(second[n] / (1 - 0.999**step)) + 1e-8)
                setattr(net, n, getattr(net, n) - move)
    net.bias = float(net.bias)
    return net


def fit(docs: DataFrame, labels: DataFrame, parts: int = 3, held: int = 1, most: int = SAMPLE) -> Network:
    found = labelled(docs, labels, "quality", parts, held, most, SAMPLE_BYTES).toArrow()
    rows = sorted(zip(found.column("doc_id").to_pylist(), ((x or "").encode() for x in found.column("text").to_pylist()), found.column("label").to_pylist(), strict=True))
    return train([r[1] for r in rows], np.array([float(r[2] > 0) for r in rows]))


def scorer(docs: DataFrame, network: Network):
    """For use in tasks: a function from a batch's texts to scores, with the network sent once."""
    shared = docs.sparkSession.sparkContext.broadcast(network)

    def run(column: pa.Array, tables: np.ndarray | None = None):
        raw, borders = as_bytes(column)
        return shared.value.scores(raw, borders, shared.value.tables() if tables is None else tables)

    return run, shared


def score(docs: DataFrame, network: Network, parts: int = 3, held: int = 1) -> DataFrame:
    """(doc_id, held_out, score, predicted) of every document."""
    apply, shared = scorer(docs, network)

    def run(batches):
        tables = shared.value.tables()
        for part in slices(batches, "text", 1 << 20):
            found = apply(part.column(1), tables)
            kept = [zlib.crc32(b"" if k is None else str(k).encode()) % parts == held for k in part.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(kept), pa.array(found), pa.array((found >= 0.5).astype(np.int32))], ["doc_id", "held_out", "score", "predicted"])

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, held_out boolean, score double, predicted int")


def quality(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """Learn from the labelled rows outside the held-out fold and score every document."""
    return score(docs, fit(docs, labels))


def accepted(docs: DataFrame, network: Network, least: float = 0.5) -> DataFrame:
    """The documents, with all their columns, whose score reaches `least`."""
    apply, shared = scorer(docs, network)
    names, at = docs.columns, docs.columns.index("text")
    own = docs.toDF(*(f"c{i}" for i in range(len(names))))

    def run(batches):
        tables = shared.value.tables()
        for part in slices(batches, f"c{at}", 1 << 20):
            yield part.filter(pa.array(apply(part.column(at), tables) >= least))

    return own.mapInArrow(run, own.schema).toDF(*names)
