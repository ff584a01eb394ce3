"""Best-fit packing of token pieces into sequences of fixed capacity.

Pieces above a third of the capacity meet at most in pairs, so these are matched greedily, the largest
with the largest that still fits; smaller pieces go, longest first, into the tightest gap. All of that
happens on the histogram of lengths, which has at most `capacity` entries whatever the corpus holds:
equal pieces are interchangeable, so the driver plans sequences by kind and count, and each piece then
finds its place from its rank among the pieces of its length.

Null or empty texts are one piece of length 1 (the end id). Very long texts are tokenized whole, one at a time, and cut into
pieces. Ties are ranked by doc_id, then piece, then checksum; rows that repeat a doc_id, or have none, are ranked too.
Other columns are left out, so names cannot clash. Empty tables: no rows.
"""

from __future__ import annotations

import bisect
import os
import zlib
from array import array
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from relgraph.llm.common import LOWER, slices, staged, texts

CAPACITY = 2048
END_ID = 0
#: Chunks between blanks whose ids a worker remembers.
REMEMBERED = 350_000
#: Words encoded in one call, and slots that tell which chunks were met before.
AT_ONCE, SLOTS = 4_000, 1 << 21
PIECES = "doc_id long, piece int, start long, length long, ids_crc32 long"


class ChunkTokenizer:
    """Ids of whole texts, by the public tokenizer, remembered for each chunk between ASCII blanks.

    The vocabulary's rules never join characters across a blank, drop the blanks and ignore case, so a
    text's ids are its chunks' ids in a row, and a comma or full stop after a letter is a token of its own.
    A text that may hold a special token goes through the tokenizer whole. Chunks are kept once they were met
    a second time, in two generations; when the younger is full, it takes the older one's place.
    """

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.inner = Tokenizer.from_file(path)
        self.young: dict[bytes, bytes] = {}
        self.old: dict[bytes, bytes] = {}
        self.met = bytearray(SLOTS)
        vocabulary = self.inner.get_vocab()
        self.ends = np.zeros(max(vocabulary.values()) + 1, bool)
        self.ends[[i for t, i in vocabulary.items() if t.endswith("</w>")]] = True
        self.marks = {m: self._encode([bytes([m])])[0] for m in b".,"}

    def _encode(self, parts: list[bytes]) -> list[bytes]:
        out = []
        for i in range(0, len(parts), AT_ONCE):
            found = self.inner.encode_batch_fast([x.decode("utf-8", "replace") for x in parts[i : i + AT_ONCE]], add_special_tokens=False)
            out += [array("I", x.ids).tobytes() for x in found]
        return out

    def _words(self, words: list[bytes]) -> list[bytes]:
        """Ids of words of Latin letters, each a single token run that ends in a token marked as a word's end."""
        if len(words) > AT_ONCE:
            return [x for i in range(0, len(words), AT_ONCE) for x in self._words(words[i : i + AT_ONCE])]
        ids = np.array(self.inner.encode_batch_fast([b" ".join(words).decode()], add_special_tokens=False)[0].ids, "<u4")
        cut = np.flatnonzero(self.ends[ids]) + 1
        if len(cut) != len(words):  # never seen; the slower way is always right
            return self._encode(words)
        raw, borders = ids.tobytes(), [0, *(4 * cut).tolist()]
        return [raw[x:y] for x, y in zip(borders, borders[1:], strict=False)]

    def _learn(self, chunks: set[bytes]) -> None:
        """Put what is not in the younger generation there."""
        young, old = self.young, self.old
        absent = []
        for c in chunks:
            ids = old.get(c)
            if ids is not None:
                young[c] = ids
            else:
                absent.append(c)
        stems = [c[:-1] if c[-1] in b".," and len(c) > 1 and 97 <= c[-2] <= 122 else c for c in absent]
        words, others = [], []
        for c in {c for c in stems if c not in young}:
            text = c.decode("utf-8", "replace")
            (words if text.isalpha() and max(text) < "\u0100" else others).append(c)
        young.update(zip(words, self._words(words), strict=True))
        young.update(zip(others, self._encode(others), strict=True))
        for c, stem in zip(absent, stems, strict=True):
            if stem is not c:
                young[c] = young[stem] + self.marks[c[-1]]

    def ids(self, raws: list[bytes]) -> list[bytes]:
        """32-bit ids of each text, least significant byte first, without an end id."""
        if len(self.young) > REMEMBERED:
            self.old, self.young = self.young, {}
        parts = [None if b"<|" in raw else raw.translate(LOWER).split() for raw in raws]
        unknown: set[bytes] = set()
        for chunks in parts:
            unknown.update(chunks or ())
        young = self.young
        unknown = {c for c in unknown if c not in young}
        self._learn(unknown)
        out = [self._encode([raw])[0] if chunks is None else b"".join([young[c] for c in chunks]) for raw, chunks in zip(raws, parts, strict=True)]
        met = self.met
        for c in unknown:
            slot = hash(c) % SLOTS
            if not met[slot]:
                met[slot] = 1
                del young[c]
        return out


@cache
def tokenizer(path: str) -> ChunkTokenizer:
    return ChunkTokenizer(path)


def pieces(df: DataFrame, vocabulary: str, capacity: int = CAPACITY, key: str = "doc_id", text: str = "text", with_ids: bool = False) -> DataFrame:
    """Token pieces of every whole text: ids and an end id, cut at the capacity only where longer.

    with_ids adds the ids themselves as a binary column of little-endian 32-bit numbers.
    """
    schema = PIECES + (", ids binary" if with_ids else "")
    end = np.array([END_ID], "<u4").tobytes()

    def run(batches):
        model = tokenizer(vocabulary)
        for batch in slices(batches, "text", 1 << 20):
            keys, at, start, length, crc, kept = [], [], [], [], [], []
            for k, ids in zip(batch.column(0).to_pylist(), model.ids(texts(batch.column(1))), strict=True):
                ids += end
                for i in range(0, len(ids), 4 * capacity):
                    part = ids[i : i + 4 * capacity]
                    keys.append(k)
                    at.append(i // (4 * capacity))
                    start.append(i // 4)
                    length.append(len(part) // 4)
                    crc.append(zlib.crc32(part))
                    if with_ids:
                        kept.append(part)
            columns = [pa.array(keys, pa.int64()), pa.array(at, pa.int32()), *(pa.array(c, pa.int64()) for c in (start, length, crc))]
            names = ["doc_id", "piece", "start", "length", "ids_crc32"]
            if with_ids:
                columns, names = [*columns, pa.array(kept, pa.binary())], [*names, "ids"]
            yield pa.RecordBatch.from_arrays(columns, names)

    return df.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, schema)


def plan(counts: dict[int, int], capacity: int = CAPACITY) -> list[tuple[tuple[int, ...], int]]:
    """Kinds of sequence, as (lengths in it, how many such sequences), that hold all counted pieces.

    Every step uses up a length or a kind of gap, so the number of kinds stays within a few times the
    number of distinct lengths.
    """
    left = {n: c for n, c in counts.items() if c > 0}
    if any(not 0 < n <= capacity for n in left):
        raise ValueError("a piece is empty or longer than a sequence")
    large = sorted(n for n in left if 3 * n > capacity)
    open_: dict[int, list[tuple[tuple[int, ...], int]]] = {}

    def add(kind: tuple[int, ...], count: int) -> None:
        open_.setdefault(capacity - sum(kind), []).append((kind, count))

    while large:
        a = large[-1]
        if not left[a]:
            large.pop()
            continue
        fits = bisect.bisect_right(large, capacity - a) - 1
        while fits >= 0 and not left[large[fits]]:
            large.pop(fits)
            fits -= 1
        if fits < 0:
            add((a,), left[a])
            left[a] = 0
            continue
        b = large[fits]
        if a == b:
            pairs, odd = divmod(left[a], 2)
            if pairs:
                add((a, a), pairs)
            left[a] = odd
            if odd:
                smaller = [n for n in large[:fits] if left[n]]
                if smaller:
                    add((a, smaller[-1]), 1)
                    left[smaller[-1]] -= 1
                else:
                    add((a,), 1)
                left[a] = 0
        else:
            count = min(left[a], left[b])
            add((a, b), count)
            left[a] -= count
            left[b] -= count
    for n in sorted((n for n in left if 3 * n <= capacity), reverse=True):
        count = left[n]
        gaps = sorted(g for g in open_ if g >= n)
        for g in gaps:
            while count and open_.get(g):
                kind, many = open_[g].pop()
                each = g // n
                full = min(many, count // each)
                if full:
                    add((*kind, *[n] * each), full)
                    count -= full * each
                    many -= full
                if many and count:
                    add((*kind, *[n] * count), 1)
                    many, count = many - 1, 0
                if many:
                    open_[g].append((kind, many))
            if not open_.get(g):
                open_.pop(g, None)
            if not count:
                break
        if count:
            each = capacity // n
            if count // each:
                add((n,) * each, count // each)
            if count % each:
                add((n,) * (count % each), 1)
    return [x for kinds in open_.values() for x in kinds]


def places(kinds: list[tuple[tuple[int, ...], int]]) -> list[tuple[int, int, int, int, int]]:
    """Where ranks go: (length, first rank, ranks, first sequence, offset), a row for each piece of a kind."""
    taken: dict[int, int] = {}
    rows, sequence = [], 0
    for kind, count in kinds:
        offset = 0
        for n in kind:
            rows.append((n, taken.get(n, 0), count, sequence, offset))
            taken[n] = taken.get(n, 0) + count
            offset += n
        sequence += count
    return rows


def ranked(df: DataFrame, group: str, order: list[str], salts: int) -> DataFrame:
    """Add `rank`, from 0, of each row among the rows of its group, without gathering a group in one task.

    Groups are dealt to salted shares by hash; a share's rows are numbered where they lie, from the sum of
    the shares before, of which there are at most `salts` a group.
    """
    df = df.withColumn("share", F.pmod(F.xxhash64(*order), F.lit(salts)))
    before = Window.partitionBy(group).orderBy("share").rowsBetween(Window.unboundedPreceding, -1)
    base = df.groupBy(group, "share").agg(F.count("*").alias("n"))
    base = base.select(group, "share", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    own = Window.partitionBy(group, "share").orderBy(*order)
    return (
        df.withColumn("own", F.row_number().over(own) - 1)
        .join(base, [group, "share"])
        .withColumn("rank", F.col("own") + F.col("base"))
        .drop("own", "base", "share")
    )


def pack(found: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """Give every row of `found` (doc_id, piece, length, ids_crc32, ...) a sequence_id and an offset in it, gapless from 0.

    The frame is read several times, so it should be a written table.
    """
    spark = found.sparkSession
    totals = found.groupBy("length").agg(F.count("*").alias("n")).collect()  # at most `capacity` rows
    counts = {r["length"]: r["n"] for r in totals}
    rows = places(plan(counts, capacity))
    rows = rows or [(1, 0, 0, 0, 0)]
    by: dict[int, list[tuple[int, ...]]] = {}
    for n, *rest in rows:
        by.setdefault(n, []).append(tuple(rest))
    spread = spark.sparkContext.broadcast({n: tuple(np.array(c) for c in zip(*x, strict=True)) for n, x in by.items()})
    salts = max(1, 1 + int(sum(counts.values()) // 20_000), int(spark.conf.get("spark.sql.shuffle.partitions")))
    schema = found.schema.names
    kinds = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in found.schema)

    def run(batches):
        table = spread.value
        for batch in batches:
            length, rank = (batch.column(batch.schema.get_field_index(c)).to_numpy() for c in ("length", "rank"))
            sequence, offset = np.zeros(len(length), np.int64), np.zeros(len(length), np.int64)
            for n in np.unique(length):
                first, _, seq, off = table[int(n)]
                own = np.flatnonzero(length == n)
                at = np.searchsorted(first, rank[own], side="right") - 1
                sequence[own] = seq[at] + rank[own] - first[at]
                offset[own] = off[at]
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(len(schema))), pa.array(sequence), pa.array(offset)], [*schema, "sequence_id", "offset"])

    numbered = ranked(found, "length", ["doc_id", "piece", "ids_crc32"], salts)
    return numbered.select(*schema, "rank").mapInArrow(run, f"{kinds}, sequence_id long, offset long")


def pack_documents(df: DataFrame, vocabulary: str, capacity: int = CAPACITY, key: str = "doc_id", text: str = "text", with_ids: bool = False) -> DataFrame:
    """Tokenize every whole text and pack the pieces; see `pieces` and `pack`."""
    return pack(staged(pieces(df, vocabulary, capacity, key, text, with_ids), "pieces"), capacity)
