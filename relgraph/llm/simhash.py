"""SimHash near-duplicates with bit-sliced comparison.

Fingerprints that differ in at most `radius` bits are linked. Of radius + 4 blocks of bits, two such
fingerprints share four, so each choice of four blocks deals the distinct fingerprints to buckets, and
within buckets distances come from bit planes: 64 fingerprints stand side by side in a word for each bit,
one exclusive-or gives 64 difference bits, and carry-save counters add them up. A comparison is given up
as soon as every lane of a word is beyond the radius. A bucket has fixed four blocks of bits, so the
distinct fingerprints in it are bounded by the remaining bits, not by the corpus; copies were merged before.

`distinct` keeps one row of each group of texts whose sets of word shingles have a Jaccard similarity of at least 0.8.
Fingerprints of such texts differ in about 10 of 64 bits, too many for blocks of equal bits, so texts are dealt to buckets
by BANDS keys, each made of ROWS least values of the set under random orders: a pair of similarity s is missed by
all keys with a chance of (1 - s^ROWS)^BANDS, 3e-6 at 0.8 and less above. In a bucket one member is compared with
all, then another where the bucket still falls into parts. Where it still does, bit slices compare all members and
each is tested against the nearest of another part, so that groups grow together; what that leaves apart is tested pair by pair.
What lies within REACH bits (five standard deviations beyond the mean distance at 0.8) and has signs that allow it is
compared exactly, set with set, and only that links. A sign has SIGN bits, each the parity of the shingles that fall on it; two signs
differ in no more bits than their sets differ in shingles, so those that differ in too many need no comparison and
no pair that is similar enough is lost by it. So large groups of copies cost no square of pairs, though members that share much without being similar do,
and no candidate stays apart untested.

Null or empty texts have fingerprint zero and are linked like any other. Very long texts are hashed whole, one at a time. A
row without doc_id links nothing in `near_duplicates` and gets the component of its fingerprint, null if no other row
has that; rows that repeat a doc_id are returned once each; other columns are left out. In `distinct` rows are judged
by their text alone: the row with the least doc_id stays (null after all others), then the one of least row hash, so null
and repeated ids lose nothing but duplicates; all columns are kept, whatever their names. Empty tables: no rows.
"""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relgraph.llm.common import LOWER, components, discard, joined_names, local_roots, slices, staged, texts, width

BITS, KEPT = 64, 4
BANDS, ROWS, REACH = 32, 5, 24
#: The step from which on all pairs of parts are tested; a mark for no partner.
MEET, NONE = 4, (1 << 63) - 1
#: Bits of a sign, 64 to a column.
SIGN = 512
#: Least similarity of linked texts, as a fraction; words that a worker remembers the hash of.
LEAST, REMEMBERED = (4, 5), 1 << 20
_RNG = np.random.default_rng(11)
_FACTOR = _RNG.integers(0, 1 << 63, BANDS * ROWS, dtype=np.uint64) << np.uint64(1) | np.uint64(1)
_ADDEND = _RNG.integers(0, 1 << 63, BANDS * ROWS, dtype=np.uint64)
ALL = np.uint64(0xFFFFFFFFFFFFFFFF)
ONE = np.uint64(1)


def fingerprint(raw: bytes, shingle: int = 3, seed: int = 42) -> int:
    """Majority of the bits of XXH64 over word shingles (repeats count), A to Z lower-cased; no word: 0."""
    from xxhash import xxh64_intdigest as digest

    words = raw.translate(LOWER).split()
    if not words:
        return 0
    line = b" ".join(words)
    n = len(words)
    if n <= shingle:
        return digest(line, seed)
    size = np.fromiter(map(len, words), np.int64, n) + 1
    start = np.cumsum(size) - size
    end = (start + size - 1)[shingle - 1 :]
    return majority(np.array([digest(line[a:b], seed) for a, b in zip(start.tolist(), end.tolist(), strict=False)], np.uint64))


def majority(hashes: np.ndarray) -> int:
    """The bits that are set in over half of the hashes."""
    ones = np.unpackbits(hashes.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(0, dtype=np.int64)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view(np.uint64)[0])


def fingerprints(df: DataFrame, key: str = "doc_id", text: str = "text", shingle: int = 3, seed: int = 42) -> DataFrame:
    """(doc_id, fp): the fingerprint of each whole text, as a signed long."""

    def run(batches):
        for batch in slices(batches, "text"):
            found = np.array([fingerprint(raw, shingle, seed) for raw in texts(batch.column(1))], np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found.view(np.int64))], ["doc_id", "fp"])

    return df.select(F.col(key).cast("long").alias("doc_id"), F.col(text).alias("text")).mapInArrow(run, "doc_id long, fp long")


def masks(radius: int) -> list[int]:
    """Masks of every choice of four among radius + 4 blocks of the 64 bits."""
    n = radius + KEPT
    borders = [BITS * i // n for i in range(n + 1)]
    blocks = [((1 << b) - (1 << a)) for a, b in zip(borders, borders[1:], strict=False)]
    return [sum(c) for c in combinations(blocks, KEPT)]


def planes(values: np.ndarray) -> np.ndarray:
    """64 bit planes of the values, 64 values a word: bit j of planes[p, w] is bit p of value 64 w + j."""
    words = -(-len(values) // 64)
    bits = np.zeros((words * 64, BITS), np.uint8)
    bits[: len(values)] = np.unpackbits(values.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
    return np.ascontiguousarray(np.packbits(bits.T, axis=1, bitorder="little")).view(np.uint64)


def beyond(counter: list[np.ndarray], radius: int) -> np.ndarray:
    """Lanes whose count, given by its bits from the lowest, is above the radius."""
    above, same = np.zeros_like(counter[0]), np.full_like(counter[0], ALL)
    for k in reversed(range(len(counter))):
        if radius >> k & 1:
            same &= counter[k]
        else:
            above |= same & counter[k]
            same &= ~counter[k]
    return above


def close_pairs(values: np.ndarray, last: np.ndarray, radius: int, step: int = 8, chunk: int = 1 << 16):
    """Index pairs i < j <= last[i] of values that differ in at most `radius` bits, chunk by chunk."""
    grid = planes(values)
    first = np.arange(len(values))
    words = np.where(last > first, last // 64 - (first + 1) // 64 + 1, 0)
    ends = np.cumsum(words)
    depth = (radius + 1).bit_length()
    total, done = int(ends[-1]) if len(ends) else 0, 0
    while done < total:
        task = np.arange(done, min(done + chunk, total))
        done += len(task)
        row = np.searchsorted(ends, task, side="right")
        word = (row + 1) // 64 + task - (ends[row] - words[row])
        low, high = np.maximum(row + 1 - 64 * word, 0), np.minimum(last[row] - 64 * word, 63)
        out = ~((ALL >> (63 - high).astype(np.uint64)) & (ALL << low.astype(np.uint64)))
        counter = [np.zeros(len(task), np.uint64) for _ in range(depth)]
        for p in range(BITS):
            carry = grid[p, word] ^ (np.uint64(0) - (values[row] >> np.uint64(p) & ONE))
            for c in counter:
                c ^= carry
                carry = carry & ~c
            out |= carry
            if p % step == step - 1:
                out |= beyond(counter, radius)
                alive = out != ALL
                if not alive.all():
                    row, word, out = row[alive], word[alive], out[alive]
                    counter = [c[alive] for c in counter]
                    if not len(row):
                        break
        if len(row):
            lanes = np.unpackbits((~out).view(np.uint8).reshape(-1, 8), axis=1, bitorder="little")
            at, lane = np.nonzero(lanes)
            yield row[at], 64 * word[at] + lane


def whole_buckets(batches, keys: int, least: int = 1 << 16):
    """Columns of sorted rows as arrays, cut so that rows with the same first `keys` columns stay together."""
    held: list[list[np.ndarray]] = []
    for batch in batches:
        if not batch.num_rows:
            continue
        held.append([c.to_numpy(zero_copy_only=False) for c in batch.columns])
        if sum(len(x[0]) for x in held) < least:
            continue
        whole = [np.concatenate(x) for x in zip(*held, strict=True)]
        end = len(whole[0])
        while end and all(c[end - 1] == c[-1] for c in whole[:keys]):
            end -= 1
        if end:
            yield [x[:end] for x in whole]
        held = [[x[end:] for x in whole]]
    if held:
        yield [np.concatenate(x) for x in zip(*held, strict=True)]


def last_of_bucket(keys: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Rows in buckets of several, and for each the index of its bucket's last row among these."""
    differ = np.logical_or.reduce([k[1:] != k[:-1] for k in keys])
    edge = np.flatnonzero(differ) + 1
    sizes = np.diff(np.concatenate([[0], edge, [len(keys[0])]]))
    return np.repeat(sizes > 1, sizes), np.repeat(np.cumsum(sizes[sizes > 1]) - 1, sizes[sizes > 1])


def bucket_links(batches, radius: int):
    """Star links (a, b: representatives) of the buckets in sorted rows (choice, bucket, fp, rep)."""
    for choice, bucket, fp, rep in whole_buckets(batches, 2):
        keep, last = last_of_bucket([choice, bucket])
        fp, rep = fp[keep].view(np.uint64), rep[keep]
        found = list(close_pairs(fp, last, radius)) if len(fp) else []
        if not found:
            continue
        left, right = (np.concatenate(x) for x in zip(*found, strict=True))
        root = local_roots(len(fp), left, right)
        own = np.flatnonzero(root != np.arange(len(fp)))
        yield pa.RecordBatch.from_arrays([pa.array(rep[own]), pa.array(rep[root[own]])], ["a", "b"])


def linked(found: DataFrame, radius: int = 2) -> DataFrame:
    """(doc_id, fp) -> (doc_id, fp, component_id): smallest doc_id reachable over links of at most `radius` bits.

    The frame is read twice, so it should be a written table.
    """
    spark = found.sparkSession
    classes = staged(found.where("doc_id is not null").groupBy("fp").agg(F.min("doc_id").alias("rep")), "classes")
    choices = F.explode(F.array(*[F.struct(F.lit(i).alias("choice"), (F.lit(m - (m >> 63 << 64))).cast("long").alias("mask")) for i, m in enumerate(masks(radius))])).alias("c")
    dealt = classes.select(choices, "fp", "rep").select("c.choice", F.col("fp").bitwiseAND(F.col("c.mask")).alias("bucket"), "fp", "rep")
    dealt = dealt.repartition(width(spark), "choice", "bucket").sortWithinPartitions("choice", "bucket")
    links = dealt.mapInArrow(lambda batches: bucket_links(batches, radius), "a long, b long")
    joined = components(links)
    named = classes.join(joined, classes.rep == joined.node, "left").select("fp", F.coalesce("component", "rep").alias("component_id"))
    return found.join(named, "fp", "left").select("doc_id", "fp", "component_id")


def near_duplicates(df: DataFrame, key: str = "doc_id", text: str = "text", shingle: int = 3, radius: int = 2, seed: int = 42) -> DataFrame:
    """(doc_id, fingerprint in 16 hex digits, component_id) of every document."""
    found = linked(staged(fingerprints(df, key, text, shingle, seed), "fingerprints"), radius)
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


class WordHashes(dict):
    """XXH64 of words, worked out once; forgotten when there are too many."""

    def __missing__(self, word: bytes) -> int:
        from xxhash import xxh64_intdigest

        if len(self) >= REMEMBERED:
            self.clear()
        found = self[word] = xxh64_intdigest(word, 42)
        return found


def shingles(raw: bytes, known: WordHashes, shingle: int = 5) -> np.ndarray:
    """Sorted distinct hashes of the word shingles, put together from hashes of words; fewer words are one shingle."""
    words = raw.translate(LOWER).split()
    if not words:
        return np.zeros(0, np.uint64)
    h = np.fromiter(map(known.__getitem__, words), np.uint64, len(words))
    size = min(shingle, len(h))
    out = np.full(len(h) - size + 1, size, np.uint64)
    for k in range(size):
        out = joined_names(out, h[k : len(h) - size + 1 + k])
    return np.unique(out)


def band_keys(own: np.ndarray, most: int = 1 << 16) -> np.ndarray:
    """One key for each band of least values; none for an empty set."""
    if not len(own):
        return np.zeros(0, np.uint64)
    least = np.full(BANDS * ROWS, ALL)
    for at in range(0, len(own), most // 16):
        part = own[at : at + most // 16]
        step = max(1, most // len(part))
        for k in range(0, len(least), step):
            values = _FACTOR[k : k + step, None] * part + _ADDEND[k : k + step, None]
            np.minimum(least[k : k + step], values.min(1), out=least[k : k + step])
    out = np.arange(BANDS, dtype=np.uint64)
    for column in least.reshape(BANDS, ROWS).T:
        out = joined_names(out, column)
    return out


def signed(own: np.ndarray) -> np.ndarray:
    """The sign of a set of hashes: for each value of a hash's highest bits, whether an odd number of hashes has it."""
    odd = np.bincount((own >> np.uint64(65 - SIGN.bit_length())).astype(np.int64), minlength=SIGN) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view(np.uint64)


def allowed(differ, total):
    """Whether sets of `total` hashes together that differ in at least `differ` can be similar enough; for arrays and columns."""
    return differ * (LEAST[1] + LEAST[0]) <= total * (LEAST[1] - LEAST[0])


def similar(a: np.ndarray, b: np.ndarray) -> bool:
    shared = len(np.intersect1d(a, b, assume_unique=True))
    return shared * LEAST[1] >= LEAST[0] * (len(a) + len(b) - shared)


def sketches(rows: DataFrame, shingle: int) -> DataFrame:
    """(id, row, doc_id, text) -> (id, row, doc_id, name, n, fp, bands, sign): hash and size of the set, fingerprint, keys of the bands, sign."""

    def run(batches):
        known = WordHashes()
        for batch in slices(batches, "text"):
            sets = [shingles(raw, known, shingle) for raw in texts(batch.column(3))]
            found = [band_keys(x) for x in sets]
            ends = np.cumsum([0, *map(len, found)]).astype(np.int32)
            bands = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(found).view(np.int64)))
            names = [_named(x) for x in sets]
            prints = [majority(x) if len(x) else 0 for x in sets]
            names, prints = (pa.array(np.array(x, np.uint64).view(np.int64)) for x in (names, prints))
            signs = pa.ListArray.from_arrays(np.arange(len(sets) + 1, dtype=np.int32) * (SIGN // 64), np.concatenate([signed(x) for x in sets]).view(np.int64))
            sizes = pa.array([len(x) for x in sets], pa.int32())
            yield pa.RecordBatch.from_arrays([*batch.columns[:3], names, sizes, prints, bands, signs], ["id", "row", "doc_id", "name", "n", "fp", "bands", "sign"])

    return rows.mapInArrow(run, "id long, row long, doc_id long, name long, n int, fp long, bands array<long>, sign array<long>")


def _named(own: np.ndarray) -> int:
    from xxhash import xxh64_intdigest

    return xxh64_intdigest(own.tobytes()) if len(own) else 0


def fetched(rows: DataFrame, shingle: int) -> DataFrame:
    """(name, text) -> (name, held): the set itself."""

    def run(batches):
        known = WordHashes()
        for batch in slices(batches, "text"):
            held = [shingles(raw, known, shingle).tobytes() for raw in texts(batch.column(1))]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(held, pa.binary())], ["name", "held"])

    return rows.mapInArrow(run, "name long, held binary")


def tested(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """The pairs (a, b) whose sets are similar enough."""

    def run(batches):
        for batch in slices(batches, "x"):
            x, y = ([np.frombuffer(v, np.uint64) for v in batch.column(k).to_pylist()] for k in (2, 3))
            yield batch.select(["a", "b"]).filter(pa.array([similar(p, q) for p, q in zip(x, y, strict=True)], pa.bool_()))

    left, right = sets.toDF("a", "x"), sets.toDF("b", "y")
    return pairs.join(left, "a").join(right, "b").select("a", "b", "x", "y").mapInArrow(run, "a long, b long")


SIZES = f"least(n, mn) * {LEAST[1]} >= greatest(n, mn) * {LEAST[0]}"
MEMBER = ("name", "n", "part", "fp", "sign")


def candidates(members: DataFrame, joined: DataFrame | None, step: int) -> DataFrame:
    """Pairs (a < b) within REACH, and with signs that allow it, of two parts of a bucket (key, name, n, fp, sign): of one
    member with the others (steps 0 and 1), of each member with its nearest (until MEET), or all."""
    if joined is None:
        members = members.withColumn("part", F.col("name"))
    else:
        members = members.join(joined.toDF("name", "part"), "name", "left").withColumn("part", F.coalesce("part", "name"))
    if step < 2:
        order = F.xxhash64("name", "key") if step else F.col("name")
        other = members.groupBy("key").agg(F.min(F.struct(order.alias("o"), *MEMBER)).alias("h"))
        other = other.select("key", *(F.col(f"h.{c}").alias(f"m{c}") for c in MEMBER))
        met = members.join(other, "key").where("part <> mpart").where(F.bit_count(F.col("fp").bitwiseXOR(F.col("mfp"))) <= REACH).where(SIZES)
        differ = sum((F.bit_count(F.col("sign")[k].bitwiseXOR(F.col("msign")[k])) for k in range(SIGN // 64)), F.lit(0))
        met = met.where(allowed(differ, F.col("n") + F.col("mn")))
        return met.select(F.least("name", "mname").alias("a"), F.greatest("name", "mname").alias("b")).distinct()
    parts = members.groupBy("key").agg(F.min("part").alias("low"), F.max("part").alias("high")).where("low <> high").select("key")
    signs = [F.col("sign")[k].alias(f"s{k}") for k in range(SIGN // 64)]
    dealt = members.join(parts, "key").select("key", "fp", "name", "part", F.col("n").cast("long").alias("n"), *signs)
    dealt = dealt.repartition(width(members.sparkSession), "key").sortWithinPartitions("key")

    def run(batches):
        for key, fp, name, part, n, *sign in whole_buckets(batches, 1):
            keep, last = last_of_bucket([key])
            sign = [x[keep].view(np.uint64) for x in sign]  # bits of negative numbers are not counted
            fp, name, part, n = fp[keep].view(np.uint64), name[keep], part[keep], n[keep]
            best = np.full(len(fp), NONE)
            for i, j in close_pairs(fp, last, REACH) if len(fp) else ():
                near = (part[i] != part[j]) & (np.minimum(n[i], n[j]) * LEAST[1] >= np.maximum(n[i], n[j]) * LEAST[0])
                i, j = i[near], j[near]
                near = allowed(sum(np.bitwise_count(x[i] ^ x[j]).astype(np.int64) for x in sign), n[i] + n[j])
                i, j = i[near], j[near]
                if step >= MEET:
                    yield linked_names(name[i], name[j])
                    continue
                far = np.bitwise_count(fp[i] ^ fp[j]).astype(np.int64) << 40
                np.minimum.at(best, i, far | j)
                np.minimum.at(best, j, far | i)
            met = np.flatnonzero(best != NONE)
            yield linked_names(name[met], name[best[met] & (1 << 40) - 1])

    return dealt.mapInArrow(run, "a long, b long").distinct()


def linked_names(a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b))], ["a", "b"])


def similar_groups(classes: DataFrame, rows: DataFrame, shingle: int) -> DataFrame | None:
    """(node, component) of the classes (name, n, fp, bands, sign, first) that are linked; rows: (id, row, doc_id, text)."""
    dealt = classes.select("name", F.explode("bands").alias("key"))
    marks = [F.bit_xor(F.xxhash64("name", F.lit(i))).alias(f"x{i}") for i in range(2)]
    buckets = dealt.groupBy("key").agg(F.count("*").alias("c"), *marks).where("c > 1")
    buckets = buckets.groupBy("c", "x0", "x1").agg(F.min("key").alias("key"))  # buckets with the same members count once
    members = staged(dealt.join(buckets.select("key"), "key").join(classes.select("name", "n", "fp", "sign"), "name"), "members")
    wanted = members.select("name").distinct().join(classes, "name").select("name", F.coalesce("first.doc_id", F.lit(0).cast("long")).alias("id"), "first.row")
    sets = staged(fetched(rows.join(wanted, ["id", "row"]).select("name", "text"), shingle).dropDuplicates(["name"]), "shingles")
    joined, links, done = None, None, None
    for step in range(MEET + 1):
        met = staged(candidates(members, joined, step), "met")
        if met.isEmpty():
            if step < 2:
                continue
            break  # no two parts have members within reach
        pairs = staged(met.join(done, ["a", "b"], "left_anti"), "pairs") if done else met
        if pairs.isEmpty():
            continue
        found = staged(tested(pairs, sets), "similar")
        done, links = (done.union(pairs), links.union(found)) if done else (pairs, found)
        joined = components(links)
    discard(members, sets)
    return joined


def distinct(docs: DataFrame, shingle: int = 5, text: str = "text", key: str = "doc_id") -> DataFrame:
    """One row of each group of near-duplicates, with all its columns."""
    columns = [F.col(f"`{c}`") for c in docs.columns]
    row = F.xxhash64(*columns, *(c.isNull() for c in columns))  # nulls leave no mark by themselves
    doc_id = F.col(f"`{key}`").cast("long")
    ident = [F.coalesce(doc_id, F.lit(0).cast("long")).alias("id"), row.alias("row")]
    rows = docs.select(*ident, doc_id.alias("doc_id"), F.col(f"`{text}`").alias("text"))
    sets = staged(sketches(rows, shingle), "sets")
    first = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "row"))
    classes = sets.groupBy("name").agg(first.alias("first"), *(F.first(c).alias(c) for c in ("n", "fp", "bands", "sign")))
    classes = staged(classes, "classes")
    discard(sets)
    joined = similar_groups(classes, rows, shingle)
    groups = classes.select(F.col("name").alias("component"), "first")
    if joined:
        groups = classes.join(joined, classes.name == joined.node, "left").select(F.coalesce("component", "name").alias("component"), "first")
    kept = groups.groupBy("component").agg(F.min("first").alias("first"))
    kept = kept.select(F.coalesce("first.doc_id", F.lit(0).cast("long")).alias("id"), F.col("first.row").alias("row"))
    found = docs.select(*ident, F.struct(*columns).alias("doc")).join(kept, ["id", "row"], "left_semi")
    return found.dropDuplicates(["id", "row"]).select("doc.*")  # what is left twice is the same row
