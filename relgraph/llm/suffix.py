"""Exact repeats of `length` bytes, by a distributed difference cover.

The search runs over distinct texts; a text that stands in several rows is a repeat as a whole. Long texts are cut
into pieces that overlap by one byte less than `length`, so that each string of that length lies in one piece.

1. Screen. Hashes of sampled strings, at the residues of a wide cover, tell which parts of the pieces can hold
   repeats at all. Equal strings have equal hashes, so nothing is lost; what only collides goes in the next step.
   Only the parts that are left, the regions, go on.
2. Sorted triples. Within regions the positions on three residues mod 7 are sampled. The triple of three 7-byte words
   at each is sorted in buckets with its equals and named by its rank; a string that stands once has no name and
   ends here. The names are recursed on: triples of names of 21 bytes name 63 bytes, and triples of those, with the
   few bytes left over, name strings of length - 6 bytes.
3. Merge. For any two positions some shift below 7 brings both onto the cover, so two equal strings of the whole
   length have equal names at that shift and equal bytes around: d before the named string and 6 - d behind it.
   Suffixes of one name are sorted by these bytes and compared with their neighbours, for each shift.
4. Bytes under a repeated string are removed.

Ranks come from comparing whole triples and neighbours are compared byte by byte, so no two different strings are taken
for one. A fixed length needs classes and not a whole order, so triples are dealt to buckets by hash and a name is a
bucket and a rank in it. Units and buckets grow in number with the corpus, not in size. Each unit sends a string once.
A name that very many strings share, as of a passage cut off by different words, is dealt out again by its
surrounding bytes (CROWD). Texts are told apart by 128 bits of hashes when results go back to their rows.

Null or empty texts have no bytes. Very long texts are searched in pieces and put together in one task, as one row. Matches
never cross documents. Rows that repeat a doc_id, or whose doc_id is null, are documents of their own (equal texts repeat
each other). There are no ties to break. Other columns are left out, so names cannot clash. Empty tables: no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relgraph.llm.common import as_bytes, discard, joined_names, slices, staged, width

LENGTH, PERIOD, STEP = 200, 73, 7
UNIT_BYTES, BUCKET_BYTES, PIECE = 3 << 20, 16 << 20, 1 << 20
#: Strings of one name in a bucket from which on its suffixes are dealt by their surrounding bytes too.
CROWD = 1 << 16
RESULT = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"
_A = np.uint64(0x9E3779B97F4A7C15)
_MANY, _HOT = np.uint64(1 << 55), np.uint32(1 << 31)


def cover(period: int = PERIOD) -> np.ndarray:
    """Residues whose differences are all residues: powers of two, for periods such as 7 and 73."""
    found, x = [], 1
    while x not in found:
        found.append(x)
        x = 2 * x % period
    if len({(a - b) % period for a in found for b in found}) != period:
        raise ValueError(f"powers of two are no difference cover of {period}")
    return np.array(sorted(found))


class Hashes:
    """Hashes of strings at every position of some bytes, by doubling from 8 bytes up to `top`, block by block."""

    def __init__(self, raw: np.ndarray, top: int, block: int = 1 << 14):
        n = len(raw)
        view = np.ndarray((n + top,), "<u8", raw.tobytes() + bytes(top + 8), strides=(1,))
        self.small, self.big, self.top = view[:n], np.empty(n, np.uint64), top
        for a in range(0, n, block):
            x, size = view[a : min(a + block, n) + top - 8].copy(), 8
            while size < top:
                x = joined_names(x[:-size], x[size:])
                size *= 2
            self.big[a : a + block] = x

    def of(self, at: np.ndarray, length: int) -> np.ndarray:
        """Hashes of `length` bytes from each position, of the largest pieces and then of 8 bytes; pieces may overlap."""
        if length < self.top:
            raise ValueError("shorter than the level")
        out, done = self.big[at], self.top
        while done + self.top <= length:
            out = joined_names(out, self.big[at + done])
            done += self.top
        while done < length:
            step = min(done, length - 8)
            out = joined_names(out, self.small[at + step])
            done = step + 8
        return out


def ordered(rows: pa.Table, *keys: str) -> pa.Table:
    return rows.sort_by([(k, "ascending") for k in keys])


def on_cover(sizes: np.ndarray, period: int, reach: int) -> tuple[np.ndarray, np.ndarray]:
    """The positions within each part, of so many bytes, whose residues are on the cover and from which `reach` bytes are left; their parts."""
    spots = np.flatnonzero(np.isin(np.arange(int(sizes.max(initial=0))) % period, cover(period)))
    many = np.searchsorted(spots, sizes - reach, side="right")
    part = np.repeat(np.arange(len(sizes)), many)
    return spots[np.arange(len(part)) - (np.cumsum(many) - many)[part]], part


class Screen:
    """The pieces of a unit side by side, in an order that a second run repeats, and their sampled strings."""

    def __init__(self, rows: pa.Table, length: int, period: int):
        self.rows = ordered(rows, "h", "g", "k")
        self.raw, self.borders = as_bytes(self.rows.column("body").combine_chunks())
        self.length, self.period, self.reach, n = length, period, length - period + 1, len(self.raw)
        within, self.part = on_cover(np.diff(self.borders), period, self.reach)
        self.sampled = self.borders[self.part] + within
        top = 8
        while 2 * top <= min(64, self.reach):
            top *= 2
        self.hashes = Hashes(self.raw, top).of(self.sampled, self.reach) if n else np.zeros(0, np.uint64)

    def regions(self, tied: np.ndarray) -> list[tuple[int, int, int]]:
        """(piece, from, to) of the maximal runs of whole strings with a tied sample within the period."""
        at, part = self.sampled[tied], self.part[tied]
        base, end = self.borders[part], self.borders[part + 1]
        first, last = np.maximum(at - self.period + 1, base), np.minimum(at, end - self.length) + self.length
        fresh = np.ones(len(at), bool)
        fresh[1:] = (part[1:] != part[:-1]) | (first[1:] > last[:-1])
        of = np.flatnonzero(fresh)
        until = np.append(of[1:], len(at))[: len(of)] - 1
        return list(zip(part[of].tolist(), (first - base)[of].tolist(), (last - base)[until].tolist(), strict=True))


def runs(at: np.ndarray, length: int, borders: np.ndarray) -> list[tuple[int, int, int]]:
    """(part, from, to) of the maximal runs of bytes under strings at the positions, each given once; parts end at the borders."""
    n = int(borders[-1])
    step = np.zeros(n + 1, np.int32)
    step[at] += 1
    step[at + length] -= 1
    under = np.cumsum(step[:-1]) > 0
    cut = np.zeros(n + 1, bool)
    cut[borders] = True
    first = np.flatnonzero(under & (cut[:-1] | ~np.concatenate([[False], under[:-1]])))
    last = np.flatnonzero(under & (cut[1:] | ~np.concatenate([under[1:], [False]]))) + 1
    part = np.searchsorted(borders, first, side="right") - 1
    return list(zip(part.tolist(), (first - borders[part]).tolist(), (last - borders[part]).tolist(), strict=True))


def by_hash(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """An order of the hashes by as many of their high bits as leave room for a place beside them, and these bits in that order."""
    bits = np.uint64(len(keys).bit_length())
    both = keys >> bits << bits
    both |= np.arange(len(keys), dtype=np.uint64)
    both.sort()  # much faster than to sort places by their hashes
    low = (np.uint64(1) << bits) - np.uint64(1)
    return (both & low).astype(np.int64), both & ~low


def with_equals(order: np.ndarray, keys: np.ndarray) -> np.ndarray:
    """Whose key stands more than once, for keys given in order."""
    out, same = np.zeros(len(order), bool), keys[1:] == keys[:-1]
    out[order[1:][same]] = True
    out[order[:-1][same]] = True
    return out


def dealt(names: np.ndarray, buckets: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Hashes in order, most repeats left out, borders of the buckets (ranges of high bits), each input's place, places with several."""
    order, _ = by_hash(names)
    sorted_ = names[order]
    fresh = np.ones(len(names), bool)
    fresh[1:] = sorted_[1:] != sorted_[:-1]
    place = np.empty(len(names), np.int64)
    place[order] = np.cumsum(fresh) - 1
    hashes = sorted_[fresh]
    often = np.bincount(place, minlength=len(hashes)) > 1 if len(names) else np.zeros(0, bool)
    return hashes, bucket_borders(hashes, buckets), place, often


def bucket_of(hashes: np.ndarray, buckets: int) -> np.ndarray:
    return (hashes >> np.uint64(32)) * np.uint64(buckets) >> np.uint64(32)


def bucket_borders(hashes: np.ndarray, buckets: int) -> np.ndarray:
    return np.searchsorted(bucket_of(hashes, buckets), np.arange(buckets + 1, dtype=np.uint64))


def planes(words: np.ndarray, borders: np.ndarray) -> list[bytes]:
    """The rows of words of each range that is not empty, byte by byte, after a mask of the bytes that are not 0 in all its rows; only those are kept."""
    full = np.flatnonzero(np.diff(borders))
    if not len(full):
        return []
    (n, k), first = words.shape, borders[full]
    raw, used = np.empty((8 * k, n), np.uint8), np.empty((len(full), k), "<u8")
    for c in range(k):
        word = np.ascontiguousarray(words[:, c], "<u8")
        raw[8 * c : 8 * c + 8] = word.view(np.uint8).reshape(n, 8).T
        used[:, c] = np.bitwise_or.reduceat(word, first)
    on = used.view(np.uint8) > 0
    masks = np.packbits(on, axis=1, bitorder="little")
    return [masks[i].tobytes() + raw[on[i], borders[b] : borders[b + 1]].tobytes() for i, b in enumerate(full)]


def all_planes(bodies: list[bytes], width_: int) -> tuple[np.ndarray, list[int]]:
    """The rows, not all 0, of so many words that `planes` wrote, one body after the other, and how many each has."""
    on = [np.unpackbits(np.frombuffer(x, np.uint8, width_), bitorder="little").astype(bool) for x in bodies]
    sizes = [(len(x) - width_) // int(o.sum()) for x, o in zip(bodies, on, strict=True)]
    n, a = sum(sizes), 0
    raw, words = np.zeros((8 * width_, n), np.uint8), np.empty((width_, n), "<u8")
    for body, o, m in zip(bodies, on, sizes, strict=True):
        raw[o, a : a + m] = np.frombuffer(body, np.uint8, offset=width_).reshape(-1, m)
        a += m
    for c in range(width_):
        words[c].view(np.uint8).reshape(n, 8)[:] = raw[8 * c : 8 * c + 8].T
    return words.T, sizes


def from_planes(body: bytes, width_: int) -> np.ndarray:
    return all_planes([body], width_)[0]


def sent(unit: int, packed: np.ndarray, borders: np.ndarray) -> pa.Table:
    """What a unit sends to each bucket, a row a bucket; rows of words as planes."""
    full = np.flatnonzero(np.diff(borders))
    bodies = planes(packed, borders) if packed.ndim > 1 else [packed[borders[b] : borders[b + 1]].tobytes() for b in full]
    return pa.table({
        "unit": pa.array(np.full(len(full), unit), pa.int32()),
        "bucket": pa.array(full, pa.int32()),
        "body": pa.array(bodies, pa.binary()),
    })


def ties(rows: pa.Table) -> pa.Table:
    """For each unit's hashes in a bucket, which ones stand there again."""
    parts = [np.frombuffer(x, np.uint32) for x in rows.column("body").to_pylist()]
    names = np.concatenate(parts)
    both = names.astype(np.uint64) << np.uint64(32) | np.arange(len(names), dtype=np.uint64)
    both.sort()
    tied = with_equals((both & np.uint64((1 << 32) - 1)).astype(np.int64), both >> np.uint64(32))
    return answered(rows, [np.packbits(x).tobytes() for x in apart(tied, map(len, parts))])


def apart(values: np.ndarray, sizes: Iterable[int]) -> list[np.ndarray]:
    return np.split(values, np.cumsum([*sizes])[:-1])


def answered(rows: pa.Table, bodies: list[bytes]) -> pa.Table:
    return pa.table({"unit": rows.column("unit"), "bucket": rows.column("bucket"), "body": pa.array(bodies, pa.binary())})


def told(own: Screen, flags: pa.Table, buckets: int) -> np.ndarray:
    """Which samples have an equal, in this unit or by the flags that came back."""
    _, borders, place, often = dealt(own.hashes, buckets)
    tied = often.copy()
    for b, bits in zip(flags.column("bucket").to_pylist(), flags.column("body").to_pylist(), strict=True):
        n = int(borders[b + 1] - borders[b])
        tied[borders[b] : borders[b + 1]] |= np.unpackbits(np.frombuffer(bits, np.uint8), count=n).astype(bool)
    return tied[place] if len(own.hashes) else np.zeros(0, bool)


def mixed(words: np.ndarray, bits: int, block: int = 1 << 15) -> np.ndarray:
    """A hash of each row of words, of which so many high bits are used; worked out block by block."""
    out = np.empty(len(words), np.uint64)
    for a in range(0, len(words), block):
        x = words[a : a + block, 0] * _A
        for k in range(1, words.shape[1]):
            x = joined_names(x, words[a : a + block, k])
        out[a : a + block] = joined_names(x, x >> np.uint64(32))
    return out if bits >= 64 else out >> np.uint64(64 - bits) << np.uint64(64 - bits)


def picked(words: np.ndarray, at: np.ndarray) -> np.ndarray:
    """Rows of words, which lie in memory word by word."""
    return (np.compress if at.dtype == bool else lambda i, x, axis: np.take(x, i, axis))(at, words.T, 1).T


def distinct(words: np.ndarray, bits: int, key: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Distinct rows sorted by the high bits of their hash and then word by word, these bits, each input's place, and how often each stands."""
    order, keys = by_hash(mixed(words, bits) if key is None else key)
    rows = picked(words, order)
    equal = keys[1:] == keys[:-1]
    same = np.logical_and.reduce([equal, *(c[1:] == c[:-1] for c in rows.T)])
    if (same != equal).any():  # different rows of one hash: these hashes' rows are sorted
        group = np.cumsum(np.concatenate([[False], ~equal]))
        several = np.zeros(int(group[-1]) + 1, bool)
        several[group[1:][same != equal]] = True
        on = np.flatnonzero(several[group])
        order[on] = order[on][np.lexsort((*picked(rows, on).T[::-1], group[on]))]
        rows = picked(words, order)
        same = np.logical_and.reduce([equal, *(c[1:] == c[:-1] for c in rows.T)])
    fresh = np.concatenate([np.ones(min(1, len(rows)), bool), ~same])
    place = np.empty(len(words), np.int64)
    place[order] = np.cumsum(fresh) - 1
    return picked(rows, fresh), keys[fresh], place, np.diff(np.flatnonzero(fresh), append=len(words))


def again(words: np.ndarray, bits: int, many: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes and places as `distinct` gave them, when it found so many rows; no row is compared if as many hashes differ."""
    key = mixed(words, bits)
    order, keys = by_hash(key)
    fresh = np.concatenate([np.ones(min(1, len(keys)), bool), keys[1:] != keys[:-1]])
    if int(fresh.sum()) != many:
        return distinct(words, bits, key)[1:3]
    place = np.empty(len(words), np.int64)
    place[order] = np.cumsum(fresh) - 1
    return keys[fresh], place


def levels(length: int) -> list[tuple[int, tuple[int, ...], int]]:
    """(bytes named, offsets of the names it is made of, bytes left over) of each level; the last names length - STEP + 1 bytes."""
    reach, size, out = length - STEP + 1, STEP, []
    if reach < STEP:
        raise ValueError(f"repeats of under {2 * STEP - 1} bytes are not searched")
    while 3 * size < reach - STEP + 1:
        out.append((3 * size, (0, size, 2 * size), 0))
        size *= 3
    last = (reach - size) // STEP * STEP
    return [*out, (reach, (0, min(size, last), last), reach - last - size)]


class Zone:
    """The regions of a unit side by side, and the names of their samples as levels give them."""

    def __init__(self, rows: pa.Table, length: int, bits: int):
        self.rows = ordered(rows, "h", "g", "at")
        self.raw, self.borders = as_bytes(self.rows.column("body").combine_chunks())
        self.length, self.bits, n = length, bits, len(self.raw)
        self.within, part = on_cover(np.diff(self.borders), STEP, STEP)
        self.at, self.left = self.borders[part] + self.within, np.diff(self.borders)[part] - self.within
        #: Eight bytes from each position, with eight of nothing before the first.
        self.view = np.ndarray((n + length + 16,), "<u8", bytes(8) + self.raw.tobytes() + bytes(length + 16), strides=(1,))
        self.names = self.view[self.at + 8] & np.uint64((1 << 8 * STEP) - 1)
        self.hot = np.zeros(len(self.at), bool)

    def triples(self, level: tuple[int, tuple[int, ...], int], first: bool) -> tuple[np.ndarray, np.ndarray]:
        """Samples that can be named at a level, and the names that make up theirs; each STEP bytes of a region hold as many samples."""
        size, offsets, over = level
        own = np.flatnonzero(self.left >= size)
        parts = [self.names[own + o // STEP * len(cover(STEP))] for o in offsets]
        if not first:
            alive = np.logical_and.reduce([p > 0 for p in parts])
            own, parts = own[alive], [p[alive] for p in parts]
        if over:
            parts.append(self.view[self.at[own] + 8 + size - over] & np.uint64((1 << 8 * over) - 1))
        return own, np.stack(parts).T

    def take(self, own: np.ndarray, words: np.ndarray, ranks: pa.Table, buckets: int) -> None:
        """Name the samples by the ranks that came back; 0 stands for no name."""
        bodies = ranks.column("body").to_pylist()
        keys, place = again(words, self.bits, sum(map(len, bodies)) // 4)
        borders, found = bucket_borders(keys, buckets), np.zeros(len(keys), np.uint64)
        hot = np.zeros(len(keys), bool)
        for b, body in zip(ranks.column("bucket").to_pylist(), bodies, strict=True):
            rank = np.frombuffer(body, np.uint32)
            part = slice(borders[b], borders[b + 1])
            hot[part] = rank & _HOT > 0
            rank = rank & ~_HOT
            found[part] = np.where(rank > 0, np.uint64(b << 32) | rank.astype(np.uint64), np.uint64(0))
        self.names = np.zeros(len(self.at), np.uint64)
        if len(own):
            self.names[own], self.hot[own] = found[place], hot[place]

    def suffixes(self) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(sample, words, hash to deal by) of named samples: the name, the bytes before with the shifts that fit in the
        region, the bytes behind; one row for each shift where the name is crowded."""
        around, reach = STEP - 1, self.length - STEP + 1
        own = np.flatnonzero(self.names)
        low = lambda n: (np.uint64(1) << (np.uint64(8) * n.astype(np.uint64))) - np.uint64(1)
        had = np.minimum(self.within[own], around)
        before = self.view[self.at[own] + 8 - around] & np.uint64((1 << 8 * around) - 1)
        before &= ~low(around - had)  # nothing from the region before
        behind = self.view[self.at[own] + 8 + reach] & low(np.clip(self.left[own] - reach, 0, around))
        least, most = np.maximum(self.length - self.left[own], 0), had
        fits = np.zeros(len(own), np.uint64)
        for d in range(STEP):
            fits |= ((least <= d) & (d <= most)).astype(np.uint64) << np.uint64(48 + d)
        words = picked(np.stack([self.names[own], before | fits, behind]).T, fits > 0)
        own = own[fits > 0]
        hot = self.hot[own]
        sample, rows = [own[~hot]], [picked(words, ~hot)]
        keys = [mixed(rows[0][:, :1], self.bits)]
        for d in range(STEP if hot.any() else 0):
            fit = hot & (words[:, 1] >> np.uint64(48 + d) & np.uint64(1) > 0)
            part = np.stack([words[fit, 0], seen_before(words[fit, 1], d) | np.uint64(1 << 48 + d), seen_behind(words[fit, 2], d) | np.uint64(1 + d << 48)]).T
            sample.append(own[fit])
            rows.append(part)
            keys.append(mixed(part, self.bits))
        return np.concatenate(sample), np.concatenate([x.T for x in rows], 1).T, np.concatenate(keys)


def seen_before(word: np.ndarray, d: int) -> np.ndarray:
    """The last d of the bytes before a named string."""
    return (word & np.uint64((1 << 48) - 1)) >> np.uint64(8 * (STEP - 1 - d))


def seen_behind(word: np.ndarray, d: int) -> np.ndarray:
    """The first bytes behind, so many that d before and these make up the whole length."""
    return word & np.uint64((1 << 8 * (STEP - 1 - d)) - 1)


def ranked(rows: pa.Table, words: int, bits: int, crowd: int) -> pa.Table:
    """Ranks from 1 of a bucket's strings that stand more than once, for each unit that sent them; others get 0."""
    whole, sizes = all_planes(rows.column("body").to_pylist(), words + 1)
    _, _, place, _ = distinct(whole[:, :-1], bits)
    often = np.bincount(place, whole[:, -1].astype(float))
    rank = np.where(often > 1, np.cumsum(often > 1), 0).astype(np.uint32)
    if len(rank) >= int(_HOT):
        raise ValueError("too many strings in a bucket")
    rank[often > crowd] |= _HOT
    return answered(rows, [x.tobytes() for x in apart(rank[place], sizes)])


def merged(rows: pa.Table, bits: int) -> pa.Table:
    """For each suffix the shifts, as bits, at which a neighbour of the same name has the same bytes around it."""
    if rows.column("bucket")[0].as_py() < 0:  # what a unit keeps
        return rows.select(["unit", "bucket", "body"])
    words, sizes = all_planes(rows.column("body").to_pylist(), 3)
    many = words[:, 1] & _MANY > 0
    words[:, 1] &= ~_MANY
    words, _, place, _ = distinct(words, bits)
    count = np.bincount(place, 1 + many)
    form, fits = words[:, 2] >> np.uint64(48), (words[:, 1] >> np.uint64(48)).astype(np.uint8)
    out = np.where(count > 1, fits, 0).astype(np.uint8)  # what stands again with all its bytes fits at all its shifts
    some = np.flatnonzero(with_equals(*by_hash(mixed(words[:, :1], bits))))  # of names with different bytes around
    for d in range(STEP):
        own = some[(fits[some] >> d & 1 > 0) & ((form[some] == 0) | (form[some] == 1 + d))]
        if not len(own):
            continue
        alone = form[own] > 0  # cut to its shift already
        before, behind = words[own, 1] & np.uint64((1 << 48) - 1), words[own, 2] & np.uint64((1 << 48) - 1)
        key = np.stack([words[own, 0], np.where(alone, before, seen_before(before, d)), seen_behind(behind, d)]).T
        _, _, at, _ = distinct(key, bits)
        often = np.bincount(at, count[own])
        out[own] |= (often[at] > 1).astype(np.uint8) << d
    return answered(rows, [x.tobytes() for x in apart(out[place], sizes)])


ROWS = "unit int, bucket int, body binary"
REGIONS = "unit int, h long, g long, at long, body binary"
_NONE = {"unit": pa.int32(), "bucket": pa.int32(), "body": pa.binary()}


def nothing() -> pa.Table:
    return pa.table({c: pa.array([], t) for c, t in _NONE.items()})


def regions(texts: DataFrame, size: int, length: int, period: int, piece: int = PIECE) -> DataFrame:
    """The parts of the texts (h, g, text) that the screen leaves, as rows (unit, h, g, at: byte offset in the text, body)."""
    spark = texts.sparkSession
    units, buckets = (max(width(spark), size // n + 1) for n in (UNIT_BYTES, BUCKET_BYTES))
    n = F.octet_length("text").cast("long")
    cut = F.explode(F.sequence(F.lit(0).cast("long"), F.floor((n - length) / piece)))
    pieces = texts.where(n >= length).select("h", "g", F.col("text").cast("binary").alias("text"), cut.alias("k"))
    body = F.expr(f"substring(text, cast(k * {piece} + 1 as int), {piece + length - 1})")
    pieces = pieces.select(F.pmod(F.xxhash64("h", "g", "k"), F.lit(units)).cast("int").alias("unit"), "h", "g", "k", body.alias("body"))

    def sample(rows: pa.Table) -> pa.Table:
        own = Screen(rows, length, period)
        hashes, borders, _, _ = dealt(own.hashes, buckets)
        return sent(rows.column("unit")[0].as_py(), hashes.astype(np.uint32), borders)

    flags = pieces.groupBy("unit").applyInArrow(sample, ROWS).groupBy("bucket").applyInArrow(ties, ROWS)
    flags = staged(flags, "ties")

    def leave(rows: pa.Table, flags: pa.Table) -> pa.Table:
        if not rows.num_rows:
            return pa.table({"unit": pa.array([], pa.int32()), "h": pa.array([], pa.int64()), "g": pa.array([], pa.int64()), "at": pa.array([], pa.int64()), "body": pa.array([], pa.binary())})
        own = Screen(rows, length, period)
        found = own.regions(told(own, flags, buckets))
        part = pa.array([i for i, _, _ in found], pa.int64())
        raw, base = own.raw, own.borders
        take = lambda c: own.rows.column(c).combine_chunks().take(part)
        return pa.table({
            "unit": take("unit"), "h": take("h"), "g": take("g"),
            "at": pc.add(pc.multiply(take("k"), piece), pa.array([a for _, a, _ in found], pa.int64())),
            "body": pa.array([raw[base[i] + a : base[i] + b].tobytes() for i, a, b in found], pa.binary()),
        })

    out = staged(pieces.groupBy("unit").cogroup(flags.groupBy("unit")).applyInArrow(leave, REGIONS), "regions", "zstd")
    discard(flags)
    return out


def repeated(left: DataFrame, length: int, bits: int, crowd: int) -> DataFrame:
    """(h, g, from, to): runs of repeated bytes of the texts, from their regions; runs of neighbouring pieces can overlap."""
    spark, plan = left.sparkSession, levels(length)
    size = left.agg(F.sum(F.octet_length("body"))).first()[0] or 0
    zones = max(width(spark), size // UNIT_BYTES + 1)
    buckets = max(width(spark), size * 12 // BUCKET_BYTES + 1)
    left = left.withColumn("unit", F.pmod("unit", F.lit(zones)).cast("int"))

    def named(rows: pa.Table, known: pa.Table, most: int) -> Zone:
        own = Zone(rows, length, bits)
        for n, level in enumerate(plan[:most]):
            ranks = known.filter(pc.equal(known.column("level"), n))
            own.take(*own.triples(level, n == 0), ranks, buckets)
        return own

    def step(most: int):
        def run(rows: pa.Table, known: pa.Table | None) -> pa.Table:
            if not rows.num_rows:
                return nothing()
            own, unit = named(rows, known, most), rows.column("unit")[0].as_py()
            if most < len(plan):
                words, keys, _, often = distinct(own.triples(plan[most], most == 0)[1], bits)
                words, borders = np.concatenate([words.T, often[None].astype(np.uint64)]).T, bucket_borders(keys, buckets)
            else:
                sample, words, keys = own.suffixes()
                room = np.uint64(buckets.bit_length())  # for the bucket, above the hash of all words
                keys = bucket_of(keys, buckets) << np.uint64(64) - room | mixed(words, bits) >> room
                words, keys, place, often = distinct(words, bits, keys)
                borders = np.searchsorted(keys >> np.uint64(64) - room, np.arange(buckets + 1, dtype=np.uint64))
                words[often > 1, 1] |= _MANY
                # Where each suffix stands and its place among those sent wait in a group of their own for the answers.
                order = np.argsort(sample, kind="stable")
                held = b"".join(planes(np.stack([np.diff(own.at[sample[order]], prepend=0), place[order] + 1]).T, np.array([0, len(sample)])))
                state = pa.table({"unit": pa.array([unit], pa.int32()), "bucket": pa.array([-1 - unit], pa.int32()), "body": pa.array([held], pa.binary())})
                return pa.concat_tables([sent(unit, words, borders), state])
            return sent(unit, words, borders)

        return run if most else lambda rows: run(rows, None)

    def mark(rows: pa.Table, known: pa.Table) -> pa.Table:
        empty = {"h": pa.int64(), "g": pa.int64(), "from": pa.int64(), "to": pa.int64()}
        if not rows.num_rows:
            return pa.table({c: pa.array([], t) for c, t in empty.items()})
        rows = ordered(rows, "h", "g", "at")
        raw, borders = as_bytes(rows.column("body").combine_chunks())
        state, answers = known.filter(pc.less(known.column("bucket"), 0)), known.filter(pc.greater_equal(known.column("bucket"), 0)).sort_by("bucket")
        body = state.column("body")[0].as_py()
        steps, place = from_planes(body, 2).astype(np.int64).T if body else np.zeros((2, 0), np.int64)
        at, place = np.cumsum(steps), place - 1
        found = np.frombuffer(b"".join(answers.column("body").to_pylist()), np.uint8)
        shifts, there = found[place], np.zeros(len(raw) + 1, bool)
        for d in range(STEP):
            there[at[shifts >> d & 1 > 0] - d] = True
        spans = runs(np.flatnonzero(there), length, borders)
        part = pa.array([i for i, _, _ in spans], pa.int64())
        take = lambda c: rows.column(c).combine_chunks().take(part)
        at = take("at")
        return pa.table({"h": take("h"), "g": take("g"), "from": pc.add(at, pa.array([a for _, a, _ in spans], pa.int64())), "to": pc.add(at, pa.array([b for _, _, b in spans], pa.int64()))})

    def rank(words: int):
        return lambda t: ranked(t, words, bits, crowd)

    known = None
    for n in range(len(plan) + 1):
        if known is None:
            out = left.groupBy("unit").applyInArrow(step(n), ROWS)
        else:
            out = left.groupBy("unit").cogroup(known.groupBy("unit")).applyInArrow(step(n), ROWS)
        apply = rank(3 + (plan[n][2] > 0)) if n < len(plan) else lambda t: merged(t, bits)
        answers = staged(out.groupBy("bucket").applyInArrow(apply, ROWS).withColumn("level", F.lit(n)), "ranks")
        known = answers if known is None else known.union(answers)
    return left.groupBy("unit").cogroup(answers.groupBy("unit")).applyInArrow(mark, "h long, g long, from long, to long")


def repeats(
    df: DataFrame, key: str = "doc_id", text: str = "text", length: int = LENGTH, period: int = PERIOD, with_text: bool = False, bits: int = 64, crowd: int = CROWD, piece: int = PIECE
) -> DataFrame:
    """Per document the bytes, removed bytes and maximal removed runs, and a digest of what remains.

    with_text adds the runs (from, to: byte borders) and the remaining bytes. bits: how many bits of the hash deal and
    presort triples; crowd and piece: as CROWD and PIECE. None of the three changes the results.
    """
    spark = df.sparkSession
    base = df.select(F.col(key).cast("long").alias("doc_id"), F.coalesce(F.col(text).cast("string"), F.lit("")).alias("text"))
    named = [F.xxhash64("text").alias("h"), F.xxhash64(F.lit("copy"), "text").alias("g")]
    texts = staged(base.groupBy("text").agg(F.count("*").alias("n")).select(*named, "n", "text"), "texts", "zstd")
    size, most = texts.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0)), F.coalesce(F.sum("n"), F.lit(0))).first()
    left = regions(texts.select("h", "g", "text"), size, length, period, piece)
    found = repeated(left, length, bits, crowd)
    spans = staged(found.groupBy("h", "g").agg(F.sort_array(F.collect_list(F.struct("from", "to"))).alias("spans")), "spans")  # the runs of one text
    discard(left)

    more = ", kept binary, spans array<struct<from: long, to: long>>" if with_text else ""

    def finish(batches):
        for batch in slices(batches, "text", 8 << 20):
            out = []
            for h, g, n, raw, own in zip(*(batch.column(c).to_pylist() for c in ("h", "g", "n")), batch.column("text").cast(pa.large_binary()).to_pylist(), batch.column("spans").to_pylist(), strict=True):
                gone, kept, at = [], [], 0
                for a, b in [(0, len(raw))] if n > 1 and len(raw) >= length else [(s["from"], s["to"]) for s in own or ()]:
                    if gone and a <= gone[-1][1]:
                        gone[-1][1] = max(gone[-1][1], b)
                    else:
                        gone.append([a, b])
                for a, b in gone:
                    kept.append(raw[at:a])
                    at = b
                rest = b"".join([*kept, raw[at:]])
                row = (h, g, n, len(raw), len(raw) - len(rest), len(gone), hashlib.sha256(rest).hexdigest())
                out.append((*row, rest, [{"from": a, "to": b} for a, b in gone]) if with_text else row)
            kinds = [pa.int64()] * 6 + [pa.string()] + ([pa.binary(), pa.list_(pa.struct([("from", pa.int64()), ("to", pa.int64())]))] if with_text else [])
            names = ["h", "g", "n", "n_bytes", "n_removed", "n_spans", "kept_sha256"] + (["kept", "spans"] if with_text else [])
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), kinds, strict=True)], names)

    joined = texts.join(spans, ["h", "g"], "left").select("h", "g", "n", "text", "spans")
    results = staged(joined.mapInArrow(finish, "h long, g long, n long, n_bytes long, n_removed long, n_spans long, kept_sha256 string" + more), "results")
    discard(texts, spans)
    # Texts with very many rows, at most a thousand of them, are dealt out by the order of their rows.
    share = max(1000, most // 1000)
    hot = staged(results.where(F.col("n") > share).select(F.col("h").alias("hh"), F.col("g").alias("gg"), F.ceil(F.col("n") / share).cast("long").alias("salts")), "hot")
    rows = base.select("doc_id", *named)
    rows = rows.join(F.broadcast(hot), (F.col("h") == F.col("hh")) & (F.col("g") == F.col("gg")), "left")
    rows = rows.withColumn("salt", F.coalesce(F.pmod(F.monotonically_increasing_id(), F.col("salts")), F.lit(0).cast("long"))).select("doc_id", "h", "g", "salt")
    every = F.explode(F.sequence(F.lit(0).cast("long"), F.when(F.col("n") > share, F.ceil(F.col("n") / share) - 1).otherwise(0).cast("long")))
    columns = [x.split()[0] for x in RESULT.split(", ")] + (["kept", "spans"] if with_text else [])
    return rows.join(results.withColumn("salt", every).drop("n"), ["h", "g", "salt"]).select(*columns)
