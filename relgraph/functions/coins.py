"""Random numbers that depend on their key alone, so that a repeated task draws the same worlds.

The md5 form can be drawn in other SQL engines too; the xxhash64 form is faster.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterable, Iterator

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

DIGITS = 13


def coin(seed: int, *key: Column | str, fast: bool = False) -> Column:
    """A number in [0, 1) for the key, which usually is (rep, world, edge_id)."""
    columns = [F.col(k) if isinstance(k, str) else k for k in key]
    if fast:
        return F.shiftrightunsigned(F.xxhash64(F.lit(seed), *columns), 11).cast("double") / float(1 << 53)
    text = F.concat_ws(":", F.lit(str(seed)), *(c.cast("string") for c in columns))
    return F.conv(F.substring(F.md5(text), 1, DIGITS), 16, 10).cast("long").cast("double") / float(1 << 4 * DIGITS)


def coins_of(ids: Iterable[int], seed: int, *key: int) -> np.ndarray:
    """The md5 form in Python, for keys that differ in their last part."""
    head = ":".join(map(str, (seed, *key, ""))).encode()
    drawn = (int.from_bytes(hashlib.md5(head + b"%d" % i, usedforsecurity=False).digest()[:7], "big") >> 4 for i in ids)
    return np.fromiter(drawn, np.int64) / float(1 << 4 * DIGITS)


#: Factors of xxhash64.
_P1, _P2, _P3, _P4, _P5 = (np.array([p], np.uint64) for p in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5))
#: Ids whose hashes are worked out together.
_SLICE = 1 << 9


def _turned(x: np.ndarray, by: int) -> np.ndarray:
    return x << np.uint64(by) | x >> np.uint64(64 - by)


def _mixed(x: np.ndarray, y: np.ndarray | None = None) -> np.ndarray:
    """The last steps of a hash, in place; y is room for as many."""
    y = np.empty_like(x) if y is None else y
    for by, factor in ((33, _P2), (29, _P3), (32, None)):
        np.right_shift(x, np.uint64(by), out=y)
        np.bitwise_xor(x, y, out=x)
        if factor is not None:
            np.multiply(x, factor, out=x)
    return x


def _hashed(values: np.ndarray, on: np.ndarray) -> np.ndarray:
    """Spark's xxhash64 of ints on top of earlier hashes; those over 32 bits are longs in Spark."""
    if np.array_equal(values, values.astype(np.int32)):
        return _mixed(_turned((on + _P5 + np.uint64(4)) ^ (values.astype(np.uint32).astype(np.uint64) * _P1), 23) * _P2 + _P3)
    return _mixed(_turned((on + _P5 + np.uint64(8)) ^ _turned(values.astype(np.uint64) * _P2, 31) * _P1, 27) * _P1 + _P4)


def fast_words(ids: np.ndarray, prob: np.ndarray, worlds: int, *key: int) -> Iterator[np.ndarray]:
    """For every 64 worlds a long for each id, whose bit i tells if the xxhash64 coin of (*key, world i, id) is below its probability."""
    head = np.array([42], np.uint64)
    for k in key:
        head = _hashed(np.array([k], np.int64), head)
    heads = _turned(_hashed(np.arange(worlds, dtype=np.int64), head) + _P5 + np.uint64(8), 27)
    own = _turned(_turned(ids.astype(np.int64).view(np.uint64) * _P2, 31) * _P1, 27)
    steps = np.ceil(np.where(np.isnan(prob), 1, np.clip(prob, 0, 1)) * float(1 << 53)).astype(np.uint64)
    most = (steps << np.uint64(11)) - np.uint64(1)  # the largest hash whose coin is below; all ones for a sure edge
    room, spare, on = np.empty(_SLICE * 64, np.uint64), np.empty(_SLICE * 64, np.uint64), np.zeros((_SLICE, 64), bool)
    for w in range(0, worlds, 64):
        bits, now = np.zeros(len(ids), np.int64), heads[w : w + 64]
        on[:, len(now) :] = False
        for a in range(0, len(ids), _SLICE):
            part = own[a : a + _SLICE, None]
            n = len(part) * len(now)
            drawn = room[:n]
            np.bitwise_xor(part, now, out=drawn.reshape(len(part), -1))
            np.multiply(drawn, _P1, out=drawn)
            np.add(drawn, _P4, out=drawn)
            np.less_equal(_mixed(drawn, spare[:n]).reshape(len(part), -1), most[a : a + _SLICE, None], out=on[: len(part), : len(now)])
            bits[a : a + _SLICE] = np.packbits(on[: len(part)], axis=1, bitorder="little").view("<i8")[:, 0]
        yield np.where(steps > 0, bits, 0)


def coin_sql(seed: int, *key: str) -> str:
    """The md5 form for DuckDB."""
    text = " || ':' || ".join([f"'{seed}'", *(f"CAST({k} AS VARCHAR)" for k in key)])
    return f"(('0x' || substr(md5({text}), 1, {DIGITS}))::BIGINT / {float(1 << 4 * DIGITS)!r})"


def geometric_gap(u: Column, prob: Column) -> Column:
    """Failures before the next success, for a number in [0, 1); certain edges have gap 0."""
    return F.when(prob >= 1, F.lit(0).cast("long")).otherwise(F.floor(F.log(1 - u) / F.log1p(-F.when(prob < 1, prob).otherwise(0.5))))


def gap_sql(u: str, prob: str) -> str:
    return f"CASE WHEN {prob} >= 1 THEN 0 ELSE CAST(floor(ln(1 - {u}) / ln(1 - CASE WHEN {prob} < 1 THEN {prob} ELSE 0.5 END)) AS BIGINT) END"


def rank_key(seed: int, *key: Column | str) -> Column:
    """Text that orders rows at random, but the same way everywhere."""
    columns = [F.col(k) if isinstance(k, str) else k for k in key]
    return F.md5(F.concat_ws(":", F.lit(str(seed)), *(c.cast("string") for c in columns)))


def rank_key_sql(seed: int, *key: str) -> str:
    return "md5(" + " || ':' || ".join([f"'{seed}'", *(f"CAST({k} AS VARCHAR)" for k in key)]) + ")"
