"""Counter-based randomness: a walk is a pure function of (seed, lane, start, walk, hop).

Results don't depend on partitioning, retries or the engine that runs them. Two 32-bit numbers per
step: one for the stop test, one for the choice. The same hash exists as Catalyst expressions and
as numpy code for the walk kernel.
"""

from __future__ import annotations

from hashlib import md5

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

#: Fixed values of the public 64-bit xxHash.
P1, P2, P3, P4, P5 = 0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5
SPARK_SEED = 42
LOW = 0xFFFFFFFF


def _rotate(x: np.ndarray, r: int) -> np.ndarray:
    return (x << np.uint64(r)) | (x >> np.uint64(64 - r))


def hash_longs(*values) -> np.ndarray:
    """Spark's xxhash64 of bigint columns, as unsigned numbers."""
    h = np.uint64(SPARK_SEED)
    with np.errstate(over="ignore"):
        for v in values:
            v = np.asarray(v).astype(np.int64).view(np.uint64)
            x = np.asarray(h + np.uint64(P5) + np.uint64(8), np.uint64)
            x = x ^ (_rotate(v * np.uint64(P2), 31) * np.uint64(P1))
            x = _rotate(x, 27) * np.uint64(P1) + np.uint64(P4)
            x = (x ^ (x >> np.uint64(33))) * np.uint64(P2)
            x = (x ^ (x >> np.uint64(29))) * np.uint64(P3)
            h = x ^ (x >> np.uint64(32))
    return h


def _mixed(h: np.ndarray, key) -> np.ndarray:
    """A round of the hash on h, which is overwritten."""
    h += np.uint64((P5 + 8) % 2**64)
    h ^= key
    low = h >> np.uint64(37)
    h <<= np.uint64(27)
    h |= low
    h *= np.uint64(P1)
    h += np.uint64(P4)
    for shift, factor in ((33, P2), (29, P3)):
        np.right_shift(h, np.uint64(shift), out=low)
        h ^= low
        h *= np.uint64(factor)
    np.right_shift(h, np.uint64(32), out=low)
    h ^= low
    return h


def _key(v) -> np.ndarray:
    x = np.asarray(v).astype(np.int64).view(np.uint64) * np.uint64(P2)
    return _rotate(x, 31) * np.uint64(P1)


class Hashed:
    """Draws of many walks, hop by hop; what the hops of a walk share is hashed once."""

    def __init__(self, seed: int, lane, start: np.ndarray, walk: np.ndarray):
        self.h = np.full(1, np.uint64(SPARK_SEED))
        with np.errstate(over="ignore"):
            for part in (np.array([seed]), np.atleast_1d(lane), start, walk):
                if len(self.h) < len(part):  # what all walks have in common is hashed once
                    self.h = np.repeat(self.h, len(part))
                self.h = _mixed(self.h, _key(part))
        if len(self.h) < len(start):
            self.h = np.repeat(self.h, len(start))

    def draw(self, hop: int, some: slice = slice(None)) -> tuple[np.ndarray, np.ndarray]:
        """(stop number, choice number) of some walks, both below 2**32."""
        with np.errstate(over="ignore"):
            h = _mixed(self.h[some].copy(), _key(np.array([hop])))
        return h.astype(np.uint32), (h >> np.uint64(32)).astype(np.uint32)

    def move(self, some: slice, on: np.ndarray, up: slice) -> None:
        """Of some walks, those that go on move up to a place before them."""
        self.h[up] = self.h[some][on]

    def keep(self, count: int) -> None:
        self.h = self.h[:count]


class Digested:
    """The same from md5, a digest a draw, which any SQL engine repeats."""

    def __init__(self, seed: int, lane, start: np.ndarray, walk: np.ndarray):
        lanes = np.broadcast_to(lane, np.shape(start)).tolist()
        self.text = np.array([f"{seed}|{a}|{b}|{c}|".encode() for a, b, c in zip(lanes, start.tolist(), walk.tolist(), strict=True)], object)

    def draw(self, hop: int, some: slice = slice(None)) -> tuple[np.ndarray, np.ndarray]:
        last = str(hop).encode()
        numbers = np.frombuffer(b"".join([md5(t + last).digest() for t in self.text[some].tolist()]), ">u4").reshape(-1, 4)
        return numbers[:, 0].astype(np.uint32), numbers[:, 1].astype(np.uint32)

    def move(self, some: slice, on: np.ndarray, up: slice) -> None:
        self.text[up] = self.text[some][on]

    def keep(self, count: int) -> None:
        self.text = self.text[:count]


def drawer(rng: str):
    return Digested if rng == "md5" else Hashed


def draw_columns(rng: str, seed: int, lane: Column, start: Column, walk: Column, hop: Column) -> tuple[Column, Column]:
    parts = [F.lit(seed).cast("long"), lane.cast("long"), start.cast("long"), walk.cast("long"), hop.cast("long")]
    if rng == "md5":
        text = F.md5(F.concat_ws("|", *(p.cast("string") for p in parts)))
        number = lambda at: F.conv(F.substring(text, at, 8), 16, 10).cast("long")
        return number(1), number(9)
    h = F.xxhash64(*parts)
    return h.bitwiseAND(F.lit(LOW).cast("long")), F.shiftrightunsigned(h, 32)


def stop_limit(alpha: float) -> int:
    """A stop number below this stops the walk."""
    return int(alpha * 2**32)


#: The md5 draw in DuckDB's SQL: seed, lane, start, walk and hop are expressions.
def md5_sql(seed: int, lane: str, start: str, walk: str, hop: str, at: int) -> str:
    text = f"md5('{seed}|' || {lane} || '|' || {start} || '|' || {walk} || '|' || {hop})"
    return f"('0x' || substr({text}, {at}, 8))::BIGINT"
