"""Families of k hash functions, each in three equal forms: Spark column, numpy array and SQL text.

Hashes have 31 bits and elements 32, so the pair of an element, hash first, packs into one BIGINT whose order is the pair
order (ties of the hash go to the smaller element).
"""

from __future__ import annotations

import random
from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Prime modulus of the affine and polynomial families.
PRIME = 2147483647
MASK31 = 0x7FFFFFFF
#: One above the largest element; the largest pair is then below the infinite limit.
UNIVERSE = 2**32 - 1

# Constants of the 64-bit hash that Spark's xxhash64 computes.
_P1, _P2, _P3, _P4, _P5 = 0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x85EBCA77C2B2AE63, 0x27D4EB2F165667C5


class HashFamily:
    """``k`` functions h_0 .. h_{k-1} of one kind, drawn from ``seed`` and shared by all sets."""

    KINDS = ("affine", "tabulation", "polynomial", "native")

    def __init__(self, kind: str, k: int, seed: int = 1, degree: int = 2):
        if kind not in self.KINDS:
            raise ValueError(f"unknown hash family {kind}")
        self.kind, self.k, self.seed, self.degree = kind, k, seed, degree
        rng = random.Random(f"{kind}-{seed}")
        if kind == "affine":
            self.coefficients = [[rng.randrange(1, PRIME), rng.randrange(PRIME)] for _ in range(k)]
        elif kind == "polynomial":
            self.coefficients = [[rng.randrange(1, PRIME), *(rng.randrange(PRIME) for _ in range(degree - 1))] for _ in range(k)]
        elif kind == "tabulation":
            self.coefficients = [[rng.randrange(MASK31 + 1) for _ in range(8 * 16)] for _ in range(k)]
        else:
            self.coefficients = [[seed * 1_000_003 + i & MASK31] for i in range(k)]

    @classmethod
    def affine(cls, k: int, seed: int = 1) -> HashFamily:
        return cls("affine", k, seed)

    @classmethod
    def tabulation(cls, k: int, seed: int = 1) -> HashFamily:
        return cls("tabulation", k, seed)

    @classmethod
    def polynomial(cls, k: int, degree: int = 4, seed: int = 1) -> HashFamily:
        return cls("polynomial", k, seed, degree)

    @classmethod
    def native(cls, k: int, seed: int = 1) -> HashFamily:
        return cls("native", k, seed)

    # Spark columns

    def hash(self, slot: int, x: Column) -> Column:
        c = self.coefficients[slot]
        if self.kind == "affine":
            return (F.lit(c[0]).cast("bigint") * x + F.lit(c[1]).cast("bigint")) % F.lit(PRIME).cast("bigint")
        if self.kind == "polynomial":
            y = x % F.lit(PRIME).cast("bigint")
            return reduce(lambda acc, ci: (acc * y + F.lit(ci).cast("bigint")) % F.lit(PRIME).cast("bigint"), c[1:], F.lit(c[0]).cast("bigint"))
        if self.kind == "tabulation":
            looked = [F.element_at(F.lit(c[16 * j : 16 * j + 16]), (F.shiftright(x, 4 * j).bitwiseAND(F.lit(15)) + 1).cast("int")).cast("bigint") for j in range(8)]
            return reduce(lambda a, b: a.bitwiseXOR(b), looked)
        return F.xxhash64(x, F.lit(c[0])).bitwiseAND(F.lit(MASK31).cast("bigint"))

    def pair(self, slot: int, x: Column) -> Column:
        return F.shiftleft(self.hash(slot, x), 32).bitwiseOR(x)

    def pair_wide(self, slot: int, x: Column) -> Column:
        """For elements beyond 32 bits: a struct in the same order (its aggregates sort instead of hashing)."""
        return F.struct(F.xxhash64(x, F.lit(self.coefficients[slot][0])).alias("h"), x.alias("x"))

    def pairs(self, x: Column) -> Column:
        """All k pairs as an array, slot order."""
        return F.array(*[self.pair(i, x) for i in range(self.k)])

    # numpy

    def hash_numpy(self, x: np.ndarray) -> np.ndarray:
        """(len(x), k) hashes."""
        x = np.asarray(x, np.int64)
        if self.kind == "tabulation":
            return self.hash_int32(x).astype(np.int64)
        if self.kind == "native":
            inner = _xx_long(x.view(np.uint64), np.uint64(42))
            return np.column_stack([(_xx_int(c[0], inner) & np.uint64(MASK31)).astype(np.int64) for c in self.coefficients])
        c = np.array(self.coefficients, np.int64)
        if self.kind == "affine":
            return (x[:, None] * c[:, 0] + c[:, 1]) % PRIME
        y, out = (x % PRIME)[:, None], np.broadcast_to(c[:, 0], (len(x), self.k))
        for i in range(1, c.shape[1]):
            out = (out * y + c[:, i]) % PRIME
        return out

    def hash_int32(self, x: np.ndarray) -> np.ndarray:
        """(len(x), k) hashes in half the space."""
        if self.kind != "tabulation":
            return self.hash_numpy(x).astype(np.int32)
        x, tables = np.asarray(x, np.int64), self._byte_tables()
        out = tables[0][x & 255]
        for j in (1, 2, 3):
            out ^= tables[j][x >> (8 * j) & 255]
        return out

    def _byte_tables(self) -> np.ndarray:
        """(4, 256, k): the nibble tables of two neighbouring nibbles combined, so that an element takes four look-ups."""
        if not hasattr(self, "_tables"):
            nibble = np.array(self.coefficients, np.int32).reshape(self.k, 8, 16)
            byte = np.arange(256)
            self._tables = np.stack([(nibble[:, 2 * j, byte & 15] ^ nibble[:, 2 * j + 1, byte >> 4]).T.copy() for j in range(4)])
        return self._tables

    def __getstate__(self) -> dict:
        return {k: v for k, v in self.__dict__.items() if k != "_tables"}

    def pairs_numpy(self, x: np.ndarray) -> np.ndarray:
        x = np.asarray(x, np.int64)
        return self.hash_numpy(x) << 32 | x[:, None]

    # SQL text (DuckDB)

    def hash_sql(self, slot: int, x: str) -> str:
        c = self.coefficients[slot]
        if self.kind == "affine":
            return f"(({c[0]}::BIGINT * {x} + {c[1]}::BIGINT) % {PRIME})"
        if self.kind == "polynomial":
            return reduce(lambda acc, ci: f"(({acc} * ({x} % {PRIME}) + {ci}::BIGINT) % {PRIME})", c[1:], f"{c[0]}::BIGINT")
        if self.kind == "tabulation":
            looked = [f"({c[16 * j : 16 * j + 16]}::BIGINT[])[(({x} >> {4 * j}) & 15) + 1]" for j in range(8)]
            return reduce(lambda a, b: f"xor({a}, {b})", looked)
        raise ValueError("the native family has no SQL form")

    def pair_sql(self, slot: int, x: str) -> str:
        return f"(({self.hash_sql(slot, x)} << 32) | {x})"


def _rot(x: np.ndarray, n: int) -> np.ndarray:
    return (x << np.uint64(n)) | (x >> np.uint64(64 - n))


def _finish(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(33))) * np.uint64(_P2)
    h = (h ^ (h >> np.uint64(29))) * np.uint64(_P3)
    return h ^ (h >> np.uint64(32))


def _xx_long(x: np.ndarray, seed: np.uint64) -> np.ndarray:
    with np.errstate(over="ignore"):
        h = (seed + np.uint64(_P5) + np.uint64(8)) ^ (_rot(x * np.uint64(_P2), 31) * np.uint64(_P1))
        return _finish(_rot(h, 27) * np.uint64(_P1) + np.uint64(_P4))


def _xx_int(x: int, seed: np.ndarray) -> np.ndarray:
    with np.errstate(over="ignore"):
        h = (seed + np.uint64(_P5) + np.uint64(4)) ^ (np.full(len(seed), x, np.uint64) * np.uint64(_P1))
        return _finish(_rot(h, 23) * np.uint64(_P2) + np.uint64(_P3))


def xxhash(x: np.ndarray, seed: int) -> np.ndarray:
    """Spark's ``xxhash64(x, seed)`` of a bigint and an int."""
    return _xx_int(seed, _xx_long(np.ascontiguousarray(x, np.int64).view(np.uint64), np.uint64(42))).view(np.int64)


def shuffled(spark, n: int, k: int, seed: int = 1) -> DataFrame:
    """(slot, element, h): k random permutations of 0..n-1 as a table. O(k n) space: for comparisons only."""
    from pyspark.sql import Window

    order = F.md5(F.concat_ws("-", F.lit(str(seed)), F.col("slot").cast("string"), F.col("element").cast("string")))
    every = spark.range(k).withColumnRenamed("id", "slot").crossJoin(spark.range(n).withColumnRenamed("id", "element"))
    return every.withColumn("h", F.row_number().over(Window.partitionBy("slot").orderBy(order, "element")).cast("bigint") - 1)


def minwise_bias(kind: str, members: list[int], first: list[int], trials: int = 2000, seed: int = 1) -> tuple[float, float]:
    """(observed, ideal) probability that ``first`` are the least of ``members``, over ``trials`` functions of a family."""
    from math import comb

    x = np.array(members, np.int64)
    inside = np.isin(x, first)
    hits, done = 0, 0
    while done < trials:
        k = min(256, trials - done)
        p = HashFamily(kind, k, seed + done, degree=len(first) + 1).pairs_numpy(x)
        hits += int((p[inside].max(0) < p[~inside].min(0)).sum())
        done += k
    return hits / trials, 1 / comb(len(members), len(first))
