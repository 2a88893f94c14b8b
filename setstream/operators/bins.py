"""The bin sketch: an element falls on one level (geometric) and one of its bins, where a counter goes up or down.

Counters add up, so sketches merge by sums and need no recovery, but repeated inserts count twice: legalise a stream first.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from math import ceil, log2, sqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import HashFamily
from .similarity import jaccard, signatures


class BinShape:
    """``levels`` levels of ``bins`` bins. ``rule`` names how full the level chosen for a query may be expected to be:
    'alpha_bins' (alpha times the bins, the default), 'root' (their square root) or 'alpha_root'."""

    def __init__(self, bins: int = 64, levels: int = 18, seed: int = 77, rule: str = "alpha_bins", alpha: float = 0.1):
        self.bins, self.levels, self.rule, self.alpha = bins, levels, rule, alpha
        self.family = HashFamily.affine(2, seed)

    @property
    def occupancy(self) -> float:
        return {"alpha_bins": self.alpha * self.bins, "root": sqrt(self.bins), "alpha_root": self.alpha * sqrt(self.bins)}[self.rule]

    def level(self, x: Column) -> Column:
        """Trailing zero bits of a hash of its own, at most the last level."""
        h = self.family.hash(0, x)
        return reduce(lambda a, b: a + b, [F.when(h % F.lit(1 << j).cast("bigint") == 0, 1).otherwise(0) for j in range(1, self.levels)])

    def bin(self, x: Column) -> Column:
        return (self.family.hash(1, x) % self.bins).cast("int")

    def level_sql(self, x: str) -> str:
        h = self.family.hash_sql(0, x)
        return "(" + " + ".join(f"({h} % {1 << j} = 0)::INT" for j in range(1, self.levels)) + ")"

    def bin_sql(self, x: str) -> str:
        return f"({self.family.hash_sql(1, x)} % {self.bins})::INT"

    def place_numpy(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        h = self.family.hash_numpy(x)
        level = sum((h[:, 0] % (1 << j) == 0).astype(np.int64) for j in range(1, self.levels))
        return level, h[:, 1] % self.bins

    def level_of(self, n: int) -> int:
        """Least level whose expected number of elements, n / 2^(level + 1), is within the occupancy."""
        return min(self.levels - 1, max(0, ceil(log2(n / self.occupancy)) - 1)) if n > 0 else 0

    def level_for(self, n: Column) -> Column:
        wanted = (F.ceil(F.log2(F.greatest(n, F.lit(1)) / F.lit(self.occupancy))) - 1).cast("int")
        return F.least(F.lit(self.levels - 1), F.greatest(F.lit(0), wanted))

    def level_for_sql(self, n: str) -> str:
        return f"least({self.levels - 1}, greatest(0, (ceil(log2(greatest({n}, 1) / {self.occupancy!r}::DOUBLE)) - 1)::INT))"


def bins_init(members: DataFrame, shape: BinShape) -> DataFrame:
    """(set_id, level, bin, cnt); zero counters are left out. Of (set_id, e), each set in one row, its counters are one row too: (set_id, bins)."""
    if "e" in members.columns:
        return _bins_of_sets(members, shape)
    return bins_apply(None, members.withColumn("op", F.lit(1)), shape)


def _bins_of_sets(sets: DataFrame, shape: BinShape) -> DataFrame:
    """(set_id, bins) of (set_id, e), counted where each set stands."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            # So many elements are counted at once, of one set at least.
            upto = np.cumsum(whole.column(1).value_lengths().to_numpy(zero_copy_only=False), dtype=np.int64)
            a = 0
            while a < whole.num_rows:
                b = max(a + 1, int(np.searchsorted(upto, (upto[a - 1] if a else 0) + (1 << 18), "right")))
                batch, a = whole.slice(a, b - a), b
                n = batch.column(1).value_lengths().to_numpy(zero_copy_only=False)
                level, at = shape.place_numpy(batch.column(1).flatten().to_numpy(zero_copy_only=False))
                key, cnt = np.unique((np.repeat(np.arange(len(n)), n) * shape.levels + level) * shape.bins + at, return_counts=True)
                row, place = np.divmod(key, shape.levels * shape.bins)
                taken = pa.StructArray.from_arrays([pa.array(place // shape.bins, pa.int32()), pa.array(place % shape.bins, pa.int32()), pa.array(cnt, pa.int64())], names=["level", "bin", "cnt"])
                offsets = np.searchsorted(row, np.arange(len(n) + 1)).astype(np.int32)
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(offsets), taken)], names=["set_id", "bins"])

    return sets.where("size(e) > 0").select("set_id", "e").mapInArrow(count, "set_id bigint, bins array<struct<level: int, bin: int, cnt: bigint>>")


def _level_signatures_of_sets(bins: DataFrame, family: HashFamily, shape: BinShape) -> DataFrame:
    """``bins_level_signatures`` of (set_id, bins), made where each set's counters stand."""
    n = F.aggregate("bins", F.lit(0).cast("bigint"), lambda s, x: s + x["cnt"])

    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pairs = family.pairs_numpy(np.arange(shape.bins))
        for batch in batches:
            taken = batch.column(2)
            row = np.repeat(np.arange(batch.num_rows), taken.value_lengths().to_numpy(zero_copy_only=False))
            level, at = (c.to_numpy(zero_copy_only=False).astype(np.int64) for c in taken.flatten().flatten()[:2])
            near = np.abs(level - batch.column(1).to_numpy(zero_copy_only=False)[row]) <= 1
            key = row[near] * shape.levels + level[near]
            order = np.argsort(key, kind="stable")
            key, at = key[order], at[near][order]
            first = np.flatnonzero(np.r_[True, key[1:] != key[:-1]][: len(key)])
            step = max(1, (1 << 21) // family.k // shape.bins)
            for a in range(0, len(first), step):
                own = first[a : a + step]
                end = first[a + step] if a + step < len(first) else len(key)
                low = np.minimum.reduceat(pairs[at[own[0] : end]], own - own[0], axis=0)
                sig = pa.ListArray.from_arrays(pa.array(np.arange(len(own) + 1, dtype=np.int32) * family.k), pa.array(low.ravel()))
                yield pa.RecordBatch.from_arrays([batch.column(0).take(pa.array(key[own] // shape.levels)), pa.array(key[own] % shape.levels, pa.int32()), sig], names=["set_id", "level", "sig"])

    return bins.select("set_id", shape.level_for(n).alias("own"), "bins").mapInArrow(walk, "set_id bigint, level int, sig array<bigint>")


def bins_apply(bins: DataFrame | None, updates: DataFrame, shape: BinShape) -> DataFrame:
    """Counters after the updates: constant work for each, summed before the shuffle."""
    x = F.col("element")
    moved = updates.select("set_id", shape.level(x).alias("level"), shape.bin(x).alias("bin"), F.col("op").cast("bigint").alias("cnt"))
    every = moved if bins is None else bins.unionByName(moved)
    return every.groupBy("set_id", "level", "bin").agg(F.sum("cnt").alias("cnt")).where("cnt <> 0")


def bins_sizes(bins: DataFrame) -> DataFrame:
    return bins.groupBy("set_id").agg(F.sum("cnt").alias("n"))


def bins_level(bins: DataFrame, levels: DataFrame) -> DataFrame:
    """(set_id, element): taken bins of the level that ``levels`` (set_id, level) names for each set."""
    return bins.join(levels, ["set_id", "level"]).select("set_id", F.col("bin").cast("bigint").alias("element"))


def bins_signature(bins: DataFrame, family: HashFamily, shape: BinShape) -> DataFrame:
    """(set_id, sig): minima over the taken bins of each set's own level."""
    levels = bins_sizes(bins).select("set_id", shape.level_for(F.col("n")).alias("level"))
    return signatures(bins_level(bins, levels), family)


def bins_level_signatures(bins: DataFrame, family: HashFamily, shape: BinShape) -> DataFrame:
    """(set_id, level, sig) at each set's own level and both beside it, so that similar sets on two sides of a level's bound meet at one."""
    if "bins" in bins.columns:
        return _level_signatures_of_sets(bins, family, shape)
    own = bins_sizes(bins).select("set_id", shape.level_for(F.col("n")).alias("own"))
    near = own.select("set_id", F.explode(F.array_distinct(F.transform(F.sequence(F.col("own") - 1, F.col("own") + 1), lambda x: F.least(F.greatest(x, F.lit(0)), F.lit(shape.levels - 1))))).alias("level"))
    taken = bins.join(near, ["set_id", "level"]).select((F.col("set_id") * shape.levels + F.col("level")).alias("set_id"), F.col("bin").cast("bigint").alias("element"))
    sigs = signatures(taken, family)
    return sigs.select(F.floor(F.col("set_id") / shape.levels).cast("bigint").alias("set_id"), F.pmod("set_id", F.lit(shape.levels)).cast("int").alias("level"), "sig")


def bins_similarity(bins: DataFrame, pairs: DataFrame, shape: BinShape, family: HashFamily | None = None) -> DataFrame:
    """(a, b, est) on the level of each pair's larger set: by signatures, or exactly over the bins without ``family``."""
    n = bins_sizes(bins)
    sized = pairs.select("a", "b").join(n.select(F.col("set_id").alias("a"), F.col("n").alias("n_a")), "a").join(n.select(F.col("set_id").alias("b"), F.col("n").alias("n_b")), "b")
    asked = sized.select("a", "b", shape.level_for(F.greatest("n_a", "n_b")).alias("level"))
    if family is None:
        mine = bins.select(F.col("set_id").alias("a"), "level", "bin")
        theirs = bins.select(F.col("set_id").alias("b"), "level", "bin")
        per = bins.groupBy("set_id", "level").agg(F.count(F.lit(1)).alias("m"))
        shared = asked.join(mine, ["a", "level"]).join(theirs, ["b", "level", "bin"]).groupBy("a", "b").agg(F.count(F.lit(1)).alias("shared"))
        both = asked.join(per.select(F.col("set_id").alias("a"), "level", F.col("m").alias("m_a")), ["a", "level"], "left").join(per.select(F.col("set_id").alias("b"), "level", F.col("m").alias("m_b")), ["b", "level"], "left")
        zero = F.lit(0).cast("bigint")
        full = both.join(shared, ["a", "b"], "left").select("a", "b", *[F.coalesce(c, zero).alias(c) for c in ("shared", "m_a", "m_b")])
        return full.select("a", "b", jaccard(F.col("shared"), F.col("m_a"), F.col("m_b")).alias("est"))
    from .similarity import sig_similarity

    wanted = asked.select(F.col("a").alias("set_id"), "level").union(asked.select("b", "level")).distinct()
    taken = bins.join(wanted, ["set_id", "level"]).select(F.struct("set_id", "level").alias("set_id"), F.col("bin").cast("bigint").alias("element"))
    sigs = taken.groupBy("set_id").agg(F.array(*[F.min(family.pair(i, F.col("element"))) for i in range(family.k)]).alias("sig")).select("set_id.set_id", "set_id.level", "sig")
    one = asked.join(sigs.select(F.col("set_id").alias("a"), "level", F.col("sig").alias("x")), ["a", "level"]).join(sigs.select(F.col("set_id").alias("b"), "level", F.col("sig").alias("y")), ["b", "level"])
    return one.select("a", "b", sig_similarity(F.col("x"), F.col("y")).alias("est"))


def bins_eager_init(bins: DataFrame, family: HashFamily) -> DataFrame:
    """(set_id, level, sig): minima of every level, kept beside the counters."""
    return bins.groupBy("set_id", "level").agg(F.array(*[F.min(family.pair(i, F.col("bin").cast("bigint"))) for i in range(family.k)]).alias("sig"))


def bins_eager_apply(bins: DataFrame, sigs: DataFrame, updates: DataFrame, shape: BinShape, family: HashFamily) -> tuple[DataFrame, DataFrame]:
    """(counters, signatures) after a batch: the levels it touched are read again from their own bins, without any recovery."""
    after = bins_apply(bins, updates, shape)
    touched = updates.select("set_id", shape.level(F.col("element")).alias("level")).distinct()
    fresh = bins_eager_init(after.join(touched, ["set_id", "level"], "left_semi"), family)
    return after, sigs.join(touched, ["set_id", "level"], "left_anti").unionByName(fresh)


def bins_guarantee(r1: float, r2: float, gamma: float, delta: float) -> dict[str, float]:
    """Sensitivity of the one-function bin sketch: p1, p2 and the probability with which they hold."""
    return {"p1": (1 - gamma) * r1, "p2": 6 * r2 / (delta * (1 - gamma * sqrt(2 * r1) / 5)), "probability": 1 - delta}


def bins_required_c2(r1: float, gamma: float, delta: float) -> float:
    """Order of the bins needed for the guarantee (its constant left out)."""
    return 1 / (gamma**4 * delta**5 * r1**2)
