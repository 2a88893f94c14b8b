"""Signatures from scratch, similarity estimates, exact similarity and their errors."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.hashing import HashFamily
from ..schemas import INFINITE

#: Slots up to which signatures stay columns of one hash aggregate (dearer hashes make longer code); above, a numpy kernel
#: combines partial signatures.
COLUMN_SLOTS = {"affine": 64, "native": 64, "polynomial": 32, "tabulation": 8}


def minhash(members: DataFrame, family: HashFamily, slot: int = 0) -> DataFrame:
    """(set_id, pair): the least pair of one slot."""
    return members.groupBy("set_id").agg(F.min(family.pair(slot, F.col("element"))).alias("pair"))


def signatures(members: DataFrame, family: HashFamily, layout: str = "array") -> DataFrame:
    """Signatures of all sets: (set_id, sig) or, with ``layout='long'``, (set_id, slot, pair). One shuffle, combined before it."""
    if family.k <= COLUMN_SLOTS[family.kind]:
        least = [F.min(family.pair(i, F.col("element"))).alias(f"s{i}") for i in range(family.k)]
        arrays = members.groupBy("set_id").agg(*least).select("set_id", F.array(*[f"s{i}" for i in range(family.k)]).alias("sig"))
    else:
        arrays = _kernel_signatures(members, family)
    if layout == "array":
        return arrays
    return arrays.select("set_id", F.posexplode("sig").alias("slot", "pair"))


def _kernel_signatures(members: DataFrame, family: HashFamily) -> DataFrame:
    """Partial signatures of each batch, then one merge of each set's partials; a giant set is spread over all its input tasks."""

    def fold(ids: np.ndarray, rows: np.ndarray) -> pa.RecordBatch:
        order = np.argsort(ids, kind="stable")
        ids, rows = ids[order], rows[order]
        first = np.flatnonzero(np.r_[True, ids[1:] != ids[:-1]])
        low = np.minimum.reduceat(rows, first, axis=0)
        offsets = pa.array(np.arange(len(first) + 1, dtype=np.int32) * family.k)
        return pa.RecordBatch.from_arrays([pa.array(ids[first]), pa.ListArray.from_arrays(offsets, pa.array(low.ravel()))], names=["set_id", "sig"])

    step = max(1, (1 << 22) // family.k)

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, x = (batch.column(i).to_numpy(zero_copy_only=False).astype(np.int64) for i in (0, 1))
            order = np.argsort(ids, kind="stable")
            for a in range(0, len(ids), step):
                part = order[a : a + step]
                yield fold(ids[part], family.pairs_numpy(x[part]))

    def merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held_ids, held = np.zeros(0, np.int64), np.zeros((0, family.k), np.int64)
        for batch in batches:
            for a in range(0, batch.num_rows, step):
                part = batch.slice(a, step)
                ids = np.concatenate([held_ids, part.column(0).to_numpy(zero_copy_only=False)])
                rows = np.concatenate([held, part.column(1).flatten().to_numpy(zero_copy_only=False).reshape(-1, family.k)])
                last = ids == ids[-1]  # the set may go on
                if (~last).any():
                    yield fold(ids[~last], rows[~last])
                held_ids, held = ids[-1:], rows[last].min(0, keepdims=True)
        if len(held_ids):
            yield fold(held_ids, held)

    schema = "set_id bigint, sig array<bigint>"
    parts = members.select("set_id", "element").mapInArrow(partial, schema)
    return parts.repartition("set_id").sortWithinPartitions("set_id").mapInArrow(merge, schema)


def sig_similarity(a: Column, b: Column, hashes_only: bool = False) -> Column:
    """Share of equal slots; null if either signature is null. Whole pairs are compared unless ``hashes_only``."""
    same = (lambda p, q: F.when(F.shiftright(p, 32) == F.shiftright(q, 32), 1).otherwise(0)) if hashes_only else (lambda p, q: F.when(p == q, 1).otherwise(0))
    return F.aggregate(F.zip_with(a, b, same), F.lit(0), lambda n, x: n + x) / F.size(a)


def estimate_similarity(sigs: DataFrame, pairs: DataFrame) -> DataFrame:
    """(a, b, est) for the given id pairs."""
    left = sigs.select(F.col("set_id").alias("a"), F.col("sig").alias("sig_a"))
    right = sigs.select(F.col("set_id").alias("b"), F.col("sig").alias("sig_b"))
    joined = pairs.select("a", "b").join(left, "a").join(right, "b")
    return joined.select("a", "b", sig_similarity(F.col("sig_a"), F.col("sig_b")).alias("est"))


def jaccard(shared: Column, n_a: Column, n_b: Column) -> Column:
    """Null for two empty sets."""
    return F.when(n_a + n_b > 0, shared / (n_a + n_b - shared))


def exact_similarity(members: DataFrame, pairs: DataFrame) -> DataFrame:
    """(a, b, exact) for the given id pairs; ids without members are empty sets."""
    pairs = pairs.select("a", "b").distinct()
    # Sets in no pair are left out before anything is joined.
    asked = pairs.select(F.explode(F.array("a", "b")).alias("set_id")).distinct()
    members = members.join(asked, "set_id", "left_semi")
    n = members.groupBy("set_id").agg(F.count(F.lit(1)).alias("n"))
    mine = members.select(F.col("set_id").alias("a"), "element")
    theirs = members.select(F.col("set_id").alias("b"), "element")
    shared = pairs.join(mine, "a").join(theirs, ["b", "element"]).groupBy("a", "b").agg(F.count(F.lit(1)).alias("shared"))
    sized = pairs.join(n.select(F.col("set_id").alias("a"), F.col("n").alias("n_a")), "a", "left").join(n.select(F.col("set_id").alias("b"), F.col("n").alias("n_b")), "b", "left")
    zero = F.lit(0).cast("bigint")
    full = sized.join(shared, ["a", "b"], "left").select("a", "b", *[F.coalesce(c, zero).alias(c) for c in ("shared", "n_a", "n_b")])
    return full.select("a", "b", jaccard(F.col("shared"), F.col("n_a"), F.col("n_b")).alias("exact"))


def exact_pairs(members: DataFrame, lam: float, prefix: bool = True) -> DataFrame:
    """(a, b, exact) of all pairs a < b with similarity at least ``lam`` > 0.

    With ``prefix`` only each set's rarest elements are joined: sets of similarity lam share one of the first
    n - ceil(lam n) + 1 elements in order of rarity. Frequent elements, which make joins grow with the square, hardly take
    part; candidates are then counted in full.
    """
    n = members.groupBy("set_id").agg(F.count(F.lit(1)).alias("n"))
    if not prefix:
        sized = members.join(n, "set_id")
        a = sized.select(F.col("set_id").alias("a"), "element", F.col("n").alias("n_a"))
        b = sized.select(F.col("set_id").alias("b"), "element", F.col("n").alias("n_b"))
        fits = (F.col("a") < F.col("b")) & (F.least("n_a", "n_b") >= lam * F.greatest("n_a", "n_b") - 1e-9)
        shared = a.join(b, "element").where(fits).groupBy("a", "b", "n_a", "n_b").agg(F.count(F.lit(1)).alias("shared"))
        return shared.select("a", "b", jaccard(F.col("shared"), F.col("n_a"), F.col("n_b")).alias("exact")).where(F.col("exact") >= lam)
    return exact_similarity(members, prefix_pairs(members, lam)).where(F.col("exact") >= lam)


def prefix_pairs(members: DataFrame, lam: float) -> DataFrame:
    """(a, b): every pair that can reach ``lam`` > 0, since prefixes of its sets meet."""
    n = members.groupBy("set_id").agg(F.count(F.lit(1)).alias("n"))
    frequency = members.groupBy("element").agg(F.count(F.lit(1)).alias("f"))
    order = Window.partitionBy("set_id").orderBy("f", "element")
    ranked = members.join(frequency, "element").join(n, "set_id").withColumn("r", F.row_number().over(order))
    head = ranked.where(F.col("r") <= F.col("n") - F.ceil(F.col("n") * lam - 1e-9) + 1)
    a = head.select(F.col("set_id").alias("a"), "element", F.col("n").alias("n_a"))
    b = head.select(F.col("set_id").alias("b"), "element", F.col("n").alias("n_b"))
    fits = (F.col("a") < F.col("b")) & (F.least("n_a", "n_b") >= lam * F.greatest("n_a", "n_b") - 1e-9)
    return a.join(b, "element").where(fits).select("a", "b").distinct()


def bottom_sketch(members: DataFrame, s: int, family: HashFamily, slot: int = 0) -> DataFrame:
    """(set_id, rank, pair): the s least pairs of one function (the single-function sketch)."""
    w = Window.partitionBy("set_id").orderBy("pair")
    pairs = members.select("set_id", family.pair(slot, F.col("element")).alias("pair"))
    return pairs.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= s).select("set_id", "rank", "pair")


def bottom_similarity(sketch: DataFrame, pairs: DataFrame, s: int) -> DataFrame:
    """(a, b, est): share of the s least pairs of the union that both sketches hold."""
    rows = sketch.groupBy("set_id").agg(F.array_sort(F.collect_list("pair")).alias("p"))
    both = pairs.join(rows.select(F.col("set_id").alias("a"), F.col("p").alias("pa")), "a").join(rows.select(F.col("set_id").alias("b"), F.col("p").alias("pb")), "b")
    least = F.slice(F.array_sort(F.array_union("pa", "pb")), 1, s)
    return both.select("a", "b", (F.size(F.array_intersect(least, F.array_intersect("pa", "pb"))) / F.size(least)).alias("est"))


def rmse(joined: DataFrame, by: list[str], est: str = "est", exact: str = "exact") -> DataFrame:
    """Root mean square error, standard deviation of the errors and their number for each group."""
    error = F.col(est) - F.col(exact)
    return joined.groupBy(*by).agg(F.sqrt(F.avg(error * error)).alias("rmse"), F.stddev_samp(error).alias("error_sd"), F.count(F.lit(1)).alias("pairs"))


def error_slope(errors: DataFrame) -> DataFrame:
    """Slope of log error against log k over rows (k, rmse); near -1/2."""
    return errors.agg(F.regr_slope(F.log("rmse"), F.log("k")).alias("slope"))


def all_pairs(sets: DataFrame, block: int = 4096) -> DataFrame:
    """All id pairs a < b of a collection of any size. The result grows with the square; blocks of about ``block`` ids meet in cells, so
    no side is broadcast. Where only pairs with a shared element count, see ``sharing_pairs``."""
    ids = sets.select("set_id").distinct()
    size = F.broadcast(ids.agg(F.greatest(F.lit(1), F.ceil(F.count(F.lit(1)) / block)).cast("int").alias("blocks")))  # one row
    dealt = ids.crossJoin(size).withColumn("own", F.pmod(F.xxhash64("set_id"), F.col("blocks")).cast("int"))
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other")
    rows = dealt.select(F.col("set_id").alias("a"), F.col("own").alias("x"), other).withColumnRenamed("other", "y")
    columns = dealt.select(F.col("set_id").alias("b"), F.col("own").alias("y"), other).withColumnRenamed("other", "x")
    return rows.join(columns.hint("shuffle_hash"), ["x", "y"]).where("a < b").select("a", "b")


def sharing_pairs(members: DataFrame) -> DataFrame:
    """All id pairs a < b that share an element; every other pair has similarity 0."""
    a, b = members.select(F.col("set_id").alias("a"), "element"), members.select(F.col("set_id").alias("b"), "element")
    return a.join(b, "element").where("a < b").select("a", "b").distinct()


def empty_signature() -> int:
    return INFINITE
