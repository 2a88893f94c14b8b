"""Cost measures over fault logs, and the bounds they are held against."""

from __future__ import annotations

from math import log2

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def memory_words(kind: str, k: int, reserve: int = 1, bins: int = 0, universe_bits: int = 32) -> int:
    """Words of one set's sketch at most: reserve (pairs and limits), rebuild, bins or eager_bins."""
    return {"reserve": k * (reserve + 1), "rebuild": k, "bins": bins * (universe_bits + 1), "eager_bins": bins * (universe_bits + 1) + k * (universe_bits + 1)}[kind]


def update_cost(k: int, reserve: int, hash_cost: float = 1.0, alpha: float = 1.0) -> float:
    """Unit cost of an update without a fault."""
    return alpha * k * (log2(max(2, reserve)) + hash_cost)


def amortized_cost(updates: DataFrame, faults: DataFrame, k: int, reserve: int) -> DataFrame:
    """(set_id, seq, credit, paid): every update leaves three unit costs as credit and a fault takes its set's size times the unit.

    ``credit`` is the running balance; where it stays at zero or more, four unit costs an update pay for everything.
    """
    unit = update_cost(k, reserve)
    cost = faults.groupBy("set_id", "seq").agg(F.sum("size_after").alias("read"))
    rows = updates.select("set_id", "seq").join(cost, ["set_id", "seq"], "left").withColumn("read", F.coalesce("read", F.lit(0)))
    w = Window.partitionBy("set_id").orderBy("seq").rowsBetween(Window.unboundedPreceding, 0)
    change = F.lit(3 * unit) - F.col("read") * unit
    return rows.select("set_id", "seq", F.sum(change).over(w).alias("credit"), (unit + F.col("read") * unit).alias("paid"))


def fault_counts(replayed: DataFrame) -> DataFrame:
    """(sets, ops, faults, reread, mean_faults) over replay results."""
    return replayed.agg(F.count(F.lit(1)).alias("sets"), F.sum("ops").alias("ops"), F.sum("faults").alias("faults"), F.sum("reread").alias("reread"), F.avg("faults").alias("mean_faults"))


def recovery_volume(log: DataFrame) -> DataFrame:
    """(recoveries, elements): how often sets were read again and how much was read."""
    return log.agg(F.count(F.lit(1)).alias("recoveries"), F.coalesce(F.sum("size_after"), F.lit(0)).alias("elements"))


def speedup(times: DataFrame) -> DataFrame:
    """From (n, sketch, seconds): one row for each n with both times and the ratio of rebuild to reserve."""
    wide = times.groupBy("n").pivot("sketch", ["rebuild", "reserve"]).agg(F.avg("seconds"))
    return wide.withColumn("speedup", F.try_divide("rebuild", "reserve"))


def fault_bound(deleted: int, n: int, reserve: int, eps: float = 0.0) -> float:
    """Bound on the chance that all of a slot's reserve lies among ``deleted`` of ``n`` elements."""
    return 0.0 if deleted < reserve else min(1.0, (1 + eps) * (deleted / n) ** reserve)


def fault_rate(n: int, deleted: int, reserve: int, trials: int = 4000, seed: int = 1, kind: str = "affine") -> float:
    """Observed share of slots whose least pairs all lie among the deleted elements."""
    import numpy as np

    from ..functions.hashing import HashFamily

    x = np.random.default_rng(seed).choice(2**31, n, replace=False).astype(np.int64)
    p = HashFamily(kind, trials, seed).pairs_numpy(x)
    least = np.argpartition(p, reserve - 1, axis=0)[:reserve]
    return float((least < deleted).all(0).mean())


def survival(replayed: DataFrame) -> DataFrame:
    """(set_id, n, first_fault, survived): whether a set of n inserts lasted n/4 deletions; for insert-then-delete streams."""
    first = F.array_min(F.transform("log", lambda x: x["seq"]))
    n = F.col("ops") / 2
    return replayed.select("set_id", n.alias("n"), first.alias("first_fault"), F.coalesce(first > n + n / 4, F.lit(True)).alias("survived"))


def cost_table(spark: SparkSession, k: int, universe_bits: int, bins: int, n: int, r1: float, r2: float, gamma: float, delta: float) -> DataFrame:
    """Bounds of the three global sketches with the given parameters (constants left out)."""
    from .bins import bins_guarantee

    g = bins_guarantee(r1, r2, gamma, delta)
    rows = [
        ("rebuild", float(k), float(k * n), False, float(k), r1, r2, 1.0),
        ("bins", float(bins * universe_bits), 1.0, False, float(bins * k), g["p1"], g["p2"], g["probability"]),
        ("reserve", float(k * universe_bits), float(k * universe_bits), True, float(k), r1, r2, 1.0),
    ]
    return spark.createDataFrame(rows, "sketch string, space double, update_cost double, amortized boolean, query_cost double, p1 double, p2 double, probability double")


def cost_rows(sets: DataFrame, k: int, universe_bits: int, bins: int, r1: float, r2: float, gamma: float, delta: float) -> DataFrame:
    """The same for each set of (set_id, n): three rows with its set_id."""
    one = cost_table(sets.sparkSession, k, universe_bits, bins, 1, r1, r2, gamma, delta).collect()  # three rows
    bounds = F.inline(F.array(*[F.struct(*[F.lit(v).alias(c) for c, v in r.asDict().items()]) for r in one]))
    by_size = F.when(F.col("sketch") == "rebuild", F.col("update_cost") * F.col("n")).otherwise(F.col("update_cost"))
    return sets.select("set_id", "n", bounds).withColumn("update_cost", by_size).drop("n")


def observed_faults(sets: DataFrame, reserves: list[int], family) -> DataFrame:
    """(share, reserve, observed, bound, slots) over sets (e, gone): by tenths of the share of elements that go, how often all of a slot's least pairs are
    among them, and the mean bound on it. Sets smaller than the reserve are left out."""
    import numpy as np
    import pyarrow as pa

    from .cells import flat

    def count(batches):
        for batch in batches:
            (values, offsets), (gone, _) = flat(batch.column(0)), flat(batch.column(1))
            out = []
            for a, b in zip(offsets[:-1], offsets[1:]):
                n, lost = int(b - a), np.asarray(gone[a:b], bool)
                order = np.argsort(family.pairs_numpy(values[a:b]), axis=0)[: max(reserves)]
                all_lost = np.logical_and.accumulate(lost[order], axis=0)
                share, deleted = int(10 * lost.sum() / n), int(lost.sum())
                out += [(share, ell, int(all_lost[ell - 1].sum()), fault_bound(deleted, n, ell), family.k) for ell in reserves if ell <= n]
            columns = list(zip(*out)) if out else [[]] * 5
            kinds = [pa.int32(), pa.int32(), pa.int64(), pa.float64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, kinds)], names=["tenth", "reserve", "hits", "bound", "slots"])

    rows = sets.select("e", "gone").mapInArrow(count, "tenth int, reserve int, hits bigint, bound double, slots bigint")
    return rows.groupBy("tenth", "reserve").agg((F.sum("hits") / F.sum("slots")).alias("observed"), F.avg("bound").alias("bound"), F.sum("slots").alias("slots"))


def minwise_rates(sets: DataFrame, kinds: list[str], trials: int, seed: int = 1) -> DataFrame:
    """(family, observed, ideal) over sets (e), of three elements or more: how often a set's first two elements are its least, and how often they should be."""
    import numpy as np
    import pyarrow as pa

    from ..functions.hashing import HashFamily
    from .cells import flat

    def count(batches):
        families = {kind: HashFamily(kind, trials, seed, degree=3) for kind in kinds}
        for batch in batches:
            values, offsets = flat(batch.column(0))
            out = []
            every, at = np.unique(values, return_inverse=True)
            for kind, family in families.items():
                pairs = family.pairs_numpy(every)
                for a, b in zip(offsets[:-1], offsets[1:]):
                    p = pairs[at[a:b]]
                    out.append((kind, float((p[:2].max(0) < p[2:].min(0)).mean()), 2 / ((b - a) * (b - a - 1))))
            columns = list(zip(*out)) if out else [[]] * 3
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, (pa.string(), pa.float64(), pa.float64()))], names=["family", "observed", "ideal"])

    rows = sets.where("size(e) >= 3").select("e").mapInArrow(count, "family string, observed double, ideal double")
    return rows.groupBy("family").agg(F.avg("observed").alias("observed"), F.avg("ideal").alias("ideal"))
