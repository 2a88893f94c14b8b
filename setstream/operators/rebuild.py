"""The rebuild baseline as DataFrame operations: signatures alone; losing a minimum reads the set again."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import HashFamily
from .similarity import signatures
from .streams import net


def rebuild_init(members: DataFrame, family: HashFamily) -> DataFrame:
    """(set_id, sig). With k times the reserve functions it takes a reserve sketch's memory."""
    return signatures(members, family)


def rebuild_apply(sigs: DataFrame, updates: DataFrame, members_after: DataFrame, family: HashFamily) -> tuple[DataFrame, DataFrame]:
    """(signatures, faulty set ids) after a netted batch: inserted pairs enter the minima; a deleted pair that is one is a fault."""
    empty = F.array().cast("array<bigint>")
    last = net(updates.repartition("set_id")).groupBy("set_id").agg(
        F.collect_list(F.when(F.col("op") == 1, F.col("element"))).alias("put"), F.collect_list(F.when(F.col("op") == -1, F.col("element"))).alias("out")
    )
    joined = sigs.join(last, "set_id", "full").withColumn("put", F.coalesce("put", empty)).withColumn("out", F.coalesce("out", empty))

    def stale(i: int):
        return F.exists("out", lambda x: family.pair(i, x) == F.element_at("sig", i + 1))

    def least(i: int):
        return F.least(F.try_element_at("sig", F.lit(i + 1)), F.array_min(F.transform("put", lambda x: family.pair(i, x))))

    lost = F.lit(False)
    for i in range(family.k):
        lost = lost | stale(i)
    judged = joined.withColumn("fault", F.coalesce(F.when(F.col("sig").isNotNull(), lost), F.lit(False)))
    kept = judged.where("not fault").select("set_id", F.array(*[least(i) for i in range(family.k)]).alias("sig")).where(F.element_at("sig", 1).isNotNull())
    faulty = judged.where("fault").select("set_id")
    again = signatures(members_after.join(faulty, "set_id", "left_semi"), family)
    return kept.unionByName(again), faulty
