"""Best-fit-decreasing packing of indivisible groups into shards.

Groups are rows of equal text. Sizes are what packing needs, so the driver sees a histogram of size classes and never a
group: all units of one class are alike, and best fit fills the tightest shard with as many of them as it holds before
it moves on. The plan is a list of (class, ranks from-to, shard) runs; executors number the units of each class
and look their run up.

Edge cases: a null text counts as empty (size 16, crc 0) and groups with empty texts; null doc_ids are rows like any
other and sort first; repeated rows are one group; an empty table gives an empty result; extra columns are ignored; a
group larger than a shard's fair share is cut by hash into pieces of about an eighth of that share, since no shard
could hold it and the sizes stay near equal; any other group stays whole.
"""

from __future__ import annotations

import random
from collections.abc import Iterable

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .runtime import discard, materialise, partitions

#: Size classes are exact below this many bytes; above, sizes are rounded up by less than 1/4096. At most
#: 4,096 classes for each power of two exist, whatever the data: the bound of what the driver collects.
EXACT_BELOW = 8192
#: An oversized group is cut into pieces of about this share of a shard.
PIECE = 8


class CapacityTree:
    """Treap of (remaining capacity, bin): finds the tightest bin that still takes a size in logarithmic time."""

    def __init__(self, seed: int = 7):
        self._root = None
        self._random = random.Random(seed)

    def add(self, key: tuple[int, int]) -> None:
        left, right = self._cut(self._root, key)
        self._root = self._join(self._join(left, [key, self._random.random(), None, None]), right)

    def pop_tightest(self, size: int) -> tuple[int, int] | None:
        """Remove and return the bin of least remaining capacity that is at least ``size``."""
        left, right = self._cut(self._root, (size, -1))
        if right is None:
            self._root = left
            return None
        node = right
        while node[2] is not None:
            node = node[2]
        key = node[0]
        self._root = self._join(left, self._without_least(right))
        return key

    def _cut(self, node, key):
        """(keys below ``key``, the others)."""
        if node is None:
            return None, None
        if node[0] < key:
            node[3], right = self._cut(node[3], key)
            return node, right
        left, node[2] = self._cut(node[2], key)
        return left, node

    def _join(self, left, right):
        if left is None or right is None:
            return left or right
        if left[1] > right[1]:
            left[3] = self._join(left[3], right)
            return left
        right[2] = self._join(left, right[2])
        return right

    def _without_least(self, node):
        if node[2] is None:
            return node[3]
        node[2] = self._without_least(node[2])
        return node


def best_fit_decreasing(
    histogram: Iterable[tuple[int, int]], capacity: int, bins: int | None = None
) -> tuple[list[tuple[int, int, int, int]], int] | None:
    """Pack ``(size, count)`` classes into bins of ``capacity``.

    Returns (runs, bins used), a run being (size, first rank, rank after the last, bin). ``bins`` None opens as many as
    needed; otherwise None is returned once they don't suffice. An item above ``capacity`` gets a bin of its own.
    """
    tree, runs, used = CapacityTree(), [], 0
    for size, count in sorted(histogram, reverse=True):
        at = 0
        while at < count:
            found = tree.pop_tightest(size)
            if found is None:
                if bins is not None and used >= bins:
                    return None
                found, used = (max(capacity, size), used), used + 1
            room, which = found
            take = count - at if size == 0 else min(count - at, room // size)
            runs.append((size, at, at + take, which))
            at += take
            tree.add((room - take * size, which))
    return runs, used


def smallest_capacity(histogram: list[tuple[int, int]], bins: int) -> list[tuple[int, int, int, int]]:
    """Runs for the least capacity (of a fourfold-growing slack over the fair share) at which ``bins`` bins suffice."""
    total = sum(s * n for s, n in histogram)
    least = max(-(-total // bins), max((s for s, _ in histogram), default=0))
    slack = 0
    while (found := best_fit_decreasing(histogram, least + slack, bins)) is None:
        slack = max(16, 4 * slack)
    return found[0]


def size_class(size):
    """The packing size of ``size``: itself below ``EXACT_BELOW``, else rounded up to 12 leading bits."""
    step = F.pow(F.lit(2.0), F.floor(F.log2(size.cast("double"))) - 12).cast("long")
    return F.when(size < EXACT_BELOW, size).otherwise(F.ceil(size / F.greatest(step, F.lit(1))) * F.greatest(step, F.lit(1)))


def numbered(df: DataFrame, keys: list[str], spread, order: list, name: str) -> DataFrame:
    """Gapless 0-based numbers within ``keys``, without bringing a key's rows into one task.

    Rows are numbered in (keys, hash of ``spread``) cells and each cell starts where the cells before it end; the
    cells' counts are at most as many as keys times shuffle partitions.
    """
    cells = df.withColumn("_cell", F.pmod(F.xxhash64(*spread), F.lit(partitions(df.sparkSession))))
    counts = cells.groupBy(*keys, "_cell").agg(F.count(F.lit(1)).alias("_n"))
    before = Window.partitionBy(*keys).orderBy("_cell").rowsBetween(Window.unboundedPreceding, -1)
    starts = counts.select(*keys, "_cell", F.coalesce(F.sum("_n").over(before), F.lit(0)).alias("_start"))
    inside = Window.partitionBy(*keys, "_cell").orderBy(*order)
    ranked = cells.withColumn("_rank", F.row_number().over(inside).cast("long") - 1)
    return ranked.join(starts, [*keys, "_cell"]).withColumn(name, F.col("_rank") + F.col("_start")).drop("_cell", "_rank", "_start")


def pack(docs: DataFrame, shards: int | None = 40, capacity: int | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, size, text_crc32, digest, shard, slot) for every row of ``docs``.

    Either ``shards`` (sizes near equal, the least capacity that fits) or ``capacity`` (as few shards as best fit
    decreasing finds) is given.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    base = materialise(
        docs.select(
            F.col(id_col).alias("doc_id"),
            (F.octet_length(text).cast("long") + 16).alias("size"),
            F.crc32(text.cast("binary")).alias("text_crc32"),
            F.substring(F.unhex(F.sha2(text, 256)), 1, 16).alias("digest"),
        ),
        "pack-base",
    )
    spark = base.sparkSession
    total = base.agg(F.sum("size")).first()[0] or 0
    share = capacity or max(1, -(-total // shards))
    groups = base.groupBy("digest").agg(F.sum("size").alias("bytes"))
    # Groups above a share: at most total / share of them, that is as many as shards.
    large = groups.where(F.col("bytes") > share).collect()
    cut = spark.createDataFrame([(bytes(r["digest"]), int(-(-r["bytes"] * PIECE // share))) for r in large], "digest binary, pieces int")
    units = base.join(F.broadcast(cut), "digest", "left").withColumn(
        "piece", F.when(F.col("pieces").isNull(), F.lit(0)).otherwise(F.pmod(F.xxhash64("doc_id"), F.col("pieces")).cast("int"))
    )
    groups = materialise(
        units.groupBy("digest", "piece").agg(F.sum("size").alias("bytes")).withColumn("bytes_class", size_class(F.col("bytes"))),
        "pack-units",
    )
    histogram = [(r["bytes_class"], r["n"]) for r in groups.groupBy("bytes_class").agg(F.count(F.lit(1)).alias("n")).collect()]
    runs = best_fit_decreasing(histogram, capacity)[0] if capacity else smallest_capacity(histogram, shards)
    plan = spark.createDataFrame(runs, "bytes_class long, rank_from long, rank_to long, shard int")
    ranked = numbered(groups, ["bytes_class"], ["digest", "piece"], ["digest", "piece"], "rank")
    where = (F.col("rank") >= F.col("rank_from")) & (F.col("rank") < F.col("rank_to"))
    # As many plan rows as size classes and shards, both bounded: see EXACT_BELOW.
    placed = ranked.join(F.broadcast(plan), "bytes_class").where(where).select("digest", "piece", "shard")
    assigned = materialise(units.join(placed, ["digest", "piece"]).select("doc_id", "size", "text_crc32", "digest", "shard"), "pack-placed")
    for done in (groups, base):
        discard(done)
    return numbered(assigned, ["shard"], ["doc_id"], ["doc_id", "text_crc32", "size"], "slot")
