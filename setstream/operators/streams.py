"""Operations on update streams (seq, set_id, element, op): legality, netting, membership, sizes, edges, generators."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

_PAIR = ("set_id", "element")


def split_valid(updates: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(usable updates, quarantine): rows with a null set, element or op, or an op other than +1 and -1, are set aside."""
    good = F.col("set_id").isNotNull() & F.col("element").isNotNull() & F.coalesce(F.col("op").isin(-1, 1), F.lit(False))
    return updates.where(good), updates.where(~good)


def flag_legal(updates: DataFrame) -> DataFrame:
    """Adds ``legal``: the update changes its set. The first one of a pair has to insert, later ones to differ from the one before."""
    w = Window.partitionBy(*_PAIR).orderBy("seq", "op")
    before = F.coalesce(F.lag("op").over(w), F.lit(-1))
    return updates.withColumn("legal", F.col("op") != before)


def legalize(updates: DataFrame) -> DataFrame:
    return flag_legal(updates).where("legal").drop("legal")


def net(updates: DataFrame) -> DataFrame:
    """The last update of each (set, element): what a batch amounts to. One aggregation with partial sums. ``seq`` is at most 2^62 - 1 either way."""
    # Number and direction packed into one BIGINT: its maximum is a hash aggregate, a struct's would sort.
    last = F.max(F.col("seq") * 2 + F.when(F.col("op") == 1, 1).otherwise(0)).alias("l")
    found = updates.groupBy(*_PAIR).agg(last)
    return found.select(F.shiftright("l", 1).alias("seq"), *_PAIR, F.when(F.col("l").bitwiseAND(1) == 1, 1).otherwise(-1).alias("op"))


def members_at(updates: DataFrame, seq: int | None = None) -> DataFrame:
    """Members of every set after the update numbered ``seq`` (default: the last)."""
    upto = updates if seq is None else updates.where(F.col("seq") <= seq)
    return net(upto).where("op = 1").select(*_PAIR)


def sizes(updates: DataFrame) -> DataFrame:
    """(set_id, seq, size) after each legal update."""
    w = Window.partitionBy("set_id").orderBy("seq", "element", "op").rowsBetween(Window.unboundedPreceding, 0)
    return legalize(updates).select("set_id", "seq", F.sum("op").over(w).cast("bigint").alias("size"))


def numbered(rows: DataFrame, key: str, then: str, name: str = "seq", cells: int = 256) -> DataFrame:
    """``rows`` with gapless numbers from 1 in the order of (``key``, ``then``), a BIGINT and unique together. Rows are cut into cells by equal
    ranges of ``key``, each cell is ranked by itself and begins where those before it end: one row for each cell is summed in one place."""
    ends = F.broadcast(rows.agg(F.min(key).alias("_least"), F.max(key).alias("_most")))  # one row
    share = (F.col(key) - F.col("_least")) / (F.col("_most") - F.col("_least") + 1)
    placed = rows.join(ends).withColumn("_cell", F.floor(share * cells).cast("int")).drop("_least", "_most")
    counts = placed.groupBy("_cell").agg(F.count(F.lit(1)).alias("_n"))
    before = F.sum("_n").over(Window.orderBy("_cell").rowsBetween(Window.unboundedPreceding, -1))
    starts = F.broadcast(counts.select("_cell", F.coalesce(before, F.lit(0)).alias("_start")))  # at most ``cells`` rows
    ranked = placed.withColumn("_rank", F.row_number().over(Window.partitionBy("_cell").orderBy(key, then)))
    return ranked.join(starts, "_cell").withColumn(name, (F.col("_start") + F.col("_rank")).cast("bigint")).drop("_cell", "_rank", "_start")


def edge_updates(edges: DataFrame) -> DataFrame:
    """(seq, u, v, op) on edges as updates of the neighbourhoods of both ends."""
    there = edges.select("seq", F.col("u").alias("set_id"), F.col("v").alias("element"), "op")
    back = edges.select("seq", F.col("v").alias("set_id"), F.col("u").alias("element"), "op")
    return there.unionByName(back)


def neighbourhoods(edges: DataFrame, d: int = 1) -> DataFrame:
    """Members at distance exactly ``d`` (1 or 2 steps of self-join) of each left node ``u`` over undirected (u, v) edges."""
    both = edges.select(F.col("u").alias("set_id"), F.col("v").alias("element")).union(edges.select("v", "u")).distinct()
    if d == 1:
        return edges.select(F.col("u").alias("set_id"), F.col("v").alias("element")).distinct()
    reach = edges.select(F.col("u").alias("set_id"), F.col("v").alias("element")).distinct()
    for _ in range(d - 1):
        step = both.select(F.col("set_id").alias("element"), F.col("element").alias("next"))
        reach = reach.join(step, "element").select("set_id", F.col("next").alias("element")).where("set_id <> element").distinct()
    return reach


# Generators. All are deterministic: a row is in if its hash is under a threshold.


def _chance(*keys):
    return F.pmod(F.xxhash64(*keys), F.lit(1 << 30)) / float(1 << 30)


def uniform_sets(spark: SparkSession, sets: int, size: int, universe: int = 1 << 32, seed: int = 1) -> DataFrame:
    """``sets`` sets of about ``size`` elements spread over the universe."""
    x = F.pmod(F.xxhash64("set_id", "i", F.lit(seed)), F.lit(universe - 1))
    every = spark.range(sets).withColumnRenamed("id", "set_id").crossJoin(spark.range(size).withColumnRenamed("id", "i"))
    return every.select("set_id", x.alias("element")).distinct()


def planted_probabilities(j: float, q: float) -> tuple[float, float]:
    """(p1, p2) for which the second set has the first one's expected size and expected similarity ``j``."""
    p1 = 2 * j / (1 + j)
    return p1, q * (1 - p1) / (1 - q)


def planted_pairs(spark: SparkSession, j: float, count: int, universe: int = 1 << 17, q: float = 0.05, seed: int = 1) -> DataFrame:
    """(pair_id, side, element): ``count`` pairs of sets whose expected similarity is ``j``."""
    p1, p2 = planted_probabilities(j, q)
    every = spark.range(count).withColumnRenamed("id", "pair_id").crossJoin(spark.range(universe).withColumnRenamed("id", "element"))
    keys = ("pair_id", "element")
    first = _chance(*keys, F.lit(seed), F.lit(1)) < q
    second = F.when(first, _chance(*keys, F.lit(seed), F.lit(2)) < p1).otherwise(_chance(*keys, F.lit(seed), F.lit(3)) < p2)
    sides = F.array_compact(F.array(F.when(first, F.lit(0)), F.when(second, F.lit(1))))
    return every.where(first | second).select("pair_id", F.explode(sides).alias("side"), "element")


def insert_then_delete(members: DataFrame, seed: int = 1, share: float = 1.0) -> DataFrame:
    """All members inserted in one random order, then a share of them deleted in another."""
    put = F.row_number().over(Window.partitionBy("set_id").orderBy(F.xxhash64("element", F.lit(seed)), "element"))
    out = F.row_number().over(Window.partitionBy("set_id").orderBy(F.xxhash64("element", F.lit(seed + 1)), "element"))
    n = F.count(F.lit(1)).over(Window.partitionBy("set_id"))
    rows = members.select("set_id", "element", put.alias("put"), out.alias("out"), n.alias("n"))
    inserts = rows.select(F.col("put").cast("bigint").alias("seq"), "set_id", "element", F.lit(1).alias("op"))
    deletes = rows.where(F.col("out") <= F.col("n") * share).select((F.col("n") + F.col("out")).cast("bigint").alias("seq"), "set_id", "element", F.lit(-1).alias("op"))
    return inserts.unionByName(deletes)


def mixed_ops(updates: DataFrame, share: float) -> DataFrame:
    """Adds ``is_query``: about ``share`` of the rows ask for the signature instead of updating."""
    return updates.withColumn("is_query", F.pmod(F.xxhash64("seq"), F.lit(100)) < F.lit(round(100 * share)))


def gentle_stream(members: DataFrame, seed: int = 1) -> DataFrame:
    """Inserts; one in ten is undone at once."""
    order = F.row_number().over(Window.partitionBy("set_id").orderBy(F.xxhash64("element", F.lit(seed)), "element")).cast("bigint")
    puts = members.select((2 * order).alias("seq"), "set_id", "element", F.lit(1).alias("op"))
    undone = puts.where(F.pmod(F.xxhash64("set_id", "element", F.lit(seed + 7)), F.lit(10)) == 0)
    return puts.unionByName(undone.select((F.col("seq") + 1).alias("seq"), "set_id", "element", F.lit(-1).alias("op")))
