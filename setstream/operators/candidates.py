"""Candidate pairs by banding, their verification and quality."""

from __future__ import annotations

from math import log

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import cells
from .similarity import estimate_similarity, exact_pairs, exact_similarity, prefix_pairs, sig_similarity


def band_probability(s: float, bands: int, rows: int) -> float:
    return 1 - (1 - s**rows) ** bands


def band_probability_column(s: Column, bands: Column, rows: Column) -> Column:
    return 1 - F.pow(1 - F.pow(s, rows), bands)


def choose_bands(r1: float, p1: float = 0.8, budget: int = 2100, r2: float | None = None) -> tuple[int, int]:
    """(bands, rows) within the budget that reach ``p1`` at similarity ``r1`` and admit least at ``r2`` (default: half of it)."""
    r2 = r1 / 2 if r2 is None else r2
    best = None
    for rows in range(1, budget + 1):
        hit = r1**rows
        bands = 1 if hit >= p1 else -int(-log(1 - p1) // log(1 - hit)) if hit > 1e-12 else budget + 1
        while bands <= budget and band_probability(r1, bands, rows) < p1:
            bands += 1
        if bands * rows > budget:
            break
        key = (band_probability(r2, bands, rows), bands * rows)
        if best is None or key < best[0]:
            best = (key, (bands, rows))
    if best is None:
        raise ValueError("no banding within the budget reaches the probability")
    return best[1]


#: Sets of a bucket above which its join is split over tasks.
MAX_BUCKET = 10_000


def band_keys(sigs: DataFrame, bands: int, rows: int, text: bool = False) -> DataFrame:
    """(set_id, band, key): one row for each band. If signatures have a ``level``, only those of equal levels have equal keys. ``text`` gives keys that SQL can make; otherwise 64-bit hashes, whose rare
    collisions only add candidates."""

    def key(i: int) -> Column:
        part = F.slice("sig", i * rows + 1, rows)
        if "level" in sigs.columns:
            return F.xxhash64(F.lit(i), "level", part)
        return F.array_join(part.cast("array<string>"), "-") if text else F.xxhash64(F.lit(i), part)

    keys = F.array(*[key(i) for i in range(bands)])
    return sigs.where("sig is not null").select("set_id", F.posexplode(keys).alias("band", "key"))


def collapse_identical(sigs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(one signature row for each distinct signature, membership (set_id, leader)). Copies are the largest buckets."""
    named = sigs.where("sig is not null").withColumn("h", F.xxhash64("sig")).withColumn("h2", F.xxhash64(F.lit(7), "sig"))
    leaders = named.groupBy("h", "h2").agg(F.min("set_id").alias("leader"))
    membership = named.select("set_id", "h", "h2").join(leaders, ["h", "h2"]).select("set_id", "leader")
    kept = sigs.join(leaders.select(F.col("leader").alias("set_id")), "set_id", "left_semi")
    return kept, membership


def expand_pairs(pairs: DataFrame, membership: DataFrame) -> DataFrame:
    """Pairs of leaders as pairs of all their sets, and pairs of copies."""
    m = membership
    a, b = m.select(F.col("leader").alias("a"), F.col("set_id").alias("x")), m.select(F.col("leader").alias("b"), F.col("set_id").alias("y"))
    across = pairs.select("a", "b").join(a, "a").join(b, "b").select("x", "y")
    within = a.join(b, F.col("a") == F.col("b")).where("x < y").select("x", "y")
    return across.union(within).select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct()


def candidate_pairs(sigs: DataFrame, bands: int, rows: int, max_bucket: int | None = MAX_BUCKET, hot: str = "salt", text: bool = False) -> DataFrame:
    """(a, b), a < b: sets that agree on a whole band.

    Buckets over ``max_bucket`` sets: 'salt' splits their join over tasks and keeps every pair; 'star' links every set of the
    bucket to its least one only (a later verification or component step reaches the others); 'drop' leaves the bucket out. Without a bound no
    bucket is split.
    """
    keys = band_keys(sigs, bands, rows, text)

    def joined(k: DataFrame) -> DataFrame:
        return k.select(F.col("set_id").alias("a"), "band", "key").join(k.select(F.col("set_id").alias("b"), "band", "key"), ["band", "key"]).where("a < b").select("a", "b")

    if max_bucket is None:
        return joined(keys).distinct()
    sizes = keys.groupBy("band", "key").agg(F.count(F.lit(1)).alias("n"), F.min("set_id").alias("least"))
    large = sizes.where(F.col("n") > max_bucket)
    calm = joined(keys.join(large.select("band", "key"), ["band", "key"], "left_anti"))
    if hot == "drop":
        return calm.distinct()
    busy = keys.join(large, ["band", "key"])
    if hot == "star":
        return calm.union(busy.where("set_id > least").select(F.col("least").alias("a"), F.col("set_id").alias("b"))).distinct()
    parts = F.ceil(F.col("n") / max_bucket).cast("int")
    left = busy.select(F.col("set_id").alias("a"), "band", "key", F.pmod(F.xxhash64("set_id"), parts).cast("int").alias("salt"))
    right = busy.select(F.col("set_id").alias("b"), "band", "key", F.explode(F.sequence(F.lit(0), parts - 1)).alias("salt"))
    return calm.union(left.join(right, ["band", "key", "salt"]).where("a < b").select("a", "b")).distinct()


def verify_pairs(candidates: DataFrame, sigs: DataFrame, lam: float) -> DataFrame:
    """(a, b, est): candidates whose estimate reaches ``lam``."""
    return estimate_similarity(sigs, candidates).where(F.col("est") >= lam)


def verify_exact(candidates: DataFrame, members: DataFrame, lam: float) -> DataFrame:
    """(a, b, exact): candidates whose similarity reaches ``lam``."""
    return exact_similarity(members, candidates).where(F.col("exact") >= lam)


class Copies:
    """A collection with each distinct set once. Whatever depends on sets alone, signatures, candidates, similarity, is found among ``leaders`` (the least ids)
    and holds for all sets equal to them. ``members``: (set_id, element), or (set_id, e) with each set in one row, its elements once and in order."""

    def __init__(self, members: DataFrame):
        from ..sources.store import written

        # A fixed number of partitions: a set may be small, what is made of it is not.
        each = (members if "e" in members.columns else cells.arrays(members)).repartition(int(members.sparkSession.conf.get("spark.sql.shuffle.partitions")), "e")
        grouped = each.groupBy("e").agg(F.min("set_id").alias("leader"), F.collect_list("set_id").alias("ids"))
        self.rows = written(grouped, "copies")
        self.sets = self.rows.select(F.col("leader").alias("set_id"), "e")
        self.leaders = self.sets.select("set_id", F.explode("e").alias("element"))
        self.sizes = self.rows.select(F.col("leader").alias("set_id"), F.size("ids").cast("bigint").alias("copies"))
        self.membership = self.rows.select("leader", F.explode("ids").alias("set_id"))

    def exact(self, pairs: DataFrame) -> DataFrame:
        """(a, b, exact) of pairs of leaders, from both sets' arrays: a pair is one row, whatever its sets hold."""
        a, b = (self.sets.select(F.col("set_id").alias(x), F.col("e").alias(f"e_{x}")) for x in "ab")
        both = pairs.select("a", "b").join(a, "a").join(b, "b")
        shared = F.size(F.array_intersect("e_a", "e_b"))
        return both.select("a", "b", (shared / (F.size("e_a") + F.size("e_b") - shared)).alias("exact"))

    def expand(self, found: DataFrame) -> DataFrame:
        """(a, b, exact) of all sets: the leaders' pairs between their copies, and the pairs of copies. No pair is shuffled afterwards."""
        x, y = self.membership.toDF("a", "x"), self.membership.toDF("b", "y")
        across = found.join(x, "a").join(y, "b").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "exact")
        first, second = self.membership.toDF("leader", "a"), self.membership.toDF("leader", "b")
        return across.unionByName(first.join(second, "leader").where("a < b").select("a", "b", F.lit(1.0).alias("exact")))

    def pairs_within(self) -> int:
        return self.sizes.agg(F.coalesce(F.sum(F.expr("copies * (copies - 1) div 2")), F.lit(0))).first()[0]

    def weighed(self, pairs: DataFrame) -> DataFrame:
        """Pairs of leaders with the number ``w`` of pairs of sets that each stands for."""
        a, b = (self.sizes.toDF(x, f"w_{x}") for x in "ab")
        return pairs.join(a, "a").join(b, "b").select("a", "b", (F.col("w_a") * F.col("w_b")).alias("w"))


def exact_pairs_of_copies(members: DataFrame, lam: float) -> DataFrame:
    """``exact_pairs`` of a collection with copies: prefixes are joined, and pairs verified, between distinct sets."""
    copies = Copies(members)
    return copies.expand(copies.exact(prefix_pairs(copies.leaders, lam)).where(F.col("exact") >= lam))


def exact_pairs_in_cells(members: DataFrame, lam: float) -> DataFrame:
    """``exact_pairs`` of many small sets whose elements are much alike in frequency, so that prefixes meet nearly as often as sets: distinct sets meet in cells, where
    pairs are counted and never shuffled."""
    copies = Copies(members)
    return copies.expand(cells.similar(copies.sets, lam, kept=True))


def quality_of_copies(copies: Copies, reported: DataFrame, lam: float) -> DataFrame:
    """``quality`` of reported pairs of leaders against all pairs of similarity ``lam``, counted in sets: equal sets are reported and true."""
    truth = copies.exact(prefix_pairs(copies.leaders, lam)).where(F.col("exact") >= lam)
    r, t = copies.weighed(reported).withColumn("r", F.lit(1)), copies.weighed(truth).withColumn("t", F.lit(1)).withColumnRenamed("w", "w_t")
    w = F.coalesce("w", "w_t")
    count = lambda what: F.coalesce(F.sum(F.when(F.expr(what), w)), F.lit(0))
    c = r.join(t, ["a", "b"], "full").agg(count("r = 1 and t = 1").alias("tp"), count("r = 1 and t is null").alias("fp"), count("r is null and t = 1").alias("fn"))
    m = copies.sizes.agg(F.coalesce(F.sum("copies"), F.lit(0))).first()[0]
    c = c.withColumn("tp", F.col("tp") + F.lit(copies.pairs_within()))
    return _measures(c.withColumn("tn", F.lit(m * (m - 1) // 2).cast("bigint") - F.col("tp") - F.col("fp") - F.col("fn")))


def banded_quality(copies: Copies, lam: float, sketches: dict[str, tuple[DataFrame, int, list[tuple[int, int]]]]) -> DataFrame:
    """(sketch, bands, rows) with the measures of ``quality``: for each sketch the best banding of its grid by f1, ties to fewer rows a band. ``sketches``: signatures
    of the leaders, at levels or not, their slots, and bandings. Pairs are compared where blocks of distinct sets meet; none is joined or shuffled."""
    sets = copies.sets.join(copies.sizes, "set_id")
    for name, (sigs, _, _) in sketches.items():
        level = F.col("level").cast("int") if "level" in sigs.columns else F.lit(0)
        # Within a slot pairs are equal where their lower halves are, the elements.
        sig = F.transform("sig", lambda x: (x.bitwiseAND(F.lit(0xFFFFFFFF)) - F.lit(1 << 31)).cast("int")).alias("sig")
        rows = sigs.where("sig is not null").select("set_id", level.alias("level"), sig).groupBy("set_id").agg(F.collect_list(F.struct("level", "sig")).alias(name))
        sets = sets.join(rows, "set_id", "left")
    counts = cells.banded(sets, lam, {name: (k, grid) for name, (_, k, grid) in sketches.items()})
    m = copies.sizes.agg(F.coalesce(F.sum("copies"), F.lit(0))).first()[0]
    tp, fp, fn = F.col("tp"), F.col("returned") - F.col("tp"), F.col("effective") - F.col("tp")
    tn = F.lit(m * (m - 1) // 2).cast("bigint") - tp - fp - fn
    every = _measures(counts.select("sketch", "bands", "rows", "tp", fp.alias("fp"), fn.alias("fn"), tn.alias("tn")), ["sketch", "bands", "rows"])
    best = Window.partitionBy("sketch").orderBy(F.desc_nulls_last("f1"), "rows")
    return every.withColumn("best", F.row_number().over(best)).where("best = 1").drop("best")


def similarity_join(members: DataFrame, lam: float, family, p1: float = 0.95, budget: int = 512) -> DataFrame:
    """(a, b, exact): pairs of similarity ``lam`` or more, found by banding and verified exactly."""
    from .similarity import signatures

    bands, rows = choose_bands(lam, p1, min(budget, family.k))
    return verify_exact(candidate_pairs(signatures(members, family), bands, rows), members, lam)


def similar_to(sigs: DataFrame, query_sigs: DataFrame, bands: int, rows: int, lam: float) -> DataFrame:
    """(query_id, set_id, est): neighbours of the query sets through their buckets."""
    mine = band_keys(sigs, bands, rows)
    asked = band_keys(query_sigs, bands, rows).withColumnRenamed("set_id", "query_id")
    met = mine.join(asked, ["band", "key"]).where("set_id <> query_id").select("query_id", "set_id").distinct()
    a = query_sigs.select(F.col("set_id").alias("query_id"), F.col("sig").alias("x"))
    scored = met.join(a, "query_id").join(sigs.select("set_id", F.col("sig").alias("y")), "set_id")
    return scored.select("query_id", "set_id", sig_similarity(F.col("x"), F.col("y")).alias("est")).where(F.col("est") >= lam)


def top_similar(sigs: DataFrame, pairs: DataFrame, n: int) -> DataFrame:
    """(set_id, rank, other, est): the ``n`` most similar partners of each set among ``pairs``."""
    est = estimate_similarity(sigs, pairs)
    return _best(est.select(F.col("a").alias("set_id"), F.col("b").alias("other"), "est").union(est.select("b", "a", "est")), n)


def top_similar_of_all(sigs: DataFrame, n: int) -> DataFrame:
    """The same among all pairs: cells of sets send each set's best partners alone on."""
    return _best(cells.nearest(sigs, n), n)


def _best(both: DataFrame, n: int) -> DataFrame:
    w = Window.partitionBy("set_id").orderBy(F.desc("est"), "other")
    return both.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= n).select("set_id", "rank", "other", "est")


def choose_threshold(members: DataFrame, grid: list[float], max_share: float = 0.04, dense: bool = False) -> DataFrame:
    """(lam, pairs, share, fits) for each threshold of the grid: share of all pairs that reach it. ``dense``: for collections of which most sets
    share elements; pairs are counted where blocks of sets meet, and never joined."""
    m = members.select("set_id").distinct().agg(F.count(F.lit(1)).alias("m"))
    if dense:
        # As from the join, no rows where no pair reaches the least threshold.
        counted = cells.reached(members, grid).withColumn("most", F.max("pairs").over(Window.partitionBy(F.lit(0)))).where("most > 0").drop("most")
    else:
        exact = exact_pairs(members, min(grid))
        lams = F.explode(F.array(*[F.lit(float(x)) for x in grid])).alias("lam")
        counted = exact.select("exact", lams).groupBy("lam").agg(F.count(F.when(F.col("exact") >= F.col("lam"), 1)).alias("pairs"))
    share = F.col("pairs") / (F.col("m") * (F.col("m") - 1) / 2)
    return counted.join(F.broadcast(m)).select("lam", "pairs", share.alias("share"), (share <= max_share).alias("fits"))


def confusion(reported: DataFrame, truth: DataFrame, m: int) -> DataFrame:
    """(tp, fp, fn, tn) of reported pairs against true ones, among ``m`` sets."""
    r, t = reported.select("a", "b").distinct().withColumn("r", F.lit(1)), truth.select("a", "b").distinct().withColumn("t", F.lit(1))
    c = r.join(t, ["a", "b"], "full").agg(F.count(F.when(F.expr("r = 1 and t = 1"), 1)).alias("tp"), F.count(F.when(F.expr("r = 1 and t is null"), 1)).alias("fp"), F.count(F.when(F.expr("r is null and t = 1"), 1)).alias("fn"))
    return c.withColumn("tn", F.lit(m * (m - 1) // 2).cast("bigint") - F.col("tp") - F.col("fp") - F.col("fn"))


def quality(reported: DataFrame, truth: DataFrame, m: int) -> DataFrame:
    """Confusion counts with precision, recall, f1 (null where undefined), effective and returned pairs."""
    return _measures(confusion(reported, truth, m))


def _measures(counts: DataFrame, by: list[str] | None = None) -> DataFrame:
    tp, fp, fn = F.col("tp"), F.col("fp"), F.col("fn")
    ratio = lambda n, d: F.try_divide(n.cast("double"), d.cast("double"))
    return counts.select(
        *(by or []), "tp", "fp", "fn", "tn",
        F.round(ratio(tp, tp + fp), 9).alias("precision"), F.round(ratio(tp, tp + fn), 9).alias("recall"), F.round(ratio(2 * tp, 2 * tp + fp + fn), 9).alias("f1"),
        (tp + fn).alias("effective"), (tp + fp).alias("returned"),
    )


def tune_bands(sigs: DataFrame, truth: DataFrame, m: int, grid: list[tuple[int, int]]) -> DataFrame:
    """Quality for each (bands, rows) of the grid, best f1 first; for sketches without a closed form."""
    out = None
    for bands, rows in grid:
        one = quality(candidate_pairs(sigs, bands, rows), truth, m).withColumn("bands", F.lit(bands)).withColumn("rows", F.lit(rows))
        out = one if out is None else out.unionByName(one)
    return out.orderBy(F.desc_nulls_last("f1"))


def sensitivity(kind: str, r1: float, r2: float, bands: int = 1, rows: int = 1, gamma: float = 0.1, delta: float = 0.1) -> dict[str, float]:
    """(p1, p2, probability) of a family: 'signature' (one function, or banded) or 'bins'."""
    if kind == "bins":
        from .bins import bins_guarantee

        return bins_guarantee(r1, r2, gamma, delta)
    return {"p1": band_probability(r1, bands, rows), "p2": band_probability(r2, bands, rows), "probability": 1.0}
