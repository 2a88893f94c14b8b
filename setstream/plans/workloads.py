"""The experiments, re-expressed on the given tables and on generated sets, at sizes that suit the tables.

Counts (faults, elements read) and accuracy come from here; wall time is measured by ``bench.py``.
"""

from __future__ import annotations

from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor
from functools import reduce

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.encoders import top_dims
from ..functions.hashing import HashFamily
from ..operators import bins as B
from ..operators import candidates as C
from ..operators import cells, costs, streams
from ..operators import reserve as R
from ..operators import similarity as S
from ..operators.replay import kernel, replay
from ..sources import collections as col
from ..sources.store import written
from ..sources.tables import read

SEED = 13


def _union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


def numbered_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges of the thin graph as inserts, numbered in order of their ends (for streams that need an order)."""
    return streams.numbered(col.thin_edges(spark, sf_dir), "u", "v").select("seq", "u", "v", F.lit(1).alias("op"))


def numbered_whole(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges of the whole graph, numbered likewise."""
    return streams.numbered(col.edges(spark, sf_dir), "u", "v").select("seq", "u", "v", F.lit(1).alias("op"))


def fault_grid(updates: DataFrame, ks: list[int], reserves: list[int], kind: str = "reserve") -> DataFrame:
    """(k, reserve, sets, ops, faults, reread, mean_faults) of one stream for each k and reserve size. The stream is made once and kept."""
    out, updates = [], written(updates.select("seq", "set_id", "element", "op"), "stream")
    for k in ks:
        for ell in reserves:
            one = costs.fault_counts(replay(updates, kind, HashFamily.tabulation(k, SEED), ell))
            out.append(one.withColumn("k", F.lit(k)).withColumn("reserve", F.lit(ell)))
    return _union(out)


def returned_parts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(set_id, element, came_back): suppliers' parts, and whether (1 or 0) any line of one was returned."""
    lines = read(spark, sf_dir, "lineitem").where("l_suppkey is not null and l_partkey is not null")
    return lines.groupBy(F.col("l_suppkey").alias("set_id"), F.col("l_partkey").alias("element")).agg(F.coalesce(F.max(F.when(F.col("l_returnflag") == "R", 1).otherwise(0)), F.lit(0)).alias("came_back"))


def big_set(spark: SparkSession, sf_dir: str, n: int, sets: int = 4) -> DataFrame:
    """``sets`` random subsets of n order lines each."""
    x = (F.col("l_orderkey") * 8 + F.col("l_linenumber")).cast("bigint").alias("element")
    ids = [F.lit(s).cast("bigint") for s in range(1, sets + 1)]
    lines = read(spark, sf_dir, "lineitem").select(x).where("element is not null").select("element", *[F.xxhash64("element", s).alias(f"h{i}") for i, s in enumerate(ids)])

    def least(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        # Each task's n least lines of every set are all that leave it; a line that is there twice counts once.
        held = [(np.zeros(0, np.int64), np.zeros(0, np.int64))] * sets
        for batch in batches:
            element = batch.column(0).to_numpy()
            for i, (h, e) in enumerate(held):
                new = batch.column(i + 1).to_numpy()
                near = new <= h[-1] if len(h) == n else np.ones(len(new), bool)
                both = np.unique(np.rec.fromarrays([np.r_[h, new[near]], np.r_[e, element[near]]]))[:n] if near.any() else None
                held[i] = (h, e) if both is None else (both["f0"].copy(), both["f1"].copy())
        for i, (h, e) in enumerate(held):
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(e), i + 1, np.int64)), pa.array(e), pa.array(h)], names=["set_id", "element", "h"])

    every = lines.mapInArrow(least, "set_id bigint, element bigint, h bigint").distinct()
    order = F.row_number().over(Window.partitionBy("set_id").orderBy("h", "element"))
    return every.withColumn("r", order).where(F.col("r") <= n).select("set_id", "element")


def answers(updates: DataFrame, kind: str, family: HashFamily, reserve: int, shape: B.BinShape | None = None) -> DataFrame:
    """(set_id, seq, sig) for every row with ``is_query``: the signature as of that point of the stream."""

    def walk(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values(["seq", "element", "op"], kind="stable")
        sketch, out = kernel(kind, family, reserve, shape), []
        seq, element, op, ask = (rows[c].to_numpy() for c in ("seq", "element", "op", "is_query"))
        at = 0
        for i in [*np.flatnonzero(ask).tolist(), len(rows)]:
            sketch.run(seq[at:i].astype(np.int64), element[at:i].astype(np.int64), op[at:i])
            if i < len(rows):
                out.append((rows["set_id"].iloc[0], int(seq[i]), sketch.signature().tolist() if sketch.held else None))
            at = i + 1
        return pd.DataFrame(out, columns=["set_id", "seq", "sig"])

    return updates.select("set_id", "seq", "element", "op", "is_query").groupBy("set_id").applyInPandas(walk, "set_id bigint, seq bigint, sig array<bigint>")


def planted_errors(spark: SparkSession, js: list[float], count: int = 1000, universe: int = 1 << 17, k: int = 1024, reserve: int = 17, shape: B.BinShape | None = None) -> DataFrame:
    """(j, sketch, rmse, error_sd, pairs): the reserve as a stream with deletions leaves it (k slots), rebuild with the reserve's memory (k * reserve
    slots), the reserve in a signature's memory, and bins, against each pair's own similarity. The defaults are the published settings."""
    shape = shape or B.BinShape(bins=k, levels=17)
    # Pairs of all similarities are sets of one collection, so every sketch is made once.
    sides = [streams.planted_pairs(spark, j, count, universe, seed=SEED + n).withColumn("pair_id", F.col("pair_id") + n * count) for n, j in enumerate(js)]
    members = written(_union(sides).select((F.col("pair_id") * 2 + F.col("side")).alias("set_id"), "element"), "planted")
    pairs = spark.range(count * len(js)).select((F.col("id") * 2).alias("a"), (F.col("id") * 2 + 1).alias("b"))
    j = F.get(F.array(*[F.lit(float(x)) for x in js]), F.floor(F.col("a") / (2 * count)).cast("int")).alias("j")
    exact = written(S.exact_similarity(members, pairs).select("a", "b", "exact", j), "exact")
    kept = {name: R.reserve_signature(R.maintained(members, HashFamily.tabulation(slots, SEED), reserve)[0]).where("sig is not null") for name, slots in (("reserve", k), ("reserve_same_memory", max(1, k // reserve)))}
    kept["rebuild_same_memory"] = S.signatures(members, HashFamily.tabulation(k * reserve, SEED))
    found = {name: S.estimate_similarity(sigs, pairs) for name, sigs in kept.items()}
    found[f"bins_{shape.rule}"] = B.bins_similarity(B.bins_init(members, shape), pairs, shape, HashFamily.affine(k, SEED))
    return _union([S.rmse(est.join(exact, ["a", "b"]).withColumn("sketch", F.lit(name)), ["j", "sketch"]) for name, est in found.items()])


#: The collections of the candidate-pair experiment and their thresholds: the least at which at most 4 % of all pairs are true.
NEIGHBOURHOODS = [("customer_parts", 0.05), ("part_suppliers", 0.25), ("user_keys", 0.45), ("page_links", 0.1), ("thin_graph_1", 0.1), ("thin_graph_2", 0.1), ("doc_shingles", 0.5)]


def neighbourhood_members(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """(set_id, element), or (set_id, e) where a row of the table is a set."""
    if name == "doc_shingles":
        return col.doc_shingle_sets(spark, sf_dir)
    if name.startswith("thin_graph_"):
        return streams.neighbourhoods(col.thin_edges(spark, sf_dir), int(name[-1]))
    return col.COLLECTIONS[name](spark, sf_dir)


def band_grid(budget: int) -> list[tuple[int, int]]:
    """Bandings that spend the whole budget, by rows."""
    return [(budget // rows, rows) for rows in range(1, 7) if budget // rows]


def pair_quality(spark: SparkSession, sf_dir: str, name: str, lam: float, budget: int = 2100, reserve: int = 8, bins: int = 64) -> DataFrame:
    """Quality of candidate pairs from a maintained reserve, banded by the formula (p1 = .8 at the threshold), and from bins, whose banding is chosen as
    the best of a grid since no formula holds for them. ``budget``: hash functions, 2,100 as published."""
    # Signatures depend on sets alone: equal sets are sketched and compared once.
    copies = C.Copies(neighbourhood_members(spark, sf_dir, name))
    m = copies.sizes.agg(F.coalesce(F.sum("copies"), F.lit(0))).first()[0]
    try:
        bands, rows = C.choose_bands(lam, 0.8, budget)
    except ValueError:  # no banding of so few functions reaches it: the nearest there is
        bands, rows = budget, 1
    shape = B.BinShape(bins=bins, levels=18)
    kept = R.reserve_signature(R.maintained(copies.sets, HashFamily.affine(bands * rows, SEED), reserve)[0])
    level = B.bins_level_signatures(B.bins_init(copies.sets, shape), HashFamily.affine(budget, SEED), shape)
    found = C.banded_quality(copies, lam, {"reserve": (kept, bands * rows, [(bands, rows)]), "bins": (level, budget, band_grid(budget))})
    found = found.select("tp", "fp", "fn", "tn", "precision", "recall", "f1", "effective", "returned", "sketch", "bands", "rows")
    return found.withColumns({"collection": F.lit(name), "lam": F.lit(lam), "true_share": F.round(F.col("effective") / F.lit(m * (m - 1) / 2 or 1), 6)})


#: Rows of a block that are multiplied at once.
STRIP = 256


def topdim_correlation(vectors: DataFrame, t: int = 8, block: int = 4096) -> DataFrame:
    """(correlation, pairs) of top-``t`` set similarity and dot product over all pairs of (vec_id, e), a < b.

    Every block of vectors meets every later one (and itself) in a kernel that gives back six sums, so no pair becomes a row.
    """
    ranked = vectors.select("vec_id", "e", top_dims(F.col("e"), t).alias("top"))
    ids = F.pmod(F.xxhash64("vec_id"), F.greatest(F.lit(1), F.ceil(F.col("m") / block))).cast("int").alias("block")
    size = F.broadcast(vectors.agg(F.count(F.lit(1)).alias("m")))  # one row
    dealt = ranked.crossJoin(size).select("*", ids)
    # A block is sent to each cell (x, y), x <= y, that it is a side of.
    blocks = F.greatest(F.lit(1), F.ceil(F.col("m") / block)).cast("int")
    other = F.explode(F.sequence(F.lit(0), blocks - 1)).alias("other")
    cells = dealt.select("vec_id", "e", "top", "block", other).select("vec_id", "e", "top", "block", F.least("block", "other").alias("x"), F.greatest("block", "other").alias("y"))

    def sums(rows: pd.DataFrame) -> pd.DataFrame:
        rows = rows.sort_values("vec_id")
        x, y = int(rows["x"].iloc[0]), int(rows["y"].iloc[0])
        left, right = rows[rows["block"] == x], rows[rows["block"] == y]
        out = np.zeros(6)
        if len(left) and len(right):
            width = int(max(map(max, rows["top"]))) + 1

            def side(part: pd.DataFrame) -> tuple[np.ndarray, np.ndarray]:
                marks = np.zeros((len(part), width), np.float32)
                for i, top in enumerate(part["top"]):
                    marks[i, np.asarray(top, np.int64)] = 1
                return np.stack(part["e"].to_numpy()).astype(np.float64), marks

            (ea, ma), (eb, mb) = side(left), side(right)
            for i in range(0, len(left), STRIP):
                shared = (ma[i : i + STRIP] @ mb.T).astype(np.float64)
                exact = shared / (ma[i : i + STRIP].sum(1)[:, None] + mb.sum(1)[None, :] - shared)
                dot = ea[i : i + STRIP] @ eb.T
                if x == y:
                    pick = np.triu_indices(len(dot), i + 1, dot.shape[1])
                    exact, dot = exact[pick], dot[pick]
                exact, dot = exact.ravel(), dot.ravel()
                out += [exact.size, exact.sum(), dot.sum(), exact @ exact, dot @ dot, exact @ dot]
        return pd.DataFrame([out], columns=["n", "s", "d", "ss", "dd", "sd"])

    parts = cells.groupBy("x", "y").applyInPandas(sums, "n double, s double, d double, ss double, dd double, sd double")
    n, s, d, ss, dd, sd = (F.sum(c) for c in ("n", "s", "d", "ss", "dd", "sd"))
    spread = F.sqrt((n * ss - s * s) * (n * dd - d * d))
    return parts.agg(F.round(F.try_divide(n * sd - s * d, spread), 6).alias("correlation"), F.coalesce(n, F.lit(0.0)).cast("bigint").alias("pairs"))


def register(query) -> None:
    """Add the workload queries to the catalog."""
    from .catalog import EDGES, FEW, RESERVE, SHAPE, UPDATES, WHOLE_EDGES, _array_sig_sql, _signature_rows, _sig_sql

    @query()
    def faults_by_reserve(spark: SparkSession, sf_dir: str) -> DataFrame:
        """n inserts, then n deletes: faults fall steeply with the reserve, then level off."""
        return fault_grid(streams.insert_then_delete(big_set(spark, sf_dir, 1 << 11)), [16, 64], [1, 2, 5, 8, 16, 32, 64, 128, 200])

    @query()
    def fault_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
        grid = fault_grid(streams.insert_then_delete(big_set(spark, sf_dir, 256)), [16, 64], [2, 8, 32])
        return grid.cube("k", "reserve").agg(F.sum("faults").alias("faults"), F.sum("reread").alias("reread"))

    @query()
    def rebuild_against_reserve(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Elements that recoveries read, rebuild baseline against a reserve of 32, by set size."""
        out = []
        for n in (128, 512, 1024):
            updates = streams.insert_then_delete(big_set(spark, sf_dir, n, sets=2))
            for kind in ("rebuild", "reserve"):
                one = costs.fault_counts(replay(updates, kind, HashFamily.tabulation(64, SEED), 32))
                out.append(one.withColumns({"n": F.lit(n), "sketch": F.lit(kind)}))
        return _union(out)

    @query()
    def faults_by_sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Faults of each sketch of the same memory (bins = k) over inserts and deletes of all suppliers' parts."""
        updates = streams.insert_then_delete(col.supplier_parts(spark, sf_dir), share=0.5)
        out = []
        for kind in ("reserve", "bins", "eager_bins"):
            one = costs.fault_counts(replay(updates, kind, HashFamily.tabulation(64, SEED), 16, shape=B.BinShape(bins=64, levels=17)))
            out.append(one.withColumn("sketch", F.lit(kind)))
        return _union(out)

    @query(f"""WITH q AS (SELECT user_id AS set_id, event_id AS seq FROM events WHERE event_type = 'view'),
u AS (SELECT * FROM ({UPDATES}) WHERE seq NOT IN (SELECT seq FROM q)),
l AS (SELECT q.set_id, q.seq, element, arg_max(op, u.seq) AS op FROM q JOIN u ON u.set_id = q.set_id AND u.seq < q.seq GROUP BY 1, 2, 3)
{" UNION ALL ".join(f"SELECT set_id, seq, {i} AS slot, min({FEW.pair_sql(i, 'element')}) AS pair FROM l WHERE op = 1 GROUP BY 1, 2" for i in range(FEW.k))}""")
    def mixed_query_answers(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Views ask, errors delete, the rest insert: every answer is the signature as of its place in the stream."""
        kinds = read(spark, sf_dir, "events").select(F.col("event_id").alias("seq"), (F.col("event_type") == "view").alias("is_query"))
        found = answers(col.event_updates(spark, sf_dir).join(kinds, "seq"), "reserve", FEW, RESERVE)
        return found.where("sig is not null").select("set_id", "seq", F.posexplode("sig").alias("slot", "pair"))

    @query()
    def rmse_planted(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Error by similarity and sketch; the maintained reserve's is that of a static signature, bins are far worse. Fewer and smaller sets than
        published, for time; ``planted_errors`` has the published settings as its defaults."""
        js = [round(0.1 * i, 1) for i in range(1, 10)]
        errors = planted_errors(spark, js, 12, 1 << 13, 64, 4, B.BinShape(bins=64, levels=14))
        return errors.groupBy("sketch").pivot("j", js).agg(F.round(F.first("rmse"), 6)).toDF("sketch", *[f"j{round(100 * j)}" for j in js])

    @query()
    def mixed_share_costs(spark: SparkSession, sf_dir: str) -> DataFrame:
        """(share, sketch, updates, queries, faults): the mixed stream at several shares of queries, all answered."""
        base = streams.insert_then_delete(big_set(spark, sf_dir, 256, sets=2))
        out = []
        for share in (0.0, 0.05, 0.1, 0.3):
            asked = streams.mixed_ops(base, share)
            for kind in ("reserve", "bins", "eager_bins"):
                found = answers(asked, kind, HashFamily.tabulation(64, SEED), 17, B.BinShape(bins=64, levels=17))
                one = found.agg(F.count(F.lit(1)).alias("queries"), F.count("sig").alias("answered"))
                rest = asked.agg(F.count(F.when(~F.col("is_query"), 1)).alias("updates"))
                out.append(one.join(rest).withColumns({"share": F.lit(share), "sketch": F.lit(kind)}))
        return _union(out)

    @query()
    def error_by_slots(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Slope of log error over log k: about -1/2."""
        return S.error_slope(cells.signature_errors(col.user_keys(spark, sf_dir), [HashFamily.affine(k, SEED) for k in (8, 16, 32, 64)]))

    @query()
    def neighbourhood_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
        """All seven collections at a budget of 96 functions, for time; ``pair_quality`` has the published 2,100 as its default."""
        # A collection's small jobs leave tasks idle that others take.
        with ThreadPoolExecutor(4) as pool:
            return _union(list(pool.map(lambda c: pair_quality(spark, sf_dir, *c, budget=96), NEIGHBOURHOODS)))

    @query("SELECT 0::BIGINT AS faults")
    def gentle_faults(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Every insert undone at once with chance one in ten: no fault even with a reserve of two."""
        return replay(streams.gentle_stream(col.supplier_parts(spark, sf_dir)), "reserve", FEW, 2).agg(F.sum("faults").alias("faults"))

    @query()
    def gentle_rebuild_faults(spark: SparkSession, sf_dir: str) -> DataFrame:
        return costs.fault_counts(replay(streams.gentle_stream(col.supplier_parts(spark, sf_dir)), "rebuild", FEW))

    @query("""WITH u AS (SELECT o_custkey AS set_id, l_partkey AS element, 1 AS op FROM lineitem JOIN orders ON l_orderkey = o_orderkey
UNION ALL SELECT o_custkey, l_partkey, -1 FROM lineitem JOIN orders ON l_orderkey = o_orderkey WHERE l_returnflag = 'R') SELECT op, count(*) AS updates, count(DISTINCT set_id) AS sets FROM u GROUP BY 1""")
    def order_stream_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
        return col.order_updates(spark, sf_dir).groupBy("op").agg(F.count(F.lit(1)).alias("updates"), F.countDistinct("set_id").alias("sets"))

    @query("SELECT 0::BIGINT AS differing")
    def order_stream_paths_agree(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Sets whose signature differs between sequential maintenance, netted maintenance and scratch."""
        updates = col.order_updates(spark, sf_dir)
        scratch = S.signatures(streams.members_at(updates), FEW).withColumnRenamed("sig", "x")
        one = replay(updates, "reserve", FEW, RESERVE).where("sig is not null").select("set_id", F.col("sig").alias("y"))
        empty = spark.createDataFrame([], "set_id bigint, slots array<struct<pairs: array<bigint>, lim: bigint>>")
        netted, _ = R.reserve_apply(empty, updates, streams.members_at(updates), FEW, RESERVE)
        two = R.reserve_signature(netted).where("sig is not null").withColumnRenamed("sig", "z")
        both = scratch.join(one, "set_id", "full").join(two, "set_id", "full")
        differ = ~(F.col("x").eqNullSafe(F.col("y")) & F.col("x").eqNullSafe(F.col("z")))
        return both.agg(F.count(F.when(differ, 1)).alias("differing"))

    @query()
    def fault_probability(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Observed share of slots that lose their whole reserve when suppliers' returned parts go, with the bound, by tenths of the share that goes and reserve."""
        sets = returned_parts(spark, sf_dir).groupBy("set_id").agg(F.collect_list(F.struct("element", "came_back")).alias("m"))
        return costs.observed_faults(sets.select(F.col("m.element").alias("e"), F.col("m.came_back").alias("gone")), [1, 2, 4, 8, 16, 32], HashFamily.affine(64, SEED))

    @query()
    def survival_by_reserve(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Sets that last a quarter of their size in deletions without a fault."""
        updates = streams.insert_then_delete(big_set(spark, sf_dir, 256, sets=8))
        out = []
        for ell in (1, 4, R.choose_reserve(32, 256, 1.5)):
            kept = costs.survival(replay(updates, "reserve", HashFamily.tabulation(32, SEED), ell))
            out.append(kept.agg(F.lit(ell).alias("reserve"), F.count(F.lit(1)).alias("sets"), F.count(F.when(F.col("survived"), 1)).alias("survived")))
        return _union(out)

    @query()
    def amortized_credit(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Least balance of the credit account over all sets: at zero or above, four unit costs an update pay for all."""
        from ..operators.replay import fault_log

        updates = streams.insert_then_delete(col.supplier_parts(spark, sf_dir), share=0.5)
        log = fault_log(replay(updates, "reserve", HashFamily.tabulation(16, SEED), 16))
        rows = costs.amortized_cost(updates, log, 16, 16)
        return rows.agg(F.min("credit").alias("least_credit"), F.avg("paid").alias("mean_paid"), F.lit(4 * costs.update_cost(16, 16)).alias("amortized_bound"))

    neighbours = EDGES.replace("AS u", "AS set_id").replace("AS v", "AS element")

    @query(_sig_sql(f"{neighbours} UNION ALL SELECT element, set_id FROM ({neighbours})", FEW))
    def edge_neighbourhood_signatures(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Neighbourhood sketches of both ends kept from edge updates."""
        return _signature_rows(replay(streams.edge_updates(numbered_edges(spark, sf_dir)), "reserve", FEW, RESERVE).select("set_id", "sig"))

    whole = WHOLE_EDGES.replace("AS u", "AS set_id").replace("AS v", "AS element")

    @query(_sig_sql(f"{whole} UNION ALL SELECT element, set_id FROM ({whole})", FEW))
    def whole_edge_neighbourhood_signatures(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Neighbourhood sketches of both ends kept from the edge updates of all order lines."""
        return _signature_rows(replay(streams.edge_updates(numbered_whole(spark, sf_dir)), "reserve", FEW, RESERVE).select("set_id", "sig"))

    @query()
    def topdim_cosine(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Correlation of top-dimension set similarity with the cosine of vectors; a report on other similarities, no more."""
        v = read(spark, sf_dir, "embeddings").select(F.col("vec_id").cast("bigint").alias("vec_id"), F.col("embedding").alias("e"))
        return topdim_correlation(v.where("vec_id is not null and size(e) > 0"))

    @query()
    def minwise_check(spark: SparkSession, sf_dir: str) -> DataFrame:
        """How close each hash family comes to min-wise independence on the users' sets."""
        return costs.minwise_rates(cells.arrays(col.user_keys(spark, sf_dir)), list(HashFamily.KINDS), 64)

    @query(f"""WITH s AS ({_array_sig_sql("SELECT DISTINCT set_id, element FROM (" + UPDATES + ")", FEW)}) SELECT count(*) AS sets, sum(len(sig))::BIGINT AS words FROM s""")
    def signature_words(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Words that signatures alone take."""
        return S.signatures(col.user_keys(spark, sf_dir), FEW).agg(F.count(F.lit(1)).alias("sets"), F.sum(F.size("sig")).cast("bigint").alias("words"))

    @query()
    def counters_by_rule(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Error of the bin sketch on real pairs by the rule that picks its level."""
        members = written(col.user_keys(spark, sf_dir), "members")
        out = []
        for rule in ("alpha_bins", "root", "alpha_root"):
            shape = B.BinShape(bins=SHAPE.bins, levels=SHAPE.levels, rule=rule)
            out.append(cells.bin_errors(members, shape).withColumn("rule", F.lit(rule)))
        return _union(out)
