"""Nearest neighbours by multi-index hashing of learned binary codes.

Codes: several learned rotations (each fitted so that the rotated vectors lie close to the corners of the binary cube) give 64 bits each.
Index: each code is cut into 16-bit substrings and every substring has its own table from value to rows. A code within
radius r of a query differs in at most r / m bits in at least one of its m substrings, so probing every table with all
values that near finds every code within r. What is found within r is reranked by the exact inner product.

Rotations and radius are fitted on a bounded sample of rows (``SAMPLE``); the radius is one at which the sample's own
queries find ``recall`` of their true neighbours. Every row is indexed. Rows are dealt to shards of at most about
``SHARD_ROWS`` rows and queries to blocks of ``QUERY_BLOCK``, so a vector is sent once for every block of queries and a query once for
every shard; a query keeps its ``k`` best of each shard. A query costs a shard's probes however few its rows are, so shards are not made smaller to
occupy idle tasks: blocks of queries are. A query that
finds fewer than ``k`` rows within the radius widens it in that shard until it has ``k`` or all rows.
Scores that decide are summed in one fixed order, so that equal vectors tie exactly and go by id.

Edge cases: vectors that are null, zero, of another length than most of the sample's, or that hold a null, NaN or infinity take
no part; repeated vectors are all returned, ties go to the smaller id; of rows with equal ids the least vector counts; null ids take no part; fewer than ``k`` candidates give
all of them; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from collections import Counter

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .runtime import materialise

#: Rows that the rotations and the radius are fitted on, at most; of them, queries that the radius is fitted with.
SAMPLE, SAMPLE_QUERIES = 8192, 200
#: Learned rotations; with 64-dimensional vectors each gives 64 bits.
ROTATIONS = 4
#: Rows of a shard at most.
SHARD_ROWS = 1 << 16
#: Queries that meet one shard at once, at most, and at least where there are tasks to spare.
QUERY_BLOCK, LEAST_QUERIES = 1 << 15, 1 << 10
SUBSTRING = 16


class Codes:
    """Learned rotations and the sign codes they give, as rows of unsigned 16-bit substrings."""

    def __init__(self, mean: np.ndarray, rotations: np.ndarray):
        self.mean, self.rotations = mean, rotations

    @classmethod
    def fit(cls, sample: np.ndarray, rotations: int = ROTATIONS, steps: int = 25, seed: int = 11) -> Codes:
        """Alternate between the nearest corners of the cube and the rotation that best takes the vectors there."""
        rng = np.random.default_rng(seed)
        mean = sample.mean(0)
        x = sample - mean
        out = []
        for _ in range(rotations):
            r = np.linalg.qr(rng.standard_normal((x.shape[1],) * 2))[0]
            for _ in range(steps):
                u, _, v = np.linalg.svd(x.T @ np.where(x @ r >= 0, 1.0, -1.0))
                r = u @ v
            out.append(r)
        return cls(mean, np.concatenate(out, axis=1))

    def encode(self, vectors: np.ndarray) -> np.ndarray:
        bits = (vectors - self.mean) @ self.rotations >= 0
        missing = -bits.shape[1] % SUBSTRING
        if missing:
            bits = np.concatenate([bits, np.zeros((len(bits), missing), bool)], axis=1)
        return np.packbits(bits, axis=1).view(np.uint16)


class MultiIndex:
    """Tables of one shard: for each substring the rows in order of its value, and where each of the 2^16 values begins and how many
    it has."""

    def __init__(self, codes: np.ndarray):
        self.codes, self.tables = codes, []
        for j in range(codes.shape[1]):
            order = np.argsort(codes[:, j], kind="stable").astype(np.int32)
            count = np.bincount(codes[:, j], minlength=1 << SUBSTRING).astype(np.int32)
            self.tables.append((order, np.cumsum(count, dtype=np.int32) - count, count))

    def within(self, code: np.ndarray, radius: int) -> np.ndarray:
        """Rows whose code differs from ``code`` in at most ``radius`` bits: probes every value that near in every table."""
        near, found = radius // len(self.tables), np.zeros(len(self.codes), bool)
        masks = MASKS[: FIRST_OF_WEIGHT[min(near, SUBSTRING) + 1]]
        for (order, first, count), own in zip(self.tables, code, strict=True):
            probe = masks ^ own
            n = count[probe]
            held = np.flatnonzero(n)
            lo, n = first[probe[held]], n[held]
            found[order[np.repeat(lo - np.cumsum(n) + n, n) + np.arange(n.sum())]] = True
        rows = np.flatnonzero(found)
        return rows[np.bitwise_count(self.codes[rows] ^ code).sum(1) <= radius]


#: All 16-bit values by weight, and where each weight begins.
MASKS = np.argsort(np.bitwise_count(np.arange(1 << SUBSTRING, dtype=np.uint16)), kind="stable").astype(np.uint16)
FIRST_OF_WEIGHT = np.searchsorted(np.bitwise_count(MASKS), np.arange(SUBSTRING + 2))


def fit_radius(sample: np.ndarray, codes: Codes, k: int, recall: float) -> int:
    """Radius at which ``recall`` of the sample's true neighbours are found, by brute force on the sample."""
    queries = np.arange(0, len(sample), max(1, len(sample) // SAMPLE_QUERIES))[:SAMPLE_QUERIES]
    own = codes.encode(sample)
    # The sample is sparser than the table: its nearest 20 are farther than the table's, so the radius errs on the wide side.
    score = sample[queries] @ sample.T
    score[np.arange(len(queries)), queries] = -np.inf
    take = min(k, len(sample) - 1)
    if take < 1:
        return codes.rotations.shape[1]
    best = np.argpartition(-score, take - 1, axis=1)[:, :take]
    far = np.bitwise_count(own[best] ^ own[queries][:, None]).sum(2)
    return int(np.quantile(far, recall))


def usable(vector):
    bad = F.exists(vector, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    return vector.isNotNull() & (F.size(vector) > 0) & ~F.coalesce(bad, F.lit(True)) & F.exists(vector, lambda x: x != 0)


def exact_products(vectors: np.ndarray, query: np.ndarray) -> np.ndarray:
    """Inner products summed from the first component to the last."""
    total = np.zeros(len(vectors))
    for j in range(len(query)):
        total += vectors[:, j] * query[j]
    return total


def best_of(ids: np.ndarray, vectors: np.ndarray, query: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Positions and exact scores of the ``k`` rows of largest inner product, ties to the smaller id."""
    score = vectors @ query
    if len(score) > k:
        # Whatever may round to a place among the best is summed exactly.
        least = np.partition(score, -k)[-k]
        slack = 1e-12 * len(query) * (np.abs(vectors).max(initial=0) * np.abs(query).max(initial=0))
        some = np.flatnonzero(score >= least - slack)
    else:
        some = np.arange(len(score))
    exact = exact_products(vectors[some], query)
    order = np.lexsort((ids[some], -exact))[:k]
    return some[order], exact[order]


def search(vectors: DataFrame, every: int = 20, k: int = 20, recall: float = 0.97, id_col: str = "vec_id", vector_col: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score): for every row whose id is divisible by ``every``, its ``k`` nearest other rows by inner
    product."""
    spark = vectors.sparkSession
    rows = vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vector_col).cast("array<double>").alias("v")).where(F.col("id").isNotNull() & usable(F.col("v")))
    rows = materialise(rows, "vectors")
    found = rows.orderBy(F.xxhash64("id"), "id").limit(SAMPLE).collect()  # bounded by SAMPLE
    if not found:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    lengths = Counter(len(r["v"]) for r in found)
    size = max(lengths, key=lambda n: (lengths[n], n))
    sample = np.array([r["v"] for r in found if len(r["v"]) == size])
    rows = rows.where(F.size("v") == size)
    if not rows.groupBy("id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").isEmpty():
        rows = materialise(rows.groupBy("id").agg(F.min("v").alias("v")), "vectors")
    codes = Codes.fit(sample)
    radius = fit_radius(sample, codes, k, recall)
    n = rows.count()
    shards, asked = max(-(-n // SHARD_ROWS), 1), -(-n // every)
    # Copies of vectors for idle tasks: at most one shard for each of them.
    blocks = max(-(-asked // QUERY_BLOCK), min(-(-spark.sparkContext.defaultParallelism // shards), asked // LEAST_QUERIES), 1)
    shared = spark.sparkContext.broadcast(codes)  # ROTATIONS square matrices
    data = rows.withColumn("shard", F.pmod(F.xxhash64("id"), F.lit(shards)).cast("int")).withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    queries = rows.where(F.col("id") % every == 0).withColumn("block", F.pmod(F.xxhash64("id", F.lit(1)), F.lit(blocks)).cast("int"))
    queries = queries.withColumn("shard", F.explode(F.sequence(F.lit(0), F.lit(shards - 1))))

    def answer(own: pd.DataFrame, asked: pd.DataFrame) -> pd.DataFrame:
        out = pd.DataFrame({"query_id": np.zeros(0, np.int64), "vec_id": np.zeros(0, np.int64), "score": np.zeros(0)})
        if not len(own) or not len(asked):
            return out
        ids, x = own["id"].to_numpy(np.int64), np.stack(own["v"].to_numpy())
        index = MultiIndex(shared.value.encode(x))
        q_ids, q = asked["id"].to_numpy(np.int64), np.stack(asked["v"].to_numpy())
        q_codes = shared.value.encode(q)
        got = []
        for i in range(len(q)):
            r = radius
            while True:
                near = index.within(q_codes[i], r)
                near = near[ids[near] != q_ids[i]]
                if len(near) >= k or r >= index.codes.shape[1] * SUBSTRING:
                    break
                r += SUBSTRING
            best, score = best_of(ids[near], x[near], q[i], k)
            got.append((np.full(len(best), q_ids[i]), ids[near[best]], score))
        return pd.DataFrame({c: np.concatenate([g[j] for g in got]) for j, c in enumerate(out.columns)})

    near = queries.groupBy("shard", "block").cogroup(data.groupBy("shard", "block")).applyInPandas(lambda a, b: answer(b, a), "query_id long, vec_id long, score double")
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return near.select("query_id", F.row_number().over(best).alias("rank"), "vec_id", "score").where(F.col("rank") <= k)
