"""Kernels over all pairs of a collection: blocks of sets meet in cells, and a numpy kernel gives back what is wanted of each cell.

Sets are shuffled, pairs never are: they leave a cell as final rows, as the best of each set, or as moments of their errors.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from math import ceil

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import HashFamily
from ..sources.store import written

#: Sets of a block, and rows of a cell that are compared at once.
BLOCK, STRIP = 4096, 64
#: Elements of a block that are multiplied at once.
WIDTH = 1024
#: Members of a block of small sets, and meetings of two sets in an element that are counted at once.
MEMBERS, MEETINGS = 3 << 20, 1 << 22
#: Members of a block of sets of neighbouring sizes, whose elements are sorted beside all else that a task holds.
SIZED_MEMBERS = 1 << 20

Kernel = Callable[[pa.Table, pa.Table, bool], Iterator[pa.RecordBatch]]


def over_cells(sets: DataFrame, kernel: Kernel, schema: str, block: int = BLOCK, kept: bool = False) -> DataFrame:
    """``kernel(left, right, same)`` for every two blocks of ``sets`` (set_id, ...), one row for each set; ``same`` if they are one block, whose
    pairs are those of two rows i < j. Blocks of few sets are smaller, so that tasks are not idle. ``kept``: sets that are written already."""
    sets = sets.where("set_id is not null")
    sets = sets if kept else written(sets, "sets")
    m = sets.count()
    blocks = max(1, ceil(m / block), min(8, ceil(m / 256)))
    own = F.pmod(F.xxhash64("set_id"), F.lit(blocks)).cast("int")
    dealt = sets.select("*", own.alias("_own"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("_other"))
    dealt = dealt.select("*", F.least("_own", "_other").alias("_x"), F.greatest("_own", "_other").alias("_y")).drop("_other")

    return _walked(dealt, kernel, schema, blocks, blocks * (blocks + 1) // 2)


def _walked(dealt: DataFrame, kernel: Kernel, schema: str, blocks: int, cells: int) -> DataFrame:
    """The kernel over each cell (_x, _y) of rows that are there by their block ``_own``."""

    def cell(rows: pa.Table) -> Iterator[pa.RecordBatch]:
        own, x, y = (rows.column(c).to_numpy() for c in ("_own", "_x", "_y"))
        left, right = np.flatnonzero(own == x), np.flatnonzero(own == y)
        if len(left) and len(right):
            yield from kernel(rows.take(left), rows.take(right), bool(x[0] == y[0]))

    def walk(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, at = [], None
        for batch in batches:
            key = batch.column("_x").to_numpy().astype(np.int64) * blocks + batch.column("_y").to_numpy()
            ends = [0, *(np.flatnonzero(key[1:] != key[:-1]) + 1).tolist(), len(key)]
            for a, b in zip(ends[:-1], ends[1:]):
                if b > a:
                    if held and key[a] != at:
                        yield from cell(pa.Table.from_batches(held))
                        held = []
                    held, at = [*held, batch.slice(a, b - a)], key[a]
        if held:
            yield from cell(pa.Table.from_batches(held))

    # A fixed number of partitions: small ones are not put together, since a cell's work is the square of its rows.
    return dealt.repartition(min(4096, cells), "_x", "_y").sortWithinPartitions("_x", "_y").mapInArrow(walk, schema)


def over_sized_cells(sets: DataFrame, kernel: Kernel, schema: str, lam: float, block: int = BLOCK) -> DataFrame:
    """``over_cells`` of (set_id, e, ...), written already, for pairs that can be of similarity ``lam`` alone: blocks hold sets of neighbouring sizes, at most about
    ``SIZED_MEMBERS`` elements, and meet only where the smaller one's sizes are at least lam of the larger one's."""
    sizes = sorted((r["n"], r["c"]) for r in sets.groupBy(F.size("e").alias("n")).agg(F.count(F.lit(1)).alias("c")).collect())  # as many rows as sizes
    m = sum(c for _, c in sizes)
    most = ceil(m / max(1, ceil(m / block), min(8, ceil(m / 256)))) or 1
    runs = []  # [least size, greatest, sets, elements]
    for n, c in sizes:
        if runs and runs[-1][2] + c <= most and runs[-1][3] + n * c <= SIZED_MEMBERS:
            runs[-1][1:] = n, runs[-1][2] + c, runs[-1][3] + n * c
        else:
            runs.append([n, n, c, n * c])
    runs = runs or [[0, 0, 0, 0]]
    parts = [max(1, ceil(c / most), ceil(x / SIZED_MEMBERS)) for _, _, c, x in runs]
    first = np.r_[0, np.cumsum(parts)].tolist()
    meets = [[t for t, r in enumerate(runs) if min(own[1], r[1]) >= lam * max(own[0], r[0]) - 1e-9 or r is own] for own in runs]
    spans = [(first[t[0]], first[t[-1] + 1] - 1) for t in meets]
    blocks = first[-1]
    cells = sum(max(0, hi - x + 1) for t, (_, hi) in enumerate(spans) for x in range(first[t], first[t + 1]))
    run = F.size(F.filter(F.lit([r[1] for r in runs]), lambda x: x < F.size("e")))
    named = sets.select("*", run.alias("_run"))
    at = lambda values: F.get(F.lit([int(v) for v in values]), F.col("_run"))
    own = (at(first[:-1]) + F.pmod(F.xxhash64("set_id"), at(parts))).cast("int")
    other = F.explode(F.sequence(at([x for x, _ in spans]), at([y for _, y in spans])))
    dealt = named.select("*", own.alias("_own"), other.alias("_other"))
    dealt = dealt.select("*", F.least("_own", "_other").alias("_x"), F.greatest("_own", "_other").alias("_y")).drop("_other", "_run")
    return _walked(dealt, kernel, schema, blocks, cells)


def classes(members: DataFrame) -> DataFrame:
    """(set_id, copies, e): each distinct set once, by its least id, its elements in order, and how many sets are equal to it."""
    return arrays(members).groupBy("e").agg(F.min("set_id").alias("set_id"), F.count(F.lit(1)).alias("copies")).select("set_id", "copies", "e")


def arrays(members: DataFrame) -> DataFrame:
    """(set_id, e): each set's elements in order."""
    return members.groupBy("set_id").agg(F.sort_array(F.collect_set("element")).alias("e"))


# What kernels are made of


def flat(column) -> tuple[np.ndarray, np.ndarray]:
    """(values, offsets) of a list column."""
    lists = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    lists = pa.concat_arrays(lists.chunks) if isinstance(lists, pa.ChunkedArray) else lists
    lengths = np.asarray(lists.value_lengths().fill_null(0).to_numpy(zero_copy_only=False), np.int64)
    return lists.flatten().to_numpy(zero_copy_only=False), np.r_[0, np.cumsum(lengths)]


def slots_of(column) -> np.ndarray:
    """Signatures as an (n, k) matrix."""
    values, offsets = flat(column)
    return values.reshape(len(offsets) - 1, -1)


def least_pairs(e, family: HashFamily) -> np.ndarray:
    """(n, k) signatures of sets that are not empty."""
    values, offsets = e
    every, at = np.unique(values, return_inverse=True)
    pairs = family.pairs_numpy(every)
    out, step = np.empty((len(offsets) - 1, family.k), np.int64), max(1, (1 << 22) // family.k)
    a = 0
    while a < len(out):
        b = max(a + 1, int(np.searchsorted(offsets, offsets[a] + step, "right")) - 1)
        out[a:b] = np.minimum.reduceat(pairs[at[offsets[a] : offsets[b]]], offsets[a:b] - offsets[a], axis=0)
        a = b
    return out


def coded(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Both signature matrices, slot by slot, as small numbers that are equal where the values are."""
    left, right = [], []
    for s in range(a.shape[1]):
        at = np.unique(np.concatenate([a[:, s], b[:, s]]), return_inverse=True)[1]
        left.append(at[: len(a)])
        right.append(at[len(a) :])
    kind = np.uint8 if max(int(x.max()) for x in (*left, *right)) < 256 else np.uint16 if len(a) + len(b) <= 1 << 16 else np.int64
    return np.array(left, kind), np.array(right, kind)


def agreeing(left: np.ndarray, right: np.ndarray, i: int, j: int) -> np.ndarray:
    """(j - i, m): slots in which rows i to j of the left side agree with each one of the right."""
    out = np.zeros((min(j, left.shape[1]) - i, right.shape[1]), np.uint8 if len(left) < 256 else np.uint16)
    for s in range(len(left)):
        out += left[s, i:j, None] == right[s]
    return out


def shared_counts(a, b) -> np.ndarray:
    """(n, m) numbers of shared elements of two sides given as (values, offsets), a stretch of elements at a time."""
    every, at = np.unique(np.concatenate([a[0], b[0]]), return_inverse=True)
    n = [len(x[1]) - 1 for x in (a, b)]
    row = [np.repeat(np.arange(k), np.diff(x[1])) for k, x in zip(n, (a, b))]
    element = at[: len(a[0])], at[len(a[0]) :]
    out = np.zeros(n, np.float32)
    for low in range(0, len(every), WIDTH):
        marks = []
        for k, r, e in zip(n, row, element):
            inside = np.flatnonzero((e >= low) & (e < low + WIDTH))
            marks.append(np.zeros((k, min(WIDTH, len(every) - low)), np.float32))
            marks[-1][r[inside], e[inside] - low] = 1
        out += marks[0] @ marks[1].T
    return out


class Postings:
    """One side of a cell: the first ``heads`` elements of each row, rarest first, and where each element stands."""

    def __init__(self, x: np.ndarray, offsets: np.ndarray, heads: np.ndarray, width: int):
        row = np.repeat(np.arange(len(heads)), np.diff(offsets))
        taken = np.arange(len(x)) - offsets[row] < heads[row]
        self.x, self.row = x[taken], row[taken]
        self.order = np.argsort(self.x, kind="stable")
        self.first = np.r_[0, np.cumsum(np.bincount(self.x, minlength=width))]

    def meeting(self, x: np.ndarray) -> np.ndarray:
        """How many rows hold each of the elements."""
        return self.first[x + 1] - self.first[x]

    def rows_of(self, x: np.ndarray, n: np.ndarray) -> np.ndarray:
        """The rows that hold each of the elements, one after another."""
        ends = np.cumsum(n)
        return self.row[self.order[np.arange(ends[-1]) + np.repeat(self.first[x] - ends + n, n)]] if len(n) else np.zeros(0, np.int64)


def common(x: np.ndarray, x_offsets: np.ndarray, i: np.ndarray, y: np.ndarray, y_offsets: np.ndarray, j: np.ndarray, width: int) -> np.ndarray:
    """Shared elements of each two rows i and j."""
    keys = []
    for values, offsets, rows in ((x, x_offsets, i), (y, y_offsets, j)):
        n = offsets[rows + 1] - offsets[rows]
        ends = np.cumsum(n)
        keys.append(np.repeat(np.arange(len(rows)), n) * width + values[np.arange(ends[-1]) + np.repeat(offsets[rows] - ends + n, n)])
    both = np.sort(np.concatenate(keys))
    return np.bincount(both[1:][both[1:] == both[:-1]] // width, minlength=len(i))


def reaching(a, b, lam: float, same: bool) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(i, j, exact): rows of two sides, given as (values, offsets), whose similarity is at least ``lam`` > 0, i < j if both are the ``same``.

    Meetings in elements are counted, rows of the left side in turn. Sets of similarity lam share one of each one's n - ceil(lam n) + 1 rarest elements; what
    the rest of a set can add to a count is bounded, so few pairs are counted in full. Where these heads are nearly whole sets, whole sets are counted instead.
    """
    every, at, seen = np.unique(np.concatenate([a[0], b[0]]), return_inverse=True, return_counts=True)
    width = len(every)
    rank = np.empty(width, np.int64)
    rank[np.argsort(seen, kind="stable")] = np.arange(width)
    sides = []
    for (_, offsets), x in zip((a, b), np.split(rank[at], [len(a[0])])):
        key = np.repeat(np.arange(len(offsets) - 1), np.diff(offsets)) * width + x
        key.sort()
        sides.append((key % width if width else key, offsets, np.diff(offsets)))
    (x, x_offsets, n_a), (y, y_offsets, n_b) = sides
    m = len(n_b)
    heads = [n - np.ceil(lam * n - 1e-9).astype(np.int64) + 1 for n in (n_a, n_b)]
    heads = [np.minimum(h, n) for h, n in zip(heads, (n_a, n_b))]
    left, right = (Postings(v, o, h, width) for (v, o, _), h in zip(sides, heads))
    meet = right.meeting(left.x)
    whole = float(np.bincount(x, minlength=width) @ np.bincount(y, minlength=width).astype(float)) <= 2.0 * float(meet.sum())
    if whole:
        heads = [n_a, n_b]
        left, right = (Postings(v, o, h, width) for (v, o, _), h in zip(sides, heads))
        meet = right.meeting(left.x)
    rest_a, rest_b = n_a - heads[0], n_b - heads[1]
    sizes_b = np.unique(n_b)
    rest_of_b = np.zeros(len(sizes_b)) if whole else np.ceil(lam * sizes_b - 1e-9) - 1

    def least(n, m, rest):
        """Meetings of heads without which two sets can't reach the threshold."""
        return np.maximum(1, np.ceil(lam / (1 + lam) * (n + m) - 1e-6) - rest)

    def fits(n, m):
        return np.minimum(n, m) >= lam * np.maximum(n, m) - 1e-9

    # Entries stand by rows; a stretch of rows has at most so many meetings, a row with more is a stretch of its own.
    entries = np.r_[0, np.cumsum(heads[0])]
    upto = np.r_[0, np.cumsum(meet)]
    by_row = upto[entries]
    i0 = 0
    while i0 < len(n_a):
        i1 = max(i0 + 1, int(np.searchsorted(by_row, by_row[i0] + MEETINGS, "right")) - 1)
        lo, hi = entries[i0], entries[i1]
        total = int(upto[hi] - upto[lo])
        if total:
            if (i1 - i0) * m <= 2 * total:
                found = np.zeros((i1 - i0) * m, np.int64)
                while lo < hi:  # an entry at a time, or as many as are counted at once
                    to = min(hi, max(lo + 1, int(np.searchsorted(upto, upto[lo] + MEETINGS, "right")) - 1))
                    found += np.bincount(np.repeat(left.row[lo:to] - i0, meet[lo:to]) * m + right.rows_of(left.x[lo:to], meet[lo:to]), minlength=len(found))
                    lo = to
                keys = np.flatnonzero(found)
                shared = found[keys]
            else:
                keys = np.repeat(left.row[lo:hi] - i0, meet[lo:hi]) * m + right.rows_of(left.x[lo:hi], meet[lo:hi])
                keys.sort()
                sizes = np.unique(n_a[i0:i1])[:, None]
                k = 1
                if sizes.size * len(sizes_b) <= MEETINGS:
                    bound = least(sizes, sizes_b, np.maximum(0 if whole else np.ceil(lam * sizes - 1e-9) - 1, rest_of_b))[fits(sizes, sizes_b)]
                    k = int(bound.min()) if len(bound) else total + 1
                hit = keys[k - 1 :][keys[k - 1 :] == keys[: max(0, total - k + 1)]]
                hit = hit[np.r_[True, hit[1:] != hit[:-1]]] if len(hit) else hit
                shared = np.searchsorted(keys, hit, "right") - np.searchsorted(keys, hit, "left")
                keys = hit
            i, j = i0 + keys // m, keys % m
            keep = fits(n_a[i], n_b[j]) & (shared >= least(n_a[i], n_b[j], np.maximum(rest_a[i], rest_b[j])))
            if same:
                keep &= i < j
            i, j, shared = i[keep], j[keep], shared[keep]
            cost = np.cumsum(n_a[i] + n_b[j])
            at0 = 0
            while at0 < len(i):
                at1 = len(i) if whole else max(at0 + 1, int(np.searchsorted(cost, (cost[at0 - 1] if at0 else 0) + MEETINGS, "right")))
                p, q = i[at0:at1], j[at0:at1]
                c = (shared[at0:at1] if whole else common(x, x_offsets, p, y, y_offsets, q, width)).astype(float)
                exact = c / (n_a[p] + n_b[q] - c)
                yield p[exact >= lam], q[exact >= lam], exact[exact >= lam]
                at0 = at1
        i0 = i1


def strips(n: int) -> Iterator[tuple[int, int]]:
    return ((i, min(n, i + STRIP)) for i in range(0, n, STRIP))


def later(same: bool, i: int, j: int, m: int) -> np.ndarray | None:
    """Which of a strip's cells are pairs of their own (null: all)."""
    return np.arange(m) > np.arange(i, j)[:, None] if same else None


# Whole results


def estimates(sigs: DataFrame, lam: float | None = None, bands: int = 0, rows: int = 0, block: int = BLOCK) -> DataFrame:
    """(a, b, est) of all pairs of (set_id, sig); with ``lam`` those alone whose estimate reaches it, with ``bands`` those that agree on a whole band of
    ``rows`` slots besides."""

    def kernel(left: pa.Table, right: pa.Table, same: bool) -> Iterator[pa.RecordBatch]:
        ids = left.column("set_id").to_numpy(), right.column("set_id").to_numpy()
        p, q = coded(slots_of(left.column("sig")), slots_of(right.column("sig")))
        for i, j in strips(len(ids[0])):
            pick = later(same, i, j, len(ids[1]))
            est = agreeing(p, q, i, j) / len(p)
            keep = np.ones(est.shape, bool) if pick is None else pick
            if lam is not None:
                keep = keep & (est >= lam)
            if bands:
                met = np.zeros(est.shape, bool)
                for band in range(bands):
                    whole = p[band * rows, i:j, None] == q[band * rows]
                    for s in range(band * rows + 1, band * rows + rows):
                        whole &= p[s, i:j, None] == q[s]
                    met |= whole
                keep = keep & met
            x, y = np.nonzero(keep)
            a, b = ids[0][i + x], ids[1][y]
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b)), pa.array(est[x, y])], names=["a", "b", "est"])

    return over_cells(sigs.where("sig is not null").select("set_id", "sig"), kernel, "a bigint, b bigint, est double", block)


def similar(sets: DataFrame, lam: float, block: int | None = None, kept: bool = False) -> DataFrame:
    """(a, b, exact) of all pairs of (set_id, e) whose similarity is at least ``lam`` > 0. Blocks hold about ``MEMBERS`` elements, unless told; every set is
    sent to as many cells as there are blocks."""
    sets = sets.select("set_id", "e")
    sets = sets if kept else written(sets, "sets")
    if block is None:
        block = max(1, int(MEMBERS / (sets.agg(F.avg(F.size("e"))).first()[0] or 1)))

    def kernel(left: pa.Table, right: pa.Table, same: bool) -> Iterator[pa.RecordBatch]:
        ids = left.column("set_id").to_numpy(), right.column("set_id").to_numpy()
        for i, j, exact in reaching(flat(left.column("e")), flat(right.column("e")), lam, same):
            a, b = ids[0][i], ids[1][j]
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b)), pa.array(exact)], names=["a", "b", "exact"])

    return over_cells(sets, kernel, "a bigint, b bigint, exact double", block, kept=True)


def nearest(sigs: DataFrame, n: int, block: int = BLOCK) -> DataFrame:
    """(set_id, other, est): of all pairs, each set's ``n`` best in every cell, ties to the smaller id."""

    def kernel(left: pa.Table, right: pa.Table, same: bool) -> Iterator[pa.RecordBatch]:
        def side(rows: pa.Table) -> tuple[np.ndarray, np.ndarray]:
            ids = rows.column("set_id").to_numpy()
            order = np.argsort(ids)
            return ids[order], slots_of(rows.column("sig"))[order]

        (ids_a, a), (ids_b, b) = side(left), side(right)
        p, q = coded(a, b)
        for mine, others, x, y in ((ids_a, ids_b, p, q), (ids_b, ids_a, q, p))[: 1 if same else 2]:
            m = len(others)
            for i, j in strips(len(mine)):
                # More agreeing slots, then the smaller id, give the larger number; a set is no partner of its own.
                score = agreeing(x, y, i, j).astype(np.int64) * m + np.arange(m - 1, -1, -1)
                if same:
                    score[np.arange(j - i), np.arange(i, j)] = -1
                best = np.argpartition(score, m - n, axis=1)[:, m - n :] if m > n else np.broadcast_to(np.arange(m), score.shape)
                won = np.take_along_axis(score, best, 1)
                r, c = np.nonzero(won >= 0)
                yield pa.RecordBatch.from_arrays([pa.array(mine[i + r]), pa.array(others[best[r, c]]), pa.array((won[r, c] // m) / len(x))], names=["set_id", "other", "est"])

    return over_cells(sigs.where("sig is not null").select("set_id", "sig"), kernel, "set_id bigint, other bigint, est double", block)


def moments(group: np.ndarray, error: np.ndarray, weight: np.ndarray | None = None) -> list[tuple[int, float, float, float]]:
    """(group, n, mean, m2) of the errors of each group."""
    group, at = np.unique(group, return_inverse=True)
    n = np.bincount(at, weight, len(group)).astype(float)
    mean = np.bincount(at, error if weight is None else error * weight, len(group)) / n
    rest = (error - mean[at]) ** 2
    m2 = np.bincount(at, rest if weight is None else rest * weight, len(group))
    return [(int(g), *map(float, x)) for g, *x in zip(group, n, mean, m2)]


def moments_batch(rows: list[tuple], first: str) -> pa.RecordBatch:
    kinds = [pa.int32(), pa.int32(), pa.float64(), pa.float64(), pa.float64()]
    columns = list(zip(*rows)) if rows else [[]] * 5
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], names=[first, "tenth", "n", "mean", "m2"])


def merged(parts: DataFrame, by: list[str]) -> DataFrame:
    """rmse, error_sd and pairs of each group from the moments of its parts."""
    rows = parts.groupBy(*by).agg(F.collect_list(F.struct("n", "mean", "m2")).alias("p"))

    def total(value: Callable[[Column], Column]) -> Column:
        return F.aggregate("p", F.lit(0.0), lambda s, x: s + value(x))

    rows = rows.withColumn("n", total(lambda x: x["n"]))
    rows = rows.withColumn("mean", total(lambda x: x["n"] * x["mean"]) / F.col("n"))
    rows = rows.withColumn("m2", total(lambda x: x["m2"] + x["n"] * (x["mean"] - F.col("mean")) * (x["mean"] - F.col("mean"))))
    rmse = F.sqrt(F.col("m2") / F.col("n") + F.col("mean") * F.col("mean"))
    return rows.select(*by, rmse.alias("rmse"), F.when(F.col("n") > 1, F.sqrt(F.col("m2") / (F.col("n") - 1))).alias("error_sd"), F.col("n").cast("bigint").alias("pairs"))


def signature_errors(members: DataFrame, families: list[HashFamily], by_tenth: bool = False, sharing: bool = False, half: bool = False, block: int = BLOCK) -> DataFrame:
    """(k, rmse, error_sd, pairs), with ``tenth`` if ``by_tenth``: errors of the signatures of each family over all pairs of sets. ``sharing``: only
    pairs that share an element. Equal sets are compared once and counted as often as they occur, unless only a ``half`` of the pairs, which a
    hash of both ids picks, counts."""

    def kernel(left: pa.Table, right: pa.Table, same: bool) -> Iterator[pa.RecordBatch]:
        a, b = flat(left.column("e")), flat(right.column("e"))
        ids = left.column("set_id").to_numpy(), right.column("set_id").to_numpy()
        n_a, n_b = np.diff(a[1]).astype(float), np.diff(b[1]).astype(float)
        w_a, w_b = (x.column("copies").to_numpy().astype(float) for x in (left, right))
        shared = shared_counts(a, b)
        sides = [coded(least_pairs(a, f), least_pairs(b, f)) for f in families]
        out = []
        for i, j in strips(len(n_a)):
            keep = np.ones((j - i, len(n_b)), bool) if not same else later(True, i, j, len(n_b))
            if sharing:
                keep = keep & (shared[i:j] > 0)
            if half:
                keep = keep & chosen(ids[0][i:j, None], ids[1])
            common = shared[i:j][keep].astype(float)
            x, y = np.nonzero(keep)
            exact = common / (n_a[i + x] + n_b[y] - common)
            weight = w_a[i + x] * w_b[y]
            tenth = np.floor(exact * 10).astype(np.int64) if by_tenth else np.zeros(len(exact), np.int64)
            for f, (p, q) in zip(families, sides):
                est = agreeing(p, q, i, j)[keep] / f.k
                out += [(f.k, *row) for row in moments(tenth, est - exact, weight)] if len(exact) else []
        if same and not half:  # pairs of equal sets, of similarity and estimate 1
            twins = float((w_a * (w_a - 1) / 2).sum())
            out += [(f.k, 10 * by_tenth, twins, 0.0, 0.0) for f in families] if twins else []
        yield moments_batch(out, "k")

    sets = arrays(members).withColumn("copies", F.lit(1).cast("bigint")) if half else classes(members)
    parts = over_cells(sets, kernel, "k int, tenth int, n double, mean double, m2 double", block)
    return merged(parts, ["k", "tenth"] if by_tenth else ["k"])


class LevelMasks:
    """One side's taken bins as bit masks, by level, and each set's own level; rows in order of it."""

    def __init__(self, rows: pa.Table, shape):
        values, offsets = flat(rows.column("places"))
        words = -(-shape.bins // 64)
        row, level, at = np.repeat(np.arange(rows.num_rows), np.diff(offsets)), values // shape.bins, values % shape.bins
        self.masks = np.zeros((rows.num_rows, shape.levels, words), np.uint64)
        np.bitwise_or.at(self.masks, (row, level, at // 64), np.uint64(1) << (at % 64).astype(np.uint64))
        own = rows.column("own").to_numpy()
        self.order = np.argsort(own, kind="stable")
        self.masks, self.ids = self.masks[self.order], rows.column("set_id").to_numpy()[self.order]
        self.taken = np.bitwise_count(self.masks).sum(2).astype(np.int64)
        levels, first = np.unique(own[self.order], return_index=True)
        #: (level, begin, end) of the sets of each own level.
        self.runs = list(zip(levels.tolist(), first.tolist(), [*first[1:].tolist(), len(own)]))


def bin_places(bins: DataFrame, shape) -> DataFrame:
    """(set_id, own, places): the level that each set's size asks for, and its taken bins of all levels as level * bins + bin."""
    place = (F.col("level") * shape.bins + F.col("bin")).cast("int")
    rows = bins.groupBy("set_id").agg(F.sum("cnt").alias("n"), F.collect_list(place).alias("places"))
    return rows.select("set_id", shape.level_for(F.col("n")).alias("own"), "places")


def level_strips(p: LevelMasks, q: LevelMasks, same: bool) -> Iterator[tuple]:
    """(rows, columns, pick, shared, taken) of strips of pairs, each on the level of the larger set: ``shared`` bins and bins ``taken`` by either."""
    for la, i0, i1 in p.runs:
        for lb, j0, j1 in q.runs:
            if same and j1 <= i0:
                continue
            level = max(la, lb)  # levels rise with sizes, so the larger set's is the higher one
            for i, j in ((i0 + a, i0 + b) for a, b in strips(i1 - i0)):
                shared = np.bitwise_count(p.masks[i:j, None, level, 0] & q.masks[None, j0:j1, level, 0]).astype(np.int64)
                for w in range(1, p.masks.shape[2]):
                    shared += np.bitwise_count(p.masks[i:j, None, level, w] & q.masks[None, j0:j1, level, w])
                taken = p.taken[i:j, level, None] + q.taken[None, j0:j1, level] - shared
                pick = np.arange(j0, j1) > np.arange(i, j)[:, None] if same else np.ones(shared.shape, bool)
                yield slice(i, j), slice(j0, j1), pick, shared, taken


def bin_estimates(bins: DataFrame, shape, block: int = BLOCK) -> DataFrame:
    """(a, b, est) of all pairs of sets of a bin sketch, on the level of each pair's larger set; null where neither has a bin there."""

    def kernel(left: pa.Table, right: pa.Table, same: bool) -> Iterator[pa.RecordBatch]:
        p, q = LevelMasks(left, shape), LevelMasks(right, shape)
        for rows, columns, pick, shared, taken in level_strips(p, q, same):
            x, y = np.nonzero(pick)
            a, b, c, t = p.ids[rows][x], q.ids[columns][y], shared[x, y], taken[x, y]
            est = pa.array(c / np.maximum(t, 1), mask=t == 0)
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b)), est], names=["a", "b", "est"])

    return over_cells(bin_places(bins, shape), kernel, "a bigint, b bigint, est double", block)


def bin_errors(members: DataFrame, shape, block: int = BLOCK) -> DataFrame:
    """(rmse, error_sd, pairs): errors of a bin sketch of the given sets over all pairs that it has an estimate of. Equal sets are compared once."""

    def kernel(left: pa.Table, right: pa.Table, same: bool) -> Iterator[pa.RecordBatch]:
        p, q = LevelMasks(left, shape), LevelMasks(right, shape)
        both = shared_counts(flat(left.column("e")), flat(right.column("e")))[p.order][:, q.order]
        n_a, n_b = (np.diff(flat(x.column("e"))[1])[s.order].astype(float) for x, s in ((left, p), (right, q)))
        w_a, w_b = (x.column("copies").to_numpy()[s.order].astype(float) for x, s in ((left, p), (right, q)))
        out = []
        for rows, columns, pick, shared, taken in level_strips(p, q, same):
            pick = pick & (taken > 0)
            if pick.any():
                common = both[rows, columns].astype(float)
                exact = common / (n_a[rows, None] + n_b[columns] - common)
                error = (shared / np.maximum(taken, 1) - exact)[pick]
                out += [(0, *row) for row in moments(np.zeros(len(error), np.int64), error, (w_a[rows, None] * w_b[columns])[pick])]
        if same:  # pairs of equal sets, without an error where they have an estimate
            for level, i, j in p.runs:
                twins = float((w_a[i:j] * (w_a[i:j] - 1) / 2)[p.taken[i:j, level] > 0].sum())
                out += [(0, 0, twins, 0.0, 0.0)] if twins else []
        yield moments_batch(out, "k")

    x = F.col("e")
    place = F.transform(x, lambda v: (shape.level(v) * shape.bins + shape.bin(v)).cast("int"))
    sets = classes(members).select("set_id", "copies", "e", shape.level_for(F.size(x)).alias("own"), F.array_distinct(place).alias("places"))
    return merged(over_cells(sets, kernel, "k int, tenth int, n double, mean double, m2 double", block), ["k"]).drop("k")


def chosen(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Half of all pairs, by a hash of the smaller and the larger id."""
    low, high = np.minimum(a, b).astype(np.uint64), np.maximum(a, b).astype(np.uint64)
    h = low * np.uint64(0x9E3779B97F4A7C15) + high
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        h = (h ^ h >> np.uint64(shift)) * np.uint64(factor)
    return h >> np.uint64(63) == 0


def reached(members: DataFrame, grid: list[float], block: int = BLOCK) -> DataFrame:
    """(lam, pairs): of all pairs, how many reach each threshold above 0. Equal sets are compared once."""

    def kernel(left: pa.Table, right: pa.Table, same: bool) -> Iterator[pa.RecordBatch]:
        a, b = flat(left.column("e")), flat(right.column("e"))
        n_a, n_b = np.diff(a[1]).astype(float), np.diff(b[1]).astype(float)
        w_a, w_b = (x.column("copies").to_numpy() for x in (left, right))
        shared = shared_counts(a, b)
        found = np.array([int((w_a * (w_a - 1) // 2).sum()) if same and lam <= 1 else 0 for lam in grid], np.int64)
        for i, j in strips(len(n_a)):
            common = shared[i:j].astype(float)
            exact = common / (n_a[i:j, None] + n_b - common)
            if same:
                exact[~later(True, i, j, len(n_b))] = -1
            for g, lam in enumerate(grid):
                found[g] += w_a[i:j] @ ((exact >= lam) @ w_b)
        yield pa.RecordBatch.from_arrays([pa.array(grid, pa.float64()), pa.array(found)], names=["lam", "pairs"])

    return over_cells(classes(members), kernel, "lam double, pairs bigint", block).groupBy("lam").agg(F.sum("pairs").alias("pairs"))


#: Slots' values, by level: (rows that have a signature there, (slots, rows) values).
Leveled = dict[int, tuple[np.ndarray, np.ndarray]]


def by_level(column, k: int, order: np.ndarray | None = None) -> Leveled:
    """Signatures of a list column of (level, sig), rows in the given order."""
    structs = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    structs = pa.concat_arrays(structs.chunks) if isinstance(structs, pa.ChunkedArray) else structs
    structs = structs if order is None else structs.take(pa.array(order))
    n = np.asarray(structs.value_lengths().fill_null(0).to_numpy(zero_copy_only=False), np.int64)
    level, sig = structs.flatten().flatten()
    row, level, sig = np.repeat(np.arange(len(n)), n), level.to_numpy(zero_copy_only=False), sig.flatten().to_numpy(zero_copy_only=False).reshape(-1, k)
    return {int(v): (row[level == v], np.ascontiguousarray(sig[level == v].T)) for v in np.unique(level)}


def narrowed(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(slots, n) values of both sides as small numbers from 0 that are equal where the values are, and the bits they take in each slot."""
    left, right, bits = np.empty(a.shape, np.int64), np.empty(b.shape, np.int64), []
    for s in range(len(a)):
        low, high = min(int(a[s].min()), int(b[s].min())), max(int(a[s].max()), int(b[s].max()))
        if high - low < 1 << 10:
            left[s], right[s] = a[s].astype(np.int64) - low, b[s].astype(np.int64) - low
        else:
            at = np.unique(np.concatenate([a[s], b[s]]), return_inverse=True)[1]
            left[s], right[s] = at[: a.shape[1]], at[a.shape[1] :]
        bits.append(int(max(left[s].max(), right[s].max())).bit_length())
    return left, right, np.array(bits)


def band(left: np.ndarray, right: np.ndarray, bits: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """One number for the values of a band's slots, equal where all of them are."""
    p, q, width = left[0], right[0], int(bits[0])
    for x, y, more in zip(left[1:], right[1:], bits[1:].tolist()):
        if width + more > 62:
            at = np.unique(np.concatenate([p, q]), return_inverse=True)[1]
            p, q, width = at[: len(p)], at[len(p) :], int(at.max()).bit_length()
        p, q, width = p << more | x, q << more | y, width + more
    return p, q


class Meetings:
    """Which rows of the left side agree with which of the right side on any band so far: a bit for each pair.

    Values that many rows of the right side have are or-ed as a whole line of bits, the pairs of rare ones are set one by one."""

    def __init__(self, n: int, m: int):
        self.m, self.words = m, -(-m // 64)
        self.bits = np.zeros((n, self.words), np.uint64)
        self.rare = max(4, m // 512)

    def add(self, rows: np.ndarray, p: np.ndarray, columns: np.ndarray, q: np.ndarray) -> None:
        """Rows and columns with their values of a band."""
        value, at, n = np.unique(q, return_inverse=True, return_counts=True)
        found = np.minimum(np.searchsorted(value, p), len(value) - 1)
        held = value[found] == p
        rows, found = rows[held], found[held]
        often = n > self.rare
        lines = np.cumsum(often) - 1
        few = ~often[found]
        if few.any():
            order, ends = np.argsort(at, kind="stable"), np.cumsum(n)
            i, v = rows[few], found[few]
            each = n[v]
            upto = np.cumsum(each)
            j = columns[order[np.arange(upto[-1]) + np.repeat(ends[v] - upto, each)]]
            np.bitwise_or.at(self.bits.reshape(-1), np.repeat(i, each) * self.words + (j >> 6), np.uint64(1) << (j & 63).astype(np.uint64))
        rows, line = rows[~few], lines[found[~few]]
        step = max(1, (1 << 15) // self.words)
        most = max(1, (1 << 25) // (64 * self.words))
        for low in range(0, int(often.sum()), most):  # lines of bits that are made at once
            high = min(int(often.sum()), low + most)
            here = often[at] & (lines[at] >= low) & (lines[at] < high)
            marks = np.zeros((high - low + 1, 64 * self.words), np.uint8)
            marks[lines[at[here]] - low, columns[here]] = 1
            table = np.packbits(marks, axis=1, bitorder="little").view(np.uint64)
            inside = (line >= low) & (line < high)
            own, which = rows[inside], line[inside] - low
            if 2 * len(own) >= len(self.bits):
                every = np.full(len(self.bits), high - low)  # the last line is empty
                every[own] = which
                for i in range(0, len(every), step):
                    part = self.bits[i : i + step]
                    np.bitwise_or(part, table[every[i : i + step]], out=part)
            else:
                for i in range(0, len(own), step):
                    self.bits[own[i : i + step]] |= table[which[i : i + step]]

    def weigh(self, w_a: np.ndarray, w_b: np.ndarray) -> int:
        """Sum of both sides' weights' products over all pairs met; ``w_b`` in falling order."""
        more = int(np.count_nonzero(w_b > 1))
        total, step = 0, max(1, (1 << 22) // (64 * self.words))
        for i in range(0, len(w_a), step):
            part = self.bits[i : i + step]
            n = np.bitwise_count(part).sum(1, dtype=np.int64)
            if more:
                some = np.unpackbits(part.view(np.uint8)[:, : -(-more // 8)], axis=1, bitorder="little")[:, :more]
                n += (some @ (w_b[:more] - 1).astype(float)).astype(np.int64)
            total += int(w_a[i : i + step] @ n)
        return total


def banded(sets: DataFrame, lam: float, grids: dict[str, tuple[int, list[tuple[int, int]]]], block: int = BLOCK) -> DataFrame:
    """(sketch, bands, rows, tp, returned, effective): of all pairs of sets, how many agree on a whole band, reach ``lam`` > 0, or both.

    ``sets``: (set_id, copies, e) and for each sketch that ``grids`` names with its slots and bandings a column of that name, of the set's signatures as
    (level, sig); only those of equal levels are compared. A set stands for ``copies`` equal ones. Signatures alone meet in all cells; elements are sent
    only where sizes can reach ``lam``.
    """
    kinds = [pa.string(), pa.int32(), pa.int32(), pa.int64(), pa.int64(), pa.int64()]
    schema = "sketch string, bands int, rows int, tp bigint, returned bigint, effective bigint"

    def batch(out: list[tuple]) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), kinds)], names=["sketch", "bands", "rows", "tp", "returned", "effective"])

    def signed(levels: Leveled, n: int) -> np.ndarray:
        """Which rows have a signature."""
        out = np.zeros(n, bool)
        for rows, _ in levels.values():
            out[rows] = True
        return out

    def met(left: pa.Table, right: pa.Table, same: bool) -> Iterator[pa.RecordBatch]:
        w_a, w_b = (x.column("copies").to_numpy().astype(np.int64) for x in (left, right))
        order = np.argsort(-w_b, kind="stable")
        w_b, out = w_b[order], []
        for name, (k, grid) in grids.items():
            a, b = by_level(left.column(name), k), by_level(right.column(name), k, order)
            codes = [(a[v][0], b[v][0], *narrowed(a[v][1], b[v][1])) for v in a.keys() & b.keys()]
            own = w_a[signed(a, len(w_a))]
            for bands, width in grid:
                pairs = Meetings(len(w_a), len(w_b))
                for rows, columns, p, q, bits in codes:
                    for s in range(0, bands * width, width):
                        one, other = band(p[s : s + width], q[s : s + width], bits[s : s + width])
                        pairs.add(rows, one, columns, other)
                returned = pairs.weigh(w_a, w_b)
                if same:
                    # Every pair was met twice, and each set itself; equal sets are returned where they have a signature.
                    returned = (returned - int((own * own).sum())) // 2 + int((own * (own - 1) // 2).sum())
                out.append((name, bands, width, 0, returned, 0))
        yield batch(out)

    def true(left: pa.Table, right: pa.Table, same: bool) -> Iterator[pa.RecordBatch]:
        w_a, w_b = (x.column("copies").to_numpy().astype(np.int64) for x in (left, right))
        sides = {name: [by_level(x.column(name), k) for x in (left, right)] for name, (k, _) in grids.items()}
        places = {}
        for name, both in sides.items():
            for v in both[0].keys() & both[1].keys():
                for x, levels, n in ((0, both[0], len(w_a)), (1, both[1], len(w_b))):
                    places[name, v, x] = np.full(n, -1)
                    places[name, v, x][levels[v][0]] = np.arange(len(levels[v][0]))
        found, effective = {name: np.zeros(len(grid), np.int64) for name, (_, grid) in grids.items()}, 0
        for every_i, every_j, _ in reaching(flat(left.column("e")), flat(right.column("e")), lam, same):
            for at in range(0, len(every_i), 1 << 16):
                i, j = every_i[at : at + (1 << 16)], every_j[at : at + (1 << 16)]
                w = w_a[i] * w_b[j]
                effective += int(w.sum())
                for name, (k, grid) in grids.items():
                    hit = np.zeros((len(grid), len(i)), bool)
                    for v in sides[name][0].keys() & sides[name][1].keys():
                        p, q = places[name, v, 0][i], places[name, v, 1][j]
                        here = np.flatnonzero((p >= 0) & (q >= 0))
                        p, q = p[here], q[here]
                        whole, any_ = np.zeros((len(grid), len(here)), bool), np.zeros((len(grid), len(here)), bool)
                        for s in range(k):
                            equal = sides[name][0][v][1][s][p] == sides[name][1][v][1][s][q]
                            for g, (bands, width) in enumerate(grid):
                                if s < bands * width:
                                    whole[g] = whole[g] & equal if s % width else equal
                                    if s % width == width - 1:
                                        any_[g] |= whole[g]
                        hit[:, here] |= any_
                    found[name] += hit @ w
        twins, out = w_a * (w_a - 1) // 2 if same else np.zeros(len(w_a), np.int64), []
        for name, (_, grid) in grids.items():
            alike = int(twins[signed(sides[name][0], len(w_a))].sum())
            out += [(name, bands, width, tp + alike, 0, effective + int(twins.sum())) for (bands, width), tp in zip(grid, found[name].tolist())]
        yield batch(out)

    sets = written(sets.where("set_id is not null"), "sets")
    parts = over_cells(sets.select("set_id", "copies", *grids), met, schema, 4 * block, kept=True).union(over_sized_cells(sets.select("set_id", "copies", "e", *grids), true, schema, lam, block))
    return parts.groupBy("sketch", "bands", "rows").agg(*[F.sum(c).alias(c) for c in ("tp", "returned", "effective")])
