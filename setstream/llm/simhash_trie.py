"""SimHash fingerprints, their Hamming links by a binary-trie self-join, and the groups those links connect.

The join works on distinct fingerprints. Two fingerprints with at most ``radius`` differing bits agree on all but
``radius`` of ``blocks`` bit blocks, so each fingerprint goes, once for every choice of agreeing blocks, to the bucket
of those blocks' value; the bits that are left are a binary trie inside the bucket. All tries of a task
are walked together, level by level: a frontier of node pairs carries its differing bits so far and loses every pair
that is over the budget. Links are folded into a spanning forest before they leave the task, so that a
group of n fingerprints emits n - 1 links at most, never all pairs.
A bucket of more than ``HOT`` fingerprints is split by the same rule: its bits that don't name it are cut into ``radius + 1`` blocks,
near fingerprints agree on one of these, and each fingerprint goes to one smaller bucket for each block.

Edge cases: null and wordless texts have fingerprint zero and link like any other; texts with fewer words than a
shingle count as one shingle; repeated rows share a fingerprint; a null doc_id takes no part in the smallest id (the group's id is null only
if all are null); an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .runtime import discard, materialise, partitions, restored, sheltered
from .text import LOWER, NOT_BLANK, Words, chunks, raw

#: Fingerprints of a bucket above which it is split.
HOT = 1 << 14
#: Frontier pairs that are walked at once.
FRONTIER = 1 << 18
#: Node pairs of no more fingerprint pairs than this are compared directly.
SMALL = 64


def text_fingerprints(data: np.ndarray, offsets: np.ndarray, shingle: int) -> np.ndarray:
    """One unsigned 64-bit fingerprint for each text: bit i is 1 if over half of its shingle hashes have bit i."""
    import xxhash

    digest = xxhash.xxh64_intdigest
    words = Words(LOWER[data], offsets, NOT_BLANK)
    n_docs = len(offsets) - 1
    if not len(words):
        return np.zeros(n_docs, np.uint64)
    length = words.end - words.start
    to = np.cumsum(length + 1)  # words joined by one space each
    at = to - length - 1
    joined = np.full(int(to[-1]), 0x20, np.uint8)
    inside = np.zeros(len(words.data) + 1, np.int8)
    inside[words.start] = 1
    inside[words.end] -= 1
    body = np.ones(int(to[-1]), bool)
    body[to - 1] = False
    joined[body] = words.data[np.cumsum(inside[:-1]).astype(bool)]
    per_doc = np.diff(words.first)
    shingles = np.where(per_doc > 0, np.maximum(per_doc - shingle + 1, 1), 0)
    before = np.concatenate([[0], np.cumsum(shingles)])
    doc = np.repeat(np.arange(n_docs), shingles)
    first = words.first[doc] + np.arange(before[-1]) - before[doc]
    last = np.minimum(first + shingle, words.first[doc + 1]) - 1
    view = joined.tobytes()
    h = np.fromiter((digest(view[a:b], 42) for a, b in zip(at[first].tolist(), (to[last] - 1).tolist(), strict=True)), np.uint64, len(first))
    out = np.zeros(n_docs, np.uint64)
    some = np.flatnonzero(shingles)
    for i in range(0, len(some), 4096):
        rows = some[i : i + 4096]
        part = h[before[rows[0]] : before[rows[-1] + 1]]
        starts = before[rows] - before[rows[0]]
        for bit in range(64):
            ones = np.add.reduceat((part >> np.uint64(bit)) & np.uint64(1), starts)
            out[rows] |= (2 * ones > shingles[rows].astype(np.uint64)).astype(np.uint64) << np.uint64(bit)
    return out


def fingerprints(docs: DataFrame, shingle: int = 4, keep: tuple[str, ...] = ("doc_id",), text_col: str = "text") -> DataFrame:
    """The columns ``keep`` and ``fp``: the fingerprint of every row as a signed long of the same bits."""
    schema = T.StructType([*(docs.schema[c] for c in keep), T.StructField("fp", T.LongType(), False)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column(len(keep))
            for a, b in chunks(column):
                data, offsets = raw(column.slice(a, b - a))
                got = text_fingerprints(data, offsets, shingle).view(np.int64)
                kept = [batch.column(i).slice(a, b - a) for i in range(len(keep))]
                yield pa.RecordBatch.from_arrays([*kept, pa.array(got)], names=[*keep, "fp"])

    return docs.select(*keep, text_col).mapInArrow(run, schema)


def choose_blocks(n: int, radius: int) -> int:
    """Blocks so that a bucket of random fingerprints holds a few thousand at most."""
    blocks = radius + 1
    while n >> (64 * (blocks - radius) // blocks) > 4096 and blocks < radius + 8:
        blocks += 1
    return blocks


class Forest:
    """Union-find over positions, smaller root wins; ``join`` takes arrays of links."""

    def __init__(self, n: int):
        self.up = np.arange(n)

    def roots(self, x: np.ndarray) -> np.ndarray:
        up = self.up
        while True:
            y = up[x]
            z = up[y]
            if (y == z).all():
                return y
            up[x] = z
            x = z

    def join(self, a: np.ndarray, b: np.ndarray) -> None:
        while len(a):
            a, b = self.roots(a), self.roots(b)
            differ = a != b
            a, b = a[differ], b[differ]
            low, high = np.minimum(a, b), np.maximum(a, b)
            np.minimum.at(self.up, high, low)
            a, b = low, high


def walk_tries(bucket: np.ndarray, fp: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """Spanning links (as positions) among fingerprints of equal ``bucket`` at ``radius`` or fewer differing bits.

    Rows are sorted by (bucket, unsigned fp), each bucket's fingerprints distinct.
    """
    n, forest = len(fp), Forest(len(fp))
    ones = {}

    def split(lo: np.ndarray, hi: np.ndarray, bit: int) -> np.ndarray:
        if bit not in ones:
            ones[bit] = np.concatenate([[0], np.cumsum((fp >> np.uint64(bit)) & np.uint64(1))]).astype(np.int64)
        return hi - (ones[bit][hi] - ones[bit][lo])

    edges = np.flatnonzero(np.concatenate([[True], bucket[1:] != bucket[:-1]])) if n else np.zeros(0, np.int64)
    ends = np.append(edges[1:], n)
    some = ends - edges > 1
    lo, hi = edges[some], ends[some]
    todo = [(63, lo[i : i + FRONTIER], hi[i : i + FRONTIER], lo[i : i + FRONTIER], hi[i : i + FRONTIER], np.zeros(len(lo[i : i + FRONTIER]), np.int8)) for i in range(0, len(lo), FRONTIER)]
    while todo:
        bit, al, ah, bl, bh, err = todo.pop()
        small = (ah - al) * (bh - bl) <= SMALL if bit >= 0 else np.ones(len(al), bool)
        if small.any():
            na, nb = (ah - al)[small], (bh - bl)[small]
            each = na * nb
            which = np.repeat(np.flatnonzero(small), each)
            nth = np.arange(each.sum()) - np.repeat(np.cumsum(each) - each, each)
            width = np.repeat(nb, each)
            x, y = al[which] + nth // width, bl[which] + nth % width
            near = (x < y) & (np.bitwise_count(fp[x] ^ fp[y]) <= radius)
            forest.join(x[near], y[near])
            keep = ~small
            al, ah, bl, bh, err = al[keep], ah[keep], bl[keep], bh[keep], err[keep]
        if not len(al):
            continue
        am, bm = split(al, ah, bit), split(bl, bh, bit)
        same = al == bl
        nxt = [
            (al, am, bl, bm, err),
            (am, ah, bm, bh, err),
            (al, am, bm, bh, err + 1),
            (am[~same], ah[~same], bl[~same], bm[~same], err[~same] + 1),
        ]
        al, ah, bl, bh, err = (np.concatenate(x) for x in zip(*nxt, strict=True))
        keep = (err <= radius) & (ah > al) & (bh > bl) & ~((al == bl) & (ah - al == 1))
        al, ah, bl, bh, err = al[keep], ah[keep], bl[keep], bh[keep], err[keep]
        for i in range(0, len(al), FRONTIER):
            to = slice(i, i + FRONTIER)
            todo.append((bit - 1, al[to], ah[to], bl[to], bh[to], err[to]))
    root = forest.roots(np.arange(n))
    linked = np.flatnonzero(root != np.arange(n))
    return linked, root[linked]


def _masks(bits: list[int], radius: int, blocks: int) -> list[int]:
    """For every choice of ``blocks - radius`` of ``blocks`` runs of ``bits`` a mask of the chosen runs."""
    edges = [len(bits) * i // blocks for i in range(blocks + 1)]
    runs = [sum(1 << b for b in bits[i:j]) for i, j in zip(edges, edges[1:], strict=False)]
    return sorted({sum(pick) for pick in combinations(runs, blocks - radius)})


def _signed(mask: int) -> int:
    return mask - (1 << 64) if mask >> 63 else mask


def _keyed(rows: DataFrame, masks: dict[int, list[int]] | list[int]) -> DataFrame:
    """(mask, bucket, fp): rows once for each mask, all the same or by the mask they have now."""
    if isinstance(masks, list):
        choice = F.array(*[F.lit(_signed(m)).cast("long") for m in masks])
    else:
        choice = F.element_at(F.create_map(*[x for m, finer in masks.items() for x in (F.lit(_signed(m)).cast("long"), F.array(*[F.lit(_signed(f)).cast("long") for f in finer]))]), F.col("mask"))
    return rows.select("fp", F.explode(choice).alias("mask")).select("mask", F.col("fp").bitwiseAND(F.col("mask")).alias("bucket"), "fp")


def bucketed(distinct: DataFrame, radius: int, blocks: int) -> DataFrame:
    """(mask, bucket, fp): any two fingerprints within ``radius`` bits share a bucket, and no bucket is hot unless its bits run out."""
    masks = _masks(list(range(64)), radius, blocks)
    keyed, out = _keyed(distinct, masks), None
    while True:
        hot = keyed.groupBy("mask", "bucket").agg(F.count(F.lit(1)).alias("n")).where(F.col("n") > HOT).select("mask", "bucket")
        hot = materialise(hot, "hot-buckets")
        left = {m: [b for b in range(64) if not m >> b & 1] for m in masks}
        finer = {m: [m | f for f in _masks(bits, radius, radius + 1)] for m, bits in left.items() if len(bits) > radius}
        if not finer or hot.isEmpty():
            return keyed if out is None else out.unionByName(keyed)
        able = hot.where(F.col("mask").isin([_signed(m) for m in finer]))
        calm = keyed.join(able, ["mask", "bucket"], "left_anti")
        out = calm if out is None else out.unionByName(calm)
        # Whole buckets only are split: a bucket's fingerprints go on together, under masks of their own.
        keyed = _keyed(keyed.join(able, ["mask", "bucket"], "left_semi"), finer).distinct()
        masks = sorted({f for fs in finer.values() for f in fs})


def hamming_links(distinct: DataFrame, radius: int = 4, blocks: int | None = None) -> DataFrame:
    """(src, dst): links that connect exactly the distinct ``fp`` values within ``radius`` bits (a spanning forest of
    each bucket, so some links are replaced by a path of links)."""
    spark = distinct.sparkSession
    keyed = bucketed(distinct, radius, blocks or choose_blocks(distinct.count(), radius))
    dealt = keyed.repartition(partitions(spark), "mask", "bucket").sortWithinPartitions("mask", "bucket", "fp")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[np.ndarray] = []

        def out(parts: list[np.ndarray]):
            rows = np.concatenate(parts)
            # Signed order puts a bucket's set-top-bit half first: sort each bucket again as unsigned values.
            key = np.concatenate([[0], np.cumsum((rows[1:, :2] != rows[:-1, :2]).any(1))])
            fp = np.ascontiguousarray(rows[:, 2]).view(np.uint64)
            order = np.lexsort((fp, key))
            fp = fp[order]
            a, b = walk_tries(key, fp, radius)
            return pa.RecordBatch.from_arrays([pa.array(fp[a].view(np.int64)), pa.array(fp[b].view(np.int64))], names=["src", "dst"])

        size = 0
        for batch in batches:
            if not batch.num_rows:
                continue
            rows = np.column_stack([batch.column(i).to_numpy(zero_copy_only=False).astype(np.int64) for i in range(3)])
            turn = np.flatnonzero((rows[1:, :2] != rows[:-1, :2]).any(1)) + 1
            whole = not held or (held[-1][-1, :2] != rows[0, :2]).any()
            if size >= 1 << 18 and (whole or len(turn)):  # whole buckets leave; the last may go on in the next batch
                cut = int(turn[-1]) if len(turn) else 0
                yield out([*held, rows[:cut]])
                held, size, rows = [], 0, rows[cut:]
            held.append(rows)
            size += len(rows)
        if size:
            yield out(held)

    return dealt.mapInArrow(run, "src long, dst long").distinct()


def connect(links: DataFrame, rounds: int = 60) -> DataFrame:
    """(node, root): the smallest node reachable from each node of undirected ``links`` (long ``src``, ``dst``).

    Alternates two steps that point every node at ever smaller neighbours until nothing changes: larger neighbours are
    hung on the smallest of a node's neighbourhood, then smaller ones. Rounds grow with the logarithm of a group's
    diameter. Each round is written to the shared folder.
    """

    def hang(pairs: DataFrame, large: bool) -> DataFrame:
        """large: each node hands its larger neighbours the least of itself and its neighbours; else its smaller
        neighbours and itself."""
        both = pairs.select(F.col("a").alias("u"), F.col("b").alias("v"))
        if large:
            both = both.unionByName(pairs.select(F.col("b").alias("u"), F.col("a").alias("v")))
        else:
            both = both.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
        # Written, so that both sides of the join are exchanges and a hub's links are split over tasks.
        least = materialise(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")), "least")
        made.append(least)
        joined = both.join(least, "u")
        if large:
            return joined.where(F.col("v") > F.col("u")).select(F.col("v").alias("a"), F.col("m").alias("b")).distinct()
        hung = joined.select(F.col("v").alias("a"), F.col("m").alias("b")).union(joined.select(F.col("u").alias("a"), F.col("m").alias("b")))
        return hung.where("a <> b").distinct()

    pairs = materialise(links.where("src <> dst").select(F.col("src").alias("a"), F.col("dst").alias("b")).distinct(), "links")
    seen, made = None, []
    for _ in range(rounds):
        after = materialise(hang(hang(pairs, True), False), "links")
        row = after.agg(F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")).alias("s")).first()
        for done in (pairs, *made):
            discard(done)
        pairs, made = after, []
        if (row["n"], row["s"]) == seen:
            break
        seen = (row["n"], row["s"])
    else:
        raise RuntimeError(f"links not connected after {rounds} rounds")
    return pairs.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("root"))


def _rooted(own: DataFrame, radius: int, id_col: str) -> DataFrame:
    """(fp, least, root): distinct fingerprints, the smallest id of each, and the fingerprint that names its group."""
    distinct = materialise(own.groupBy("fp").agg(F.min(id_col).alias("least")), "distinct")
    roots = connect(hamming_links(distinct.select("fp"), radius))
    return distinct.join(roots.withColumnRenamed("node", "fp"), "fp", "left").select("fp", "least", F.coalesce("root", "fp").alias("root"))


def near_duplicates(docs: DataFrame, shingle: int = 4, radius: int = 4, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fp, component_id): every row with its fingerprint and the smallest id its links reach."""
    own = materialise(fingerprints(docs, shingle, (id_col,), text_col), "fingerprints")
    labelled = _rooted(own, radius, id_col)
    smallest = labelled.groupBy("root").agg(F.min("least").alias("component_id"))
    named = labelled.join(smallest, "root").select("fp", "component_id")
    return own.join(named, "fp").select(id_col, "fp", "component_id")


def keep_one(docs: DataFrame, shingle: int = 4, radius: int = 4) -> DataFrame:
    """One row of each group of near-duplicates, with all its columns: that of the smallest doc_id (null last; of equal ids one)."""
    text = F.coalesce("text", F.lit(""))
    keyed = sheltered(docs, "doc_id", "text").withColumn("_a", F.xxhash64("doc_id", text)).withColumn("_b", F.xxhash64(text, "doc_id", F.lit(1)))
    own = materialise(fingerprints(keyed, shingle, ("doc_id", "_a", "_b")), "fingerprints")
    labelled = _rooted(own, radius, "doc_id").select("fp", "root")
    order = F.struct(F.isnull("doc_id").alias("no_id"), "doc_id", "_a", "_b")
    winners = own.join(labelled, "fp").groupBy("root").agg(F.min(order).alias("w")).select("w._a", "w._b")
    # Identical rows have one key; the join leaves them side by side.
    first = Window.partitionBy("_a", "_b").orderBy("_a", "_b")
    kept = keyed.join(winners, ["_a", "_b"], "left_semi").withColumn("_n", F.row_number().over(first)).where("_n = 1")
    return restored(kept, docs, "doc_id", "text")
