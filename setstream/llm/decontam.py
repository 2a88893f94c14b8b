"""Verbatim overlap of documents with benchmark items, by suffix arrays of the documents.

Every run of documents of about ``SHARD_BYTES`` is a shard: its suffixes are sorted by prefix doubling and test windows are looked up by
binary search, all side by side. Words outside the benchmark's vocabulary can't be part of a match, so only
suffixes inside long enough runs of benchmark words enter the array, and of the windows only those whose first words some of these begin with
are searched; both drop no match. Texts never leave their task. Where a window is found, the document's suffix is looked up in the items'
own suffix array too, which gives its longest verbatim match and where that stands.

The benchmark side is broadcast in blocks of about ``ITEM_BYTES`` of text (its size is measured first), one after another: a block's
hits are written before the next block is collected, so the driver and the executors hold one at a time.
The rows of each block are narrow (rows with hits alone) and meet the documents in one join.

Edge cases: null or wordless documents have no words and no hits; null, wordless or null-id items have no windows; items with fewer
words than a window are one window; items that repeat count once by id; of equally long matches the first in the text counts, and of the items that hold it
the least by id, then place; very long texts are read whole; repeated documents each get a row; a doc_id is only
carried along; an empty table on either side gives an empty result or rows without hits; extra columns pass through unless they are
named like an output.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .runtime import materialise, restored, sheltered
from .text import ALNUM, LOWER, Words, chunks, mix, raw

#: Benchmark text that is broadcast at once; it takes some five times as much in memory, and 25 times while it is prepared.
ITEM_BYTES = 16 << 20
#: Text of documents whose suffixes are sorted together.
SHARD_BYTES = 8 << 20
#: Words that a window and a suffix have to begin with alike before they are compared.
LEAD = 4


def suffix_array(ids: np.ndarray, at: np.ndarray, depth: int) -> np.ndarray:
    """``at`` sorted by the ``depth`` word ids from each position on (0 past the end), by prefix doubling."""
    rank, step = ids.astype(np.int64), 1
    while step < depth:
        later = np.zeros_like(rank)
        later[:-step] = rank[step:]
        top = int(rank.max(initial=0)) + 1
        rank *= int(later.max(initial=0)) + 1
        rank += later
        del later
        order = np.argsort(rank, kind="stable")
        rank = rank[order]
        new = np.cumsum(np.r_[False, rank[1:] != rank[:-1]])
        rank[order] = new
        del order, new
        step *= 2
        if int(rank.max(initial=0)) + 1 == top:  # no rank has split: all are told apart, or equal to the end
            break
    return at[np.argsort(rank[at], kind="stable")]


def common_words(a: np.ndarray, x: np.ndarray, b: np.ndarray, y: np.ndarray, limit: int | None = None) -> np.ndarray:
    """How many words from ``a[x]`` and ``b[y]`` on agree, for each pair of positions; a 0 agrees with nothing."""
    out, open_, block = np.zeros(len(x), np.int64), np.arange(len(x)), 16
    while len(open_):
        steps = np.arange(block)
        p, q = x[open_] + out[open_], y[open_] + out[open_]
        left = a[np.minimum(p[:, None] + steps, len(a) - 1)]
        same = (left == b[np.minimum(q[:, None] + steps, len(b) - 1)]) & (left != 0)
        n = np.where(same.all(1), block, same.argmin(1))
        out[open_] += n
        open_ = open_[(n == block) & (True if limit is None else out[open_] < limit)]
    return out


class Windows:
    """The items as one array of word ids (0: an item's end), and their suffix array, in which equal windows are neighbours.

    ``lo``/``hi``: bounds of each distinct window's suffixes, ``length`` its words, ``word`` where it stands first in the text;
    ``lead``: a hash of its first ``LEAD`` words (0: it has fewer), ascending."""

    def __init__(self, item_ids: list[int], texts: pa.Array, width: int):
        hashes, counts = [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)]
        for a, b in chunks(texts):
            data, offsets = raw(texts.slice(a, b - a))
            words = Words(LOWER[data], offsets, ALNUM)
            hashes.append(words.hashes())
            counts.append(np.diff(words.first))
        hashes, sizes = np.concatenate(hashes), np.concatenate(counts)
        self.vocabulary = np.unique(hashes)
        self.width, n = width, len(hashes)
        place = (np.arange(n) + np.repeat(np.arange(len(sizes)), sizes)).astype(np.int32)
        self.ids = np.zeros(n + len(item_ids) + 1, np.int32)
        for i in range(0, n, 1 << 20):
            self.ids[place[i : i + (1 << 20)]] = np.searchsorted(self.vocabulary, hashes[i : i + (1 << 20)]) + 1
        del hashes
        before = np.cumsum(sizes) - sizes
        self.first = before + np.arange(len(item_ids))  # where each item begins
        self.item = np.array(item_ids, np.int64)
        left = (np.repeat(sizes + before, sizes) - np.arange(n)).astype(np.int32)
        whole = np.repeat(sizes, sizes)
        starts = (left >= width) | ((left == whole) & (left < width))
        del whole
        self.array = suffix_array(self.ids, place, int(sizes.max(initial=1)) + 1).astype(np.int32)
        begins, count = np.zeros(len(self.ids), bool), np.zeros(len(self.ids), np.int32)
        begins[place], count[place] = starts, np.minimum(left, width)
        ranked = self.array[begins[self.array]]
        long = count[ranked]
        # Windows in the suffix array's order are equal to their neighbours or to none.
        alike = np.zeros(max(0, len(ranked) - 1), bool)
        for i in range(0, len(alike), 1 << 16):
            a, b = ranked[i + 1 : i + 1 + (1 << 16)], ranked[i : i + len(alike[i : i + (1 << 16)])]
            alike[i : i + len(a)] = common_words(self.ids, a, self.ids, b, width) >= np.maximum(count[a], count[b])
        new = np.flatnonzero(np.r_[True, ~alike]) if len(ranked) else np.zeros(0, np.int64)
        lo, hi = new, np.append(new[1:], len(ranked))[: len(new)]
        self.ranked, length, word = ranked, long[new], ranked[new]
        lead = _lead(self.ids, word)
        lead[length < LEAD] = 0
        order = np.argsort(lead, kind="stable")
        self.lead, self.length, self.word = lead[order], length[order].astype(np.int16 if width < 1 << 15 else np.int64), word[order]
        self.lo, self.hi = lo[order].astype(np.int32), hi[order].astype(np.int32)
        self.shortest = int(self.length.min()) if len(new) else 0

    def __len__(self) -> int:
        return len(self.length)

    def items_of(self, window: int) -> np.ndarray:
        at = self.ranked[self.lo[window] : self.hi[window]]
        return np.unique(self.item[np.searchsorted(self.first, at, "right") - 1])

    def longest(self, ids: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """For each position of ``ids`` the length of its longest match in any item, and the least place in the suffix array with that."""
        lo, hi = np.zeros(len(at), np.int64), np.full(len(at), len(self.array), np.int64)
        while (open_ := np.flatnonzero(lo < hi)).size:
            mid = (lo[open_] + hi[open_]) // 2
            there = self.array[mid].astype(np.int64)
            n = common_words(ids, at[open_], self.ids, there)
            below = self.ids[np.minimum(there + n, len(self.ids) - 1)] < ids[np.minimum(at[open_] + n, len(ids) - 1)]
            lo[open_[below]] = mid[below] + 1
            hi[open_[~below]] = mid[~below]
        best, where = np.zeros(len(at), np.int64), np.zeros(len(at), np.int64)
        for side in (lo - 1, lo):
            fits = np.flatnonzero((side >= 0) & (side < len(self.array)))
            n = np.zeros(len(at), np.int64)
            n[fits] = common_words(ids, at[fits], self.ids, self.array[side[fits]].astype(np.int64))
            better = n > best
            best, where = np.where(better, n, best), np.where(better, side, where)
        return best, where

    def source(self, rank: int, n: int) -> tuple[int, int]:
        """(item_id, word) of the least item that holds the first ``n`` words of a suffix given by its place in the suffix array."""
        def edge(step: int) -> int:
            at, jump = rank, 1
            same = lambda i: 0 <= i < len(self.array) and int(common_words(self.ids, self.array[i : i + 1].astype(np.int64), self.ids, self.array[rank : rank + 1].astype(np.int64), n)[0]) >= n
            while same(at + step * jump):  # equal beginnings are one run of the array
                at, jump = at + step * jump, 2 * jump
            while jump:
                if same(at + step * jump):
                    at += step * jump
                jump //= 2
            return at

        held = self.array[edge(-1) : edge(1) + 1]
        item = np.searchsorted(self.first, held, "right") - 1
        i = np.lexsort((held - self.first[item], self.item[item]))[0]
        return int(self.item[item[i]]), int(held[i] - self.first[item[i]])


def _lead(ids: np.ndarray, at: np.ndarray) -> np.ndarray:
    """A hash of the ``LEAD`` word ids from each position on, never 0."""
    h = np.zeros(len(at), np.uint64)
    for i in range(LEAD):
        h = mix(h * np.uint64(3) + ids[np.minimum(at + i, len(ids) - 1)].astype(np.uint64) + np.uint64(1))
    return h | np.uint64(1)


def occurrences(ids: np.ndarray, array: np.ndarray, windows: Windows, which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Bounds in the suffix array of the suffixes that begin with each of the windows ``which`` (binary search, all at once)."""
    steps = np.arange(windows.width)
    reach = np.concatenate([ids, np.zeros(windows.width, ids.dtype)])
    wanted = windows.ids[np.minimum(windows.word[which][:, None] + steps, len(windows.ids) - 1)]
    used = steps < windows.length[which][:, None]

    def bound(after: bool) -> np.ndarray:
        lo, hi = np.zeros(len(which), np.int64), np.full(len(which), len(array), np.int64)
        while (open_ := np.flatnonzero(lo < hi)).size:
            mid = (lo[open_] + hi[open_]) // 2
            words = reach[array[mid][:, None] + steps]
            differ = (words != wanted[open_]) & used[open_]
            first = differ.argmax(1)
            rows = np.arange(len(open_))
            sign = np.where(differ[rows, first], np.sign(words[rows, first] - wanted[open_][rows, first]), 0)
            right = (sign < 0) | (after & (sign == 0))
            lo[open_[right]] = mid[right] + 1
            hi[open_[~right]] = mid[~right]
        return lo

    return bound(False), bound(True)


class Shard:
    """Hits of all windows in a run of documents: ``n_words`` of each document, spans (``span_doc``, ``span_from``, ``span_to``), ``pairs`` of
    (document, item), and the longest match of every document that has one (``matched``, ``match`` rows of length, place, item, item's place)."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, windows: Windows):
        words = Words(LOWER[data], offsets, ALNUM)
        n_docs, none = len(offsets) - 1, np.zeros(0, np.int64)
        self.n_words = np.diff(words.first)
        self.span_doc = self.span_from = self.span_to = self.matched = none
        self.pairs, self.match = np.zeros((0, 2), np.int64), np.zeros((0, 4), np.int64)
        if not len(words) or not len(windows):
            return
        h = words.hashes()
        found = np.minimum(np.searchsorted(windows.vocabulary, h), len(windows.vocabulary) - 1)
        place = np.arange(len(h)) + words.doc  # a 0 stands after each document's words
        ids = np.zeros(int(place[-1]) + 2, np.int32)
        ids[place] = np.where(windows.vocabulary[found] == h, found + 1, 0)
        # Distance from each position to the next word that isn't in the vocabulary: the reach of any match from there.
        stop = np.where(ids == 0, np.arange(len(ids)), len(ids))
        reach = np.minimum.accumulate(stop[::-1])[::-1] - np.arange(len(ids))
        at = np.flatnonzero(reach >= windows.shortest)
        # Suffixes that begin like some window, or are short enough for the windows of fewer words.
        lead = _lead(ids, at)
        slot = np.minimum(np.searchsorted(windows.lead, lead), len(windows) - 1)
        few = int(np.searchsorted(windows.lead, 1))  # windows of fewer words than LEAD
        alike = (windows.lead[slot] == lead) & (reach[at] >= LEAD)
        which = np.concatenate([np.arange(few), _runs(windows.lead, np.unique(lead[alike]))])
        at = at if few else at[alike]
        if not len(at) or not len(which):
            return
        # Only the runs of words that hold a candidate suffix are sorted.
        inside = np.zeros(len(ids) + 1, np.int64)
        np.add.at(inside, at, 1)
        np.add.at(inside, at + reach[at], -1)
        covered = np.cumsum(inside[:-1]) > 0
        keep = np.flatnonzero(covered | np.r_[False, covered[:-1]])
        back = np.full(len(ids), -1, np.int64)
        back[keep] = np.arange(len(keep))
        array = suffix_array(ids[keep], back[at], windows.width)
        lo, hi = occurrences(ids[keep], array, windows, which)
        hit = np.flatnonzero(hi > lo)
        if not len(hit):
            return
        doc_at = np.zeros(len(ids), np.int64)
        doc_at[place] = words.doc
        count = (hi - lo)[hit]
        start = keep[array[np.repeat(lo[hit], count) + _count(count)]]
        of = np.repeat(which[hit], count)
        cover = np.zeros(len(ids) + 1, np.int64)
        np.add.at(cover, start, 1)
        np.add.at(cover, start + windows.length[of].astype(np.int64), -1)
        edge = np.diff(np.concatenate([[0], (np.cumsum(cover[:-1]) > 0).astype(np.int8), [0]]))
        s, e = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
        self.span_doc = doc_at[s]
        origin = words.first[:-1] + np.arange(n_docs)
        self.span_from, self.span_to = s - origin[self.span_doc], e - origin[self.span_doc]
        once = np.unique(of * n_docs + doc_at[start])
        w, d = once // n_docs, once % n_docs
        items = {int(i): windows.items_of(i) for i in np.unique(w)}
        self.pairs = np.unique(np.column_stack([np.repeat(d, [len(items[i]) for i in w.tolist()]), np.concatenate([items[i] for i in w.tolist()])]), axis=0)
        self._longest(ids, np.unique(start), doc_at, origin, windows)

    def _longest(self, ids: np.ndarray, start: np.ndarray, doc_at: np.ndarray, origin: np.ndarray, windows: Windows) -> None:
        n, rank = windows.longest(ids, start)
        doc = doc_at[start]
        order = np.lexsort((start, -n, doc))
        best = order[np.r_[True, doc[order][1:] != doc[order][:-1]]]
        known: dict[tuple[int, int], tuple[int, int]] = {}
        rows = []
        for i in best.tolist():
            key = int(rank[i]), int(n[i])
            if key not in known:
                known[key] = windows.source(*key)
            rows.append((int(n[i]), int(start[i] - origin[doc[i]]), *known[key]))
        self.matched, self.match = doc[best], np.array(rows, np.int64)


def _runs(ascending: np.ndarray, values: np.ndarray) -> np.ndarray:
    """Positions of all of ``ascending`` that are one of ``values``."""
    lo, hi = np.searchsorted(ascending, values), np.searchsorted(ascending, values, "right")
    return np.repeat(lo, hi - lo) + _count(hi - lo)


def _count(sizes: np.ndarray) -> np.ndarray:
    return np.arange(sizes.sum()) - np.repeat(np.cumsum(sizes) - sizes, sizes)


def _lists(owner: np.ndarray, values: pa.Array, n: int) -> pa.ListArray:
    return pa.ListArray.from_arrays(pa.array(np.searchsorted(owner, np.arange(n + 1)), pa.int32()), values)


_LONG = T.LongType()
OUTPUT = [
    T.StructField("n_words", _LONG, False),
    T.StructField("spans", T.ArrayType(T.StructType([T.StructField("from_word", _LONG), T.StructField("to_word", _LONG)]))),
    T.StructField("item_ids", T.ArrayType(_LONG)),
    T.StructField("longest", T.StructType([T.StructField(c, _LONG) for c in ("words", "from_word", "item_id", "item_word")])),
]


def _pass(docs: DataFrame, rest: list[str], text_col: str, shared) -> DataFrame:
    """``docs`` with what one broadcast block of windows finds."""
    schema = T.StructType([docs.schema[c] for c in rest] + OUTPUT)
    names = [*rest, *(f.name for f in OUTPUT)]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column(len(rest))
            for a, b in chunks(column, SHARD_BYTES):
                found = Shard(*raw(column.slice(a, b - a)), shared.value)
                spans = pa.StructArray.from_arrays([pa.array(found.span_from), pa.array(found.span_to)], names=["from_word", "to_word"])
                place, has = np.zeros(b - a, np.int64), np.zeros(b - a, bool)
                place[found.matched], has[found.matched] = np.arange(len(found.matched)), True
                match = found.match[place] if len(found.matched) else np.zeros((b - a, 4), np.int64)
                longest = pa.StructArray.from_arrays([pa.array(match[:, i]) for i in range(4)], names=["words", "from_word", "item_id", "item_word"], mask=pa.array(~has))
                own = [pa.array(found.n_words), _lists(found.span_doc, spans, b - a), _lists(found.pairs[:, 0], pa.array(np.ascontiguousarray(found.pairs[:, 1])), b - a), longest]
                kept = [batch.column(i).slice(a, b - a) for i in range(len(rest))]
                yield pa.RecordBatch.from_arrays([*kept, *own], names=names)

    return docs.select(*rest, text_col).mapInArrow(run, schema)


def overlaps(docs: DataFrame, items: DataFrame, width: int = 10, text_col: str = "text", keep_text: bool = False) -> DataFrame:
    """``docs`` with ``n_words``, ``spans`` (maximal runs of words inside occurrences of item windows, ends exclusive), the ascending
    ``item_ids`` that occur, and ``longest``: the longest verbatim match that begins at a hit (its words, where it begins, the item and where
    in it; null without hits). The text stays only if ``keep_text``."""
    spark = docs.sparkSession
    if keep_text:
        docs = docs.withColumn("_searched", F.col(text_col))
        text_col = "_searched"
    rest = [c for c in docs.columns if c != text_col and c not in [f.name for f in OUTPUT]]
    items = items.where("item_id is not null and text is not null").select(F.col("item_id").cast("long").alias("item_id"), "text")
    size = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    blocks = int(size // ITEM_BYTES) + 1

    def block(i: int):
        part = items if blocks == 1 else items.where(F.pmod(F.xxhash64("item_id"), F.lit(blocks)) == i)
        ids, texts = [], []
        for r in part.toLocalIterator():  # ITEM_BYTES on average, see above
            ids.append(r[0])
            texts.append(r[1])
        return spark.sparkContext.broadcast(Windows(ids, pa.array(texts, pa.large_string()), width))

    if blocks == 1:
        return _pass(docs, rest, text_col, block(0))
    # More than one pass: rows are told apart by a number of their own, written once.
    numbered = materialise(docs.withColumn("_row", F.monotonically_increasing_id()), "decontam")
    found = None
    for i in range(blocks):
        shared = block(i)
        one = _pass(numbered.select("_row", text_col), ["_row"], text_col, shared)
        # The first pass counts every row's words; later ones leave the rows with hits.
        one = materialise(one if i == 0 else one.where(F.size("spans") > 0), "decontam-block")
        shared.destroy()
        found = one if found is None else found.unionByName(one)
    order = F.struct(-F.col("longest.words"), F.col("longest.from_word"), F.col("longest.item_id"), F.col("longest.item_word"))
    merged = found.groupBy("_row").agg(
        F.max("n_words").alias("n_words"),
        merge_spans(F.flatten(F.collect_list("spans"))).alias("spans"),
        F.array_sort(F.array_distinct(F.flatten(F.collect_list("item_ids")))).alias("item_ids"),
        F.min_by("longest", F.when(F.col("longest").isNotNull(), order)).alias("longest"),
    )
    return numbered.select("_row", *rest).join(merged, "_row").drop("_row")


def merge_spans(spans):
    """Overlapping or touching spans as one, in order: a span opens a run if all before it end before it begins."""
    kind = "array<struct<from_word:bigint,to_word:bigint>>"

    def add(done, span):
        last = done["last"]
        grown = F.struct(last["from_word"].alias("from_word"), F.greatest(last["to_word"], span["to_word"]).alias("to_word"))
        apart = last.isNull() | (span["from_word"] > last["to_word"])
        kept = F.when(apart & last.isNotNull(), F.concat(done["spans"], F.array(last))).otherwise(done["spans"])
        return F.struct(kept.alias("spans"), F.when(apart, span).otherwise(grown).alias("last"))

    start = F.struct(F.array().cast(kind).alias("spans"), F.lit(None).cast("struct<from_word:bigint,to_word:bigint>").alias("last"))
    return F.aggregate(F.array_sort(spans), start, add, lambda done: F.when(done["last"].isNull(), done["spans"]).otherwise(F.concat(done["spans"], F.array(done["last"]))))


def hit_words(spans):
    return F.aggregate(spans, F.lit(0).cast("long"), lambda n, s: n + s["to_word"] - s["from_word"])


def decontaminate(docs: DataFrame, items: DataFrame, width: int = 10) -> DataFrame:
    """The documents that hold no window of any item, with their own columns."""
    found = overlaps(sheltered(docs, "text"), items, width, keep_text=True)
    return restored(found.where(F.size("item_ids") == 0), docs, "text")
