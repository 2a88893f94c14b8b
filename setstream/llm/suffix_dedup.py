"""Passages that occur more than once, by sparse suffix arrays.

Of every ``length`` consecutive words the ``gram``-word run with the least hash is the window's anchor, so equal windows
have their anchors at the same place in them: only suffixes that begin at anchors are kept (about one word in 16). They are dealt out by
their first ``gram`` words, and those alone with theirs are dropped. Each task sorts its suffixes by their words, compares neighbours, and so
has the longest common prefix of any two as a run's least; the words before the anchors, read backwards, are sorted and compared the same way.
A window that reaches ``left`` words before its anchor occurs again if another suffix shares those and the ``length - left`` words after it: both are
look-ups in the two orders. That extends every match to the left and right without ever forming pairs.
Sorting and comparing is by words (words over ``LONG_WORD`` bytes by a 128-bit digest); hashes only choose anchors and tasks.

A run of words that begins more than ``HOT`` suffixes would be one task's load. Its windows are grouped instead, by 128-bit digests of their words, as
an aggregation with partial sums; both ways give the same rows.

Texts are compared once for each distinct text; copies of a whole text are counted, not compared.

Edge cases: null and empty texts, and texts of fewer than ``length`` words, have no passage; very long texts are read whole; repeated
rows are copies; null doc_ids take no part in ``first_doc_id``; an empty table gives an empty result; extra columns are
ignored, and kept by ``drop_repeats``.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .runtime import discard, materialise, partitions, restored, sheltered
from .text import NOT_BLANK, Words, chunks, raw, rolling

#: Words of more bytes stand for themselves by a digest of 32 characters.
LONG_WORD = 48
#: Rows of one run of leading words that one task may sort; those of a more frequent run are aggregated.
HOT = 256
#: Repeated windows of hot runs that are broadcast; more are joined by shuffle, which can be split.
BROADCAST_WINDOWS = 200_000
#: Suffixes that are sorted at once (whole runs of equal leading words; a run has ``HOT`` at most).
SORTED = 1 << 15
NONE = np.iinfo(np.int64).max


class Anchors:
    """Anchors of a run of texts: ``window`` first words of all windows, ``anchor`` the anchor of each, ``gram`` hashes."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray, length: int, gram: int):
        words = self.words = Words(data, offsets, NOT_BLANK)
        self.gram = rolling(words.hashes(), gram)
        last = len(words) - length + 1
        if last <= 0:
            self.window = self.anchor = np.zeros(0, np.int64)
            return
        self.window = np.flatnonzero(words.doc[:last] == words.doc[length - 1 :])
        # Least of each run of `span` gram hashes (leftmost on ties), by doubling.
        span = length - gram + 1
        best, at, width = self.gram.copy(), np.arange(len(self.gram)), 1
        while width * 2 <= span:
            best, at = _least(best[:-width], at[:-width], best[width:], at[width:])
            width *= 2
        if width < span:
            d = span - width
            best, at = _least(best[:-d], at[:-d], best[d:], at[d:])
        self.anchor = at[self.window]


def _least(a, at_a, b, at_b):
    right = b < a
    return np.where(right, b, a), np.where(right, at_b, at_a)


def _anchor_rows(docs: DataFrame, length: int, gram: int) -> DataFrame:
    """(doc_id, digest, n_words, anchors[(at, gram)])"""
    schema = "doc_id long, digest binary, n_words long, at array<int>, gram array<long>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column(2)
            for a, b in chunks(column):
                found = Anchors(*raw(column.slice(a, b - a)), length, gram)
                first = found.words.first
                at = np.unique(found.anchor)
                edge = pa.array(np.searchsorted(at, first), pa.int32())
                place = (at - first[found.words.doc[at]]).astype(np.int32)
                yield pa.RecordBatch.from_arrays(
                    [
                        batch.column(0).slice(a, b - a),
                        batch.column(1).slice(a, b - a),
                        pa.array(np.diff(first)),
                        pa.ListArray.from_arrays(edge, pa.array(place)),
                        pa.ListArray.from_arrays(edge, pa.array(found.gram[at].view(np.int64))),
                    ],
                    names=["doc_id", "digest", "n_words", "at", "gram"],
                )

    return docs.select("doc_id", "digest", "text").mapInArrow(run, schema)


#: Rows of suffixes that are sorted (``words``, of which ``before`` stand before the anchor) and of windows that are grouped (``window``).
PIECES = "digest binary, first_doc long, at int, gram long, before int, words string, window binary"


def _pieces(texts: DataFrame, length: int, gram: int) -> DataFrame:
    """The words around every anchor in ``at``, or, where it is ``hot``, the digest of every window that it is the anchor of."""
    import xxhash

    names = [c.split()[0] for c in PIECES.split(", ")]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column(4)
            for a, b in chunks(column):
                found = Anchors(*raw(column.slice(a, b - a)), length, gram)
                if not len(found.window):
                    continue
                words, first = found.words, found.words.first
                view = words.data.tobytes()
                spelt = [view[i:j] for i, j in zip(words.start.tolist(), words.end.tolist(), strict=True)]
                for i in np.flatnonzero(words.end - words.start > LONG_WORD).tolist():
                    spelt[i] = xxhash.xxh3_128_hexdigest(spelt[i]).encode()
                place = np.cumsum(np.fromiter((len(w) + 1 for w in spelt), np.int64, len(spelt)))
                place, joined = np.concatenate([[0], place]), b" ".join(spelt)
                lists = [batch.column(i).slice(a, b - a) for i in (2, 3)]
                counts = lists[0].value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
                anchor = lists[0].flatten().to_numpy(zero_copy_only=False) + np.repeat(first[:-1], counts)
                hot = np.zeros(len(words), bool)
                hot[anchor] = lists[1].flatten().to_numpy(zero_copy_only=False).astype(bool)
                cold = np.unique(anchor[~hot[anchor]])
                start = np.maximum(cold - (length - gram), first[words.doc[cold]])
                end = np.minimum(cold + length, first[words.doc[cold] + 1])
                around = [joined[i:j] for i, j in zip(place[start].tolist(), (place[end] - 1).tolist(), strict=True)]
                window = found.window[hot[found.anchor]]
                digests = [xxhash.xxh3_128_digest(joined[i:j]) for i, j in zip(place[window].tolist(), (place[window + length] - 1).tolist(), strict=True)]
                at = np.concatenate([cold, window])
                doc, n = words.doc[at], len(cold)
                own, tail = pa.array(doc + a), np.zeros(len(window), np.int64)
                arrays = [
                    batch.column(0).take(own),
                    batch.column(1).take(own),
                    pa.array((at - first[doc]).astype(np.int32)),
                    pa.array(np.concatenate([found.gram[cold].view(np.int64), tail])),
                    pa.array(np.concatenate([cold - start, tail]).astype(np.int32)),
                    pa.array([*around, *[None] * len(window)], pa.binary()).cast(pa.string(), safe=False),
                    pa.array([*[None] * n, *digests], pa.binary()),
                ]
                yield pa.RecordBatch.from_arrays(arrays, names=names)

    return texts.select("digest", "first_doc", F.col("anchors.at").alias("at"), F.col("anchors.hot").alias("hot"), "text").mapInArrow(run, PIECES)


def common(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(order, shared): the rows of word ids in ascending order, and with how many leading words each agrees with the one before it.
    Ids below 0 (past a text's end) agree with none."""
    # Big-endian bytes compare like the ids they spell.
    key = np.ascontiguousarray((rows + 1).astype(">u4"))
    order = np.argsort(key.view(f"S{4 * rows.shape[1]}").ravel(), kind="stable") if rows.size else np.arange(len(rows))
    ranked = rows[order]
    same = (ranked[1:] == ranked[:-1]) & (ranked[1:] >= 0)
    shared = np.where(same.all(1), rows.shape[1], same.argmin(1))
    return order, np.concatenate([[0], shared]).astype(np.int64)


def repeated_runs(words: pa.Array, before: np.ndarray, text: np.ndarray, doc: np.ndarray, length: int, gram: int) -> tuple[np.ndarray, ...]:
    """(row, from, to, least): windows that occur in another text too, as runs of window starts relative to their anchor, for suffixes
    given by the words around them, the number of words before, a number for their text and its least doc_id."""
    left, n = length - gram, len(before)
    parts = pc.split_pattern(words, " ")
    counts = parts.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    ids = parts.flatten().dictionary_encode().indices.to_numpy(zero_copy_only=False).astype(np.int64)
    around = np.full((n, left + length), -1, np.int64)
    row = np.repeat(np.arange(n), counts)
    inside = np.arange(len(ids)) - np.repeat(np.cumsum(counts) - counts, counts)
    around[row, left - before[row] + inside] = ids
    order, shared = common(around[:, left:])
    back, shared_back = common(around[:, left - 1 :: -1] if left else around[:, :0])
    first, last = -before, np.minimum(counts - before - length, 0)  # starts of windows within the text
    hit = np.zeros((n, left + 1), bool)
    least = np.full((n, left + 1), NONE)
    own, own_back = np.zeros(n, np.int64), np.zeros(n, np.int64)
    for reach in range(left + 1):
        fits = np.flatnonzero((first <= -reach) & (-reach <= last))
        if not len(fits):
            continue
        # Suffixes that agree on the words after the anchor, and on those before, are neighbours in the two orders.
        own[order] = np.cumsum(shared < length - reach)
        own_back[back] = np.cumsum(shared_back < reach)
        key = own[fits] * (n + 1) + own_back[fits]
        sort = np.argsort(key, kind="stable")
        key, rows = key[sort], fits[sort]
        edge = np.flatnonzero(np.r_[True, key[1:] != key[:-1]])
        several = np.minimum.reduceat(text[rows], edge) != np.maximum.reduceat(text[rows], edge)
        group = np.cumsum(np.r_[False, key[1:] != key[:-1]])
        again = several[group]
        hit[rows[again], left - reach] = True
        least[rows[again], left - reach] = np.minimum.reduceat(doc[rows], edge)[group[again]]
    padded = np.zeros((n, left + 3), np.int8)
    padded[:, 1:-1] = hit
    turn = np.diff(padded, axis=1)
    row, begin = np.nonzero(turn == 1)
    end = np.nonzero(turn == -1)[1]
    flat = np.append(least.ravel(), NONE)
    cuts = np.column_stack([row * (left + 1) + begin, row * (left + 1) + end]).ravel()
    low = np.minimum.reduceat(flat, cuts)[::2] if len(row) else np.zeros(0, np.int64)
    return row, begin - left, end - 1 - left, low


RUNS = "digest binary, start int, last int, least long"


def _sorted_runs(pieces: DataFrame, length: int, gram: int) -> DataFrame:
    """(digest, start, last, least): runs of window starts that occur in another text, for rows sorted by gram within each task."""
    names = [c.split()[0] for c in RUNS.split(", ")]

    def solve(part: pa.Table) -> pa.RecordBatch:
        part = part.combine_chunks()
        column = {c: part.column(c).combine_chunks() for c in part.column_names}
        text = column["digest"].dictionary_encode().indices.to_numpy(zero_copy_only=False).astype(np.int64)
        doc = column["first_doc"].fill_null(NONE).to_numpy(zero_copy_only=False)
        before, at = (column[c].to_numpy(zero_copy_only=False).astype(np.int64) for c in ("before", "at"))
        row, begin, end, least = repeated_runs(column["words"], before, text, doc, length, gram)
        arrays = [column["digest"].take(pa.array(row)), pa.array((at[row] + begin).astype(np.int32)), pa.array((at[row] + end).astype(np.int32)), pa.array(least, mask=least == NONE)]
        return pa.RecordBatch.from_arrays(arrays, names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []
        for batch in batches:
            at = 0
            while at < batch.num_rows:
                part = batch.slice(at, SORTED)
                at += part.num_rows
                held.append(part)
                if sum(x.num_rows for x in held) >= SORTED:
                    grams = part.column(1).to_numpy(zero_copy_only=False)
                    cut = int(np.argmax(grams == grams[-1]))  # the last run may go on
                    if cut:
                        yield solve(pa.Table.from_batches([*held[:-1], part.slice(0, cut)]))
                        held = [part.slice(cut)]
        if held:
            yield solve(pa.Table.from_batches(held))

    return pieces.select("digest", "gram", "first_doc", "at", "before", "words").mapInArrow(run, RUNS)


def repeated_passages(docs: DataFrame, length: int = 50, gram: int = 20) -> DataFrame:
    """(doc_id, from_word, to_word, first_doc_id): one row for each maximal span of words, in each document, that is covered by windows of
    ``length`` words which another document holds too; ``first_doc_id`` is the least doc_id that holds one of them."""
    return _located(docs, length, gram).drop("digest")


def _digest(text):
    return F.substring(F.unhex(F.sha2(text, 256)), 1, 16)


def _located(docs: DataFrame, length: int, gram: int) -> DataFrame:
    """The rows of ``repeated_passages`` with ``digest``, which tells the texts of repeated doc_ids apart."""
    spark = docs.sparkSession
    text = F.coalesce(F.col("text"), F.lit(""))
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), _digest(text).alias("digest"), text.alias("text"))
    anchored = materialise(_anchor_rows(docs, length, gram), "anchored")
    texts = materialise(anchored.where(F.col("n_words") >= length).groupBy("digest").agg(F.min("doc_id").alias("first_doc"), F.count(F.lit(1)).alias("copies")), "texts")
    rows = anchored.where(F.size("at") > 0).select("digest", F.explode(F.arrays_zip("at", "gram")).alias("x")).select("digest", F.col("x.at").alias("at"), F.col("x.gram").alias("gram"))
    # A gram is repeated if two texts have it. Copies of a text have the same digest; they count for ``hot`` alone, which need not be exact.
    spread = rows.groupBy("gram").agg(F.min("digest").alias("a"), F.max("digest").alias("b"), (F.count(F.lit(1)) > HOT).alias("hot")).where("a <> b")
    grams = materialise(spread.select("gram", "hot"), "grams")
    # Both sides of the join are exchanges, so that a gram with many places is split over tasks.
    kept = rows.join(grams, "gram").groupBy("digest").agg(F.collect_set(F.struct("at", "hot")).alias("anchors"))
    kept = materialise(kept.join(texts, "digest").select("digest", "first_doc", "anchors"), "kept-anchors")
    # The text goes to its anchors once; one document stands for all copies.
    mine = docs.join(kept.hint("shuffle_hash"), "digest").where(F.col("doc_id").eqNullSafe(F.col("first_doc")))
    pieces = materialise(_pieces(mine, length, gram), "pieces")
    dealt = pieces.where("words is not null").repartition(partitions(spark), "gram").sortWithinPartitions("gram")
    runs = _sorted_runs(dealt, length, gram)
    grouped = pieces.where("window is not null")
    shared = grouped.groupBy("window").agg(F.min("digest").alias("a"), F.max("digest").alias("b"), F.min("first_doc").alias("least")).where("a <> b")
    again = materialise(shared.select("window", "least"), "repeated")
    few = again.limit(BROADCAST_WINDOWS + 1).count() <= BROADCAST_WINDOWS
    hits = grouped.join(F.broadcast(again) if few else again, "window").select("digest", F.col("at").alias("start"), F.col("at").alias("last"), "least")
    found = materialise(runs.unionByName(hits), "runs")
    spans = materialise(_merged(found.groupBy("digest").agg(F.array_sort(F.collect_list(F.struct("start", "last", "least"))).alias("hits")), length), "spans")
    for done in (pieces, again, found, kept, grams):
        discard(done)
    known = materialise(texts.join(spans, "digest", "left").where("copies > 1 or spans is not null"), "known")
    least = F.array_min(F.transform("spans", lambda s: s["first_doc_id"]))
    # Both sides are read as written: copies of one text meet its spans in a join that can be split.
    ranges = anchored.where(F.col("n_words") >= length).select("doc_id", "digest", "n_words").join(known, "digest")
    whole = F.array(F.struct(F.lit(0).alias("from_word"), F.col("n_words").cast("int").alias("to_word"), F.least("first_doc", least).alias("first_doc_id")))
    out = ranges.select("doc_id", "digest", F.explode(F.when(F.col("copies") > 1, whole).otherwise(F.col("spans"))).alias("s"))
    return out.select("doc_id", "digest", F.col("s.from_word").cast("long").alias("from_word"), F.col("s.to_word").cast("long").alias("to_word"), F.col("s.first_doc_id").alias("first_doc_id"))


def _merged(hits: DataFrame, length: int) -> DataFrame:
    """(digest, spans): the runs of window starts of each text, ascending, as maximal spans."""
    schema = "digest binary, spans array<struct<from_word:int,to_word:int,first_doc_id:long>>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            column = batch.column(1)
            rows = column.value_lengths().to_numpy(zero_copy_only=False)
            flat = column.flatten()
            if not len(flat):
                continue
            start, last = (flat.field(i).to_numpy(zero_copy_only=False).astype(np.int64) for i in (0, 1))
            least = flat.field(2).fill_null(NONE).to_numpy(zero_copy_only=False)
            row = np.repeat(np.arange(len(rows)), rows)
            # The farthest end so far within each row: rows are set apart by more than any end.
            apart = row * (int(last.max()) + length + 2)
            reach = np.maximum.accumulate(apart + last + length) - apart
            new = np.flatnonzero(np.r_[True, (start[1:] > reach[:-1]) | (row[1:] != row[:-1])])
            end = reach[np.r_[new[1:], len(start)] - 1]
            first = np.minimum.reduceat(least, new)
            spans = pa.StructArray.from_arrays(
                [pa.array(start[new].astype(np.int32)), pa.array(end.astype(np.int32)), pa.array(first, mask=first == NONE)], names=["from_word", "to_word", "first_doc_id"]
            )
            edge = pa.array(np.searchsorted(row[new], np.arange(len(rows) + 1)), pa.int32())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(edge, spans)], names=["digest", "spans"])

    return hits.select("digest", "hits").mapInArrow(run, schema)


def drop_repeats(docs: DataFrame, length: int = 50, gram: int = 20) -> DataFrame:
    """``docs`` with later occurrences of repeated passages cut out of ``text`` (words joined by one space where a cut was made); rows of the
    document named by ``first_doc_id`` keep theirs."""
    own = sheltered(docs, "doc_id", "text").withColumn("_digest", _digest(F.coalesce("text", F.lit(""))))
    later = _located(own.select("doc_id", "text"), length, gram).where("not (doc_id <=> first_doc_id)")
    cuts = later.groupBy(F.col("doc_id").alias("_id"), F.col("digest").alias("_of")).agg(F.array_sort(F.collect_set(F.struct("from_word", "to_word"))).alias("_cut"))
    words = F.filter(F.split("text", r"[\x20\x09-\x0D]+"), lambda w: w != "")
    left = F.filter(words, lambda w, i: ~F.exists("_cut", lambda s: (i >= s["from_word"]) & (i < s["to_word"])))
    joined = own.join(cuts, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("_digest") == F.col("_of")), "left")
    cut = joined.withColumn("text", F.when(F.col("_cut").isNull(), F.col("text")).otherwise(F.array_join(left, " ")))
    return restored(cut, docs, "doc_id", "text")
