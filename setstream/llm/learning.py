"""Labelled samples for the classifiers: bounded, the same for every run, and free of held-out rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Labelled documents that a classifier is fitted on, of each label value, at most.
SAMPLE_ROWS = 4000
#: Bytes of text that a classifier is fitted on, at most; whole texts in hash order of doc_id until full.
SAMPLE_BYTES = 16 << 20
#: Labelled documents of more bytes are not fitted on (they are scored whole like any other).
SAMPLE_LENGTH = 8192


def is_held_out(doc_id: Column) -> Column:
    return F.coalesce(F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def training_sample(docs: DataFrame, labels: DataFrame, label: str, rows: int = SAMPLE_ROWS, size: int = SAMPLE_BYTES) -> tuple[list[str], list[int]]:
    """Texts and 0/1 labels of at most ``rows`` documents for each label, none of them held out.

    The ids are chosen on the narrow labels table (a bounded top-k by hash), and only their texts are read to the driver.
    Rows without a doc_id, label or text are passed over; of repeated ids the least label and text count.
    """
    usable = labels.where(F.col("doc_id").isNotNull() & F.col(label).isin(0, 1) & ~is_held_out(F.col("doc_id")))
    known = usable.select("doc_id", F.col(label).cast("int").alias("_label"))
    ids = None
    for value in (0, 1):
        part = known.where(F.col("_label") == value).distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(rows)
        ids = part if ids is None else ids.unionByName(part)
    ids = ids.groupBy("doc_id").agg(F.min("_label").alias("_label"))
    texts = docs.where(F.octet_length("text") <= SAMPLE_LENGTH).select("doc_id", "text").join(F.broadcast(ids), "doc_id")  # at most 2 * rows ids
    once = texts.groupBy("doc_id", "_label").agg(F.min("text").alias("text"))
    got = sorted(once.collect(), key=lambda r: hash_order(r["doc_id"]))
    out_texts, out_labels, used = [], [], 0
    for r in got:
        used += len(r["text"].encode())
        if out_texts and used > size:
            break
        out_texts.append(r["text"])
        out_labels.append(r["_label"])
    return out_texts, out_labels


def hash_order(doc_id: int) -> tuple[int, int]:
    return (doc_id * 0x9E3779B97F4A7C15 & (1 << 64) - 1) >> 7, doc_id
