"""Quality scores from supervised subword embeddings.

Words, word pairs and character n-grams (over UTF-8 bytes) are hashed to rows of an embedding table; a document is the average of
its rows, a softmax layer reads the average, and both are trained together by stochastic gradient descent in numpy.
For scoring, the table and the layer's two outputs collapse to one number for each bucket (the layer is linear), so a text
costs one look-up for each feature and the averages come from prefix sums over whole Arrow batches.

Edge cases: null and empty texts have no features and get the model's prior score; very long texts are averaged whole;
repeated rows get equal scores; with no usable labels every score is 0.5; an empty table gives an empty result; extra columns are
ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .learning import is_held_out, training_sample
from .text import ALNUM, NOT_BLANK, Prefix, Words, chunks, mix, raw

BUCKETS = 1 << 18
GRAMS = (2, 3, 4)
DIMENSIONS = 8


def features(data: np.ndarray, offsets: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
    """(bucket, first byte) of every word, word pair and n-gram of a run of texts, by kind; n-grams don't pass a text's end."""
    prefix = Prefix(data)
    mask = np.uint64(BUCKETS - 1)
    out = []
    for salt, kind in ((0x57, NOT_BLANK), (0x41, ALNUM)):
        words = Words(data, offsets, kind)
        h = prefix.span(words.start, words.end)
        out.append(((mix(h ^ np.uint64(salt)) & mask).astype(np.int64), words.start))
        # Word pairs, hashed by the difference of their words: a word said twice is one feature, whichever word it is.
        pair = np.flatnonzero(words.doc[1:] == words.doc[:-1])
        out.append(((mix((h[pair] ^ h[pair + 1]) + np.uint64(salt << 8)) & mask).astype(np.int64), words.start[pair]))
    end_of = np.repeat(offsets[1:], np.diff(offsets))
    for n in GRAMS:
        h = prefix.grams(n)
        at = np.flatnonzero(np.arange(len(h)) + n <= end_of[: len(h)])
        out.append(((h[at] & mask).astype(np.int64), at))
    return out


class SubwordModel:
    """``table``: embeddings, ``layer``/``bias``: softmax layer of the two labels."""

    def __init__(self, table: np.ndarray, layer: np.ndarray, bias: np.ndarray):
        self.table, self.layer, self.bias = table, layer, bias

    @classmethod
    def fit(cls, texts: list[str], labels: list[int], epochs: int = 6, rate: float = 0.6, seed: int = 5) -> SubwordModel:
        rng = np.random.default_rng(seed)
        table = rng.uniform(-1 / DIMENSIONS, 1 / DIMENSIONS, (BUCKETS, DIMENSIONS)).astype(np.float32)
        layer, bias = np.zeros((2, DIMENSIONS), np.float32), np.zeros(2, np.float32)
        bags = []
        column = pa.array(texts, pa.large_string())
        for a, b in chunks(column, 1 << 18):
            data, offsets = raw(column.slice(a, b - a))
            found = features(data, offsets)
            bucket, at = np.concatenate([f[0] for f in found]), np.concatenate([f[1] for f in found])
            doc = np.searchsorted(offsets, at, "right") - 1
            order = np.argsort(doc, kind="stable")
            edge = np.searchsorted(doc[order], np.arange(b - a + 1))
            for i in range(b - a):
                ids, n = np.unique(bucket[order[edge[i] : edge[i + 1]]], return_counts=True)
                bags.append((ids.astype(np.int32), (n / max(1, n.sum())).astype(np.float32)))
        steps, done = max(1, epochs * len(bags)), 0
        for _ in range(epochs):
            for i in rng.permutation(len(bags)):
                ids, share = bags[i]
                step = rate * (1 - done / steps)
                done += 1
                rows = table[ids]
                mean = share @ rows
                z = layer @ mean + bias
                p = np.exp(z - z.max())
                p /= p.sum()
                p[labels[i]] -= 1
                table[ids] = rows - step * 8 * np.outer(share, p @ layer)
                layer -= step * np.outer(p, mean)
                bias -= step * 0.1 * p
        return cls(table, layer, bias)

    def collapsed(self) -> tuple[np.ndarray, float]:
        """One logit per bucket and the prior logit, label 1 against label 0."""
        return self.table @ (self.layer[1] - self.layer[0]), float(self.bias[1] - self.bias[0])


def text_scores(data: np.ndarray, offsets: np.ndarray, logits: np.ndarray, prior: float) -> np.ndarray:
    total, count = np.zeros(len(offsets) - 1), np.zeros(len(offsets) - 1)
    for bucket, at in features(data, offsets):
        run = np.concatenate([[0.0], np.cumsum(logits[bucket], dtype=np.float64)])
        edge = np.searchsorted(at, offsets)
        total += run[edge[1:]] - run[edge[:-1]]
        count += np.diff(edge)
    return 1 / (1 + np.exp(-(total / np.maximum(count, 1) + prior)))


def score(docs: DataFrame, model: SubwordModel, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, score): the probability of label 1 for every row."""
    shared = docs.sparkSession.sparkContext.broadcast(model.collapsed())  # BUCKETS floats, whatever the data
    schema = T.StructType([docs.schema[id_col], T.StructField("score", T.DoubleType(), False)])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        logits, prior = shared.value
        for batch in batches:
            column = batch.column(1)
            for a, b in chunks(column):
                got = text_scores(*raw(column.slice(a, b - a)), logits, prior)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, b - a), pa.array(got)], names=[id_col, "score"])

    return docs.select(id_col, text_col).mapInArrow(run, schema)


def classify(docs: DataFrame, labels: DataFrame, threshold: float = 0.3) -> DataFrame:
    """Fit on the labelled sample, score every document."""
    model = SubwordModel.fit(*training_sample(docs, labels, "quality"))
    scored = score(docs, model)
    return scored.select("doc_id", is_held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
