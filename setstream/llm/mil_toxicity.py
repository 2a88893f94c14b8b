"""Toxicity by multiple-instance learning.

A document is a bag of sentences. Each sentence gets a logistic score from its hashed words, and the document's score is
their noisy-or: it is toxic unless every sentence is clean. Only document labels train the sentence weights, yet the
fitted weights say which sentences offend.

With z a sentence's logit, log(1 - p) is -softplus(z), so a document's score is 1 - exp(-sum softplus(z)).

Edge cases: null, empty and wordless texts have no sentence and score 0; very long texts are scored whole; repeated rows get equal scores; with
no usable labels every weight is zero and scores are those of the starting bias; an empty table gives an empty result; extra
columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .learning import is_held_out, training_sample
from .runtime import restored, sheltered
from .text import ALNUM, LOWER, Prefix, Words, chunks, mix, raw

BUCKETS = 1 << 19
#: Beside whole words, their beginnings of so many bytes are features: inflected and compounded forms share them.
STEMS = (4, 5, 6, 7)
#: Words and beginnings in fewer documents of the sample carry no weight.
LEAST_DOCUMENTS = 4
#: Features whose share of documents differs between the labels by fewer standard errors carry no weight either.
LEAST_Z = 4.0
#: Bytes of text whose features are held at once while fitting.
FIT_BYTES = 1 << 19
START_BIAS = -7.0
#: Words that make a sentence of its own.
LEAST_WORDS = 3

_ENDS = np.zeros(256, bool)
_ENDS[[0x0A, 0x21, 0x2E, 0x3F]] = True  # line feed ! . ?


class Sentences:
    """Sentences that hold a word, in a run of texts. ``doc``, ``start``, ``end`` (bytes) of each sentence; ``bucket`` and
    ``sentence`` of each feature (words, then beginnings of words that are longer)."""

    def __init__(self, data: np.ndarray, offsets: np.ndarray):
        words = Words(LOWER[data], offsets, ALNUM)
        passed = np.concatenate([[0], np.cumsum(_ENDS[data])])[words.start]
        new = np.ones(len(words), bool)
        other = words.doc[1:] != words.doc[:-1]
        new[1:] = (passed[1:] != passed[:-1]) | other
        # A fragment of a word or two goes with what follows, else a text of shouted words is a bag of hundreds of sentences.
        breaks = np.flatnonzero(new)
        short = np.diff(breaks) < LEAST_WORDS
        new[breaks[1:][short & ~other[breaks[1:] - 1]]] = False
        of_word = np.cumsum(new) - 1
        first = np.flatnonzero(new)
        self.doc = words.doc[first]
        self.start = words.start[first]
        self.end = words.end[np.append(first[1:], len(words)) - 1] if len(words) else self.start
        prefix, length = Prefix(words.data), words.end - words.start
        found, of = [prefix.span(words.start, words.end)], [of_word]
        for n in STEMS:
            longer = length > n
            start = words.start[longer]
            found.append(prefix.span(start, start + n) ^ np.uint64(0xA5A5 + n))
            of.append(of_word[longer])
        self.bucket = (mix(np.concatenate(found)) & np.uint64(BUCKETS - 1)).astype(np.int64)
        self.sentence = np.concatenate(of)


def softplus(z: np.ndarray) -> np.ndarray:
    return np.logaddexp(0.0, z)


def logistic(z: np.ndarray) -> np.ndarray:
    return np.exp(-softplus(-z))


class NoisyOrModel:
    def __init__(self, weight: np.ndarray, bias: float):
        self.weight, self.bias = weight, bias

    @classmethod
    def fit(cls, texts: list[str], labels: list[int], rounds: int = 150, rate: float = 0.15, shrink: float = 1e-4) -> NoisyOrModel:
        """Adam on the whole sample's log loss, each label carrying half of the weight."""
        model = cls(np.zeros(BUCKETS), START_BIAS)
        y = np.array(labels, bool)
        if not len(y):
            return model
        column = pa.array(texts, pa.large_string())
        # First pass, a chunk at a time: documents of each label that hold each feature.
        toxic, clean = np.zeros(BUCKETS, np.int32), np.zeros(BUCKETS, np.int32)
        for a, b in chunks(column, FIT_BYTES):
            s = Sentences(*raw(column.slice(a, b - a)))
            in_docs = np.unique(s.doc[s.sentence] * BUCKETS + s.bucket)
            of = y[a:b][in_docs // BUCKETS]
            toxic += np.bincount(in_docs[of] % BUCKETS, minlength=BUCKETS).astype(np.int32)
            clean += np.bincount(in_docs[~of] % BUCKETS, minlength=BUCKETS).astype(np.int32)
        n1, n0 = max(1, int(y.sum())), max(1, int((~y).sum()))
        share = np.clip((toxic + clean) / (n1 + n0), 1e-9, 1 - 1e-9)
        z = (toxic / n1 - clean / n0) / np.sqrt(share * (1 - share) * (1 / n1 + 1 / n0))
        telling = (toxic + clean >= LEAST_DOCUMENTS) & (np.abs(z) >= LEAST_Z)
        used, number = np.flatnonzero(telling), np.cumsum(telling) - 1
        if not len(used):
            return model
        # Second pass: sentences with the telling features alone.
        parts, doc, n_sentences = [], [], 0
        for a, b in chunks(column, FIT_BYTES):
            s = Sentences(*raw(column.slice(a, b - a)))
            keep = telling[s.bucket]
            parts.append(np.unique((s.sentence[keep] + n_sentences) * BUCKETS + number[s.bucket[keep]]))
            doc.append(s.doc + a)
            n_sentences += len(s.doc)
        once, doc, n_docs = np.concatenate(parts), np.concatenate(doc), len(y)
        sentence, dense = once // BUCKETS, once % BUCKETS
        cost = np.where(y, 0.5 / max(1, y.sum()), 0.5 / max(1, (~y).sum())) * len(y)
        x = np.zeros(len(used) + 1)
        x[-1] = START_BIAS
        m, v = np.zeros_like(x), np.zeros_like(x)
        for t in range(1, rounds + 1):
            z = x[-1] + np.bincount(sentence, x[dense], n_sentences)
            total = np.bincount(doc, softplus(z), n_docs)
            slope = np.where(y, -1 / np.expm1(np.clip(total, 1e-6, 50)), 1.0) * cost / len(y)
            by_sentence = slope[doc] * logistic(z)
            g = np.append(np.bincount(dense, by_sentence[sentence], len(used)) + shrink * x[:-1], by_sentence.sum())
            m = 0.9 * m + 0.1 * g
            v = 0.99 * v + 0.01 * g * g
            x -= rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-8)
        model.weight[used] = x[:-1]
        model.bias = float(x[-1])
        return model

    def sentence_logits(self, s: Sentences) -> np.ndarray:
        telling = np.flatnonzero(self.weight[s.bucket])
        once = np.unique(s.sentence[telling] * BUCKETS + s.bucket[telling])
        return self.bias + np.bincount(once // BUCKETS, self.weight[once % BUCKETS], len(s.doc))


OUTPUT = [
    T.StructField("score", T.DoubleType(), False),
    T.StructField(
        "offending",
        T.ArrayType(T.StructType([T.StructField("start", T.LongType()), T.StructField("end", T.LongType()), T.StructField("score", T.DoubleType())])),
    ),
]


def score(docs: DataFrame, model: NoisyOrModel, threshold: float = 0.5, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """The columns ``keep`` (default: doc_id) with ``score`` and ``offending``: the sentences (code points, end exclusive)
    that reach ``threshold`` by themselves."""
    keep = ["doc_id"] if keep is None else keep
    shared = docs.sparkSession.sparkContext.broadcast(model)  # BUCKETS doubles, whatever the data
    schema = T.StructType([docs.schema[c] for c in keep] + OUTPUT)
    names = [*keep, "score", "offending"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fitted = shared.value
        for batch in batches:
            column = batch.column(len(keep))
            for a, b in chunks(column):
                data, offsets = raw(column.slice(a, b - a))
                s = Sentences(data, offsets)
                z = fitted.sentence_logits(s)
                total = np.bincount(s.doc, softplus(z), b - a)
                own = logistic(z)
                bad = np.flatnonzero(own >= threshold)
                point = np.concatenate([[0], np.cumsum((data & 0xC0) != 0x80)])
                origin = point[offsets[s.doc[bad]]]
                spans = pa.StructArray.from_arrays(
                    [pa.array(point[s.start[bad]] - origin, pa.int64()), pa.array(point[s.end[bad]] - origin, pa.int64()), pa.array(own[bad])], names=["start", "end", "score"]
                )
                lists = pa.ListArray.from_arrays(pa.array(np.searchsorted(s.doc[bad], np.arange(b - a + 1)), pa.int32()), spans)
                yield pa.RecordBatch.from_arrays([*(batch.column(i).slice(a, b - a) for i in range(len(keep))), pa.array(-np.expm1(-total)), lists], names=names)

    return docs.select(*keep, docs[text_col].alias("_text")).mapInArrow(run, schema)


def fit(docs: DataFrame, labels: DataFrame) -> NoisyOrModel:
    return NoisyOrModel.fit(*training_sample(docs, labels, "toxic"))


def drop_toxic(docs: DataFrame, model: NoisyOrModel, threshold: float = 0.5) -> DataFrame:
    """The documents that score below ``threshold``, with their own columns."""
    own = sheltered(docs, "text")
    scored = score(own, model, threshold, keep=own.columns)
    return restored(scored.where(F.col("score") < threshold), docs, "text")


def classify(docs: DataFrame, labels: DataFrame, threshold: float = 0.5) -> DataFrame:
    """Fit on the labelled sample, score every document."""
    scored = score(docs, fit(docs, labels))
    held = is_held_out(F.col("doc_id")).alias("held_out")
    return scored.select("doc_id", held, "score", (F.col("score") >= threshold).cast("int").alias("predicted"), F.size("offending").cast("long").alias("n_offending"))
