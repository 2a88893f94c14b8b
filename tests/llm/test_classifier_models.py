"""Both classifiers against plain Python: scores word by word, and steps of learning by numeric gradients."""

import math
import re

import numpy as np
import pyarrow as pa
import pytest

from setstream.llm import mil_toxicity, subword_quality
from setstream.llm.text import _BASE, _BYTE, mix, raw

ALL = (1 << 64) - 1
TEXTS = [
    None, "", " \n\t", "Plain short text.", "Plain short text.", "ünï çødé 日本語 text 😀 mail x@y.zz now", "9" * 5000, "!!! ??? ...\n\n", "One two. Three four five! Six",
    "a a a b\n\nSHOUT. NOW. Here it goes on. X.", "ñandú ñandú, é.é 12-34", "plainly plain",
]


def span_hash(data, n=None):
    return (sum(int(_BYTE[b]) * pow(_BASE, i, 1 << 64) for i, b in enumerate(data)) + (len(data) if n is None else n)) & ALL


def mixed(h):
    return int(mix(np.array([h & ALL], np.uint64))[0])


def plain_features(text):
    data = (text or "").encode()
    out = []
    for salt, pattern in ((0x57, rb"[^\x20\x09-\x0D]+"), (0x41, rb"[0-9A-Za-z\x80-\xFF]+")):
        h = [span_hash(w) for w in re.findall(pattern, data)]
        out += [mixed(x ^ salt) for x in h] + [mixed((x ^ y) + (salt << 8)) for x, y in zip(h, h[1:], strict=False)]
    for n in subword_quality.GRAMS:
        out += [mixed(span_hash(data[i : i + n])) for i in range(len(data) - n + 1)]
    return [x % subword_quality.BUCKETS for x in out]


def test_quality_scores_equal_a_plain_forward_pass():
    rng = np.random.default_rng(3)
    table, layer, bias = rng.normal(size=(subword_quality.BUCKETS, 8)), rng.normal(size=(2, 8)), np.array([0.3, -0.2])
    texts = [t if t is None else t[:300] for t in TEXTS]
    got = subword_quality.text_scores(*raw(pa.array(texts)), *subword_quality.SubwordModel(table, layer, bias).collapsed())
    for text, score in zip(texts, got, strict=True):
        rows = [table[i] for i in plain_features(text)]
        z = layer @ (sum(rows) / len(rows) if rows else np.zeros(8)) + bias
        assert score == pytest.approx(math.exp(z[1]) / (math.exp(z[0]) + math.exp(z[1])), abs=1e-9), text


def numeric_gradient(loss, x, width=1e-5):
    g = np.zeros_like(x)
    for i in range(len(x)):
        step = np.zeros_like(x)
        step[i] = width
        g[i] = (loss(x + step) - loss(x - step)) / (2 * width)
    return g


def test_quality_learns_by_the_gradient_of_its_loss():
    """Three steps on one text: rates fall to zero in a line, 8 times as large for embeddings and a tenth for the bias."""
    text, label, rate, seed = "ab cd", 1, 0.6, 5
    model = subword_quality.SubwordModel.fit([text], [label], epochs=3, rate=rate, seed=seed)
    found = plain_features(text)
    ids = sorted(set(found))
    share = np.array([found.count(i) / len(found) for i in ids])
    start = np.random.default_rng(seed).uniform(-1 / 8, 1 / 8, (subword_quality.BUCKETS, 8))
    n = len(ids) * 8
    x = np.concatenate([start[ids].ravel(), np.zeros(18)])
    scale = np.concatenate([np.full(n, 8.0), np.ones(16), np.full(2, 0.1)])

    def loss(x):
        z = x[n : n + 16].reshape(2, 8) @ (share @ x[:n].reshape(-1, 8)) + x[n + 16 :]
        return math.log(math.exp(z[0]) + math.exp(z[1])) - z[label]

    for t in range(3):
        x = x - rate * (1 - t / 3) * scale * numeric_gradient(loss, x)
    fitted = np.concatenate([model.table[ids].ravel(), model.layer.ravel(), model.bias])
    assert np.allclose(fitted, x, atol=1e-5)
    others = np.setdiff1d(np.arange(subword_quality.BUCKETS), ids)
    assert np.allclose(model.table[others], start[others])


def plain_sentences(text):
    """Sets of features, by sentence: fragments of under three words go with what follows."""
    data = (text or "").encode()
    lower = bytes(b + 32 if 0x41 <= b <= 0x5A else b for b in data)
    runs, last = [], None
    for m in re.finditer(rb"[0-9a-z\x80-\xFF]+", lower):
        if last is None or re.search(rb"[\n!.?]", data[last : m.start()]):
            runs.append([])
        runs[-1].append(m[0])
        last = m.end()
    out, join = [], False
    for run in runs:
        if not join:
            out.append(set())
        for w in run:
            out[-1].add(mixed(span_hash(w)) % mil_toxicity.BUCKETS)
            out[-1] |= {mixed(span_hash(w[:n]) ^ (0xA5A5 + n)) % mil_toxicity.BUCKETS for n in mil_toxicity.STEMS if len(w) > n}
        join = len(run) < mil_toxicity.LEAST_WORDS
    return out


def test_toxicity_scores_equal_a_plain_noisy_or(spark):
    rng = np.random.default_rng(4)
    model = mil_toxicity.NoisyOrModel(np.where(rng.random(mil_toxicity.BUCKETS) < 0.7, rng.normal(size=mil_toxicity.BUCKETS), 0.0), -1.0)
    docs = spark.createDataFrame(list(enumerate(TEXTS)), "doc_id long, text string")
    rows = mil_toxicity.score(docs, model, 0.5).collect()
    assert len(rows) == len(TEXTS)
    for r in rows:
        clean, bad = 1.0, 0
        for s in plain_sentences(TEXTS[r["doc_id"]]):
            p = 1 / (1 + math.exp(-(model.bias + sum(model.weight[i] for i in s))))
            clean *= 1 - p
            bad += p >= 0.5
        assert r["score"] == pytest.approx(1 - clean, abs=1e-9) and len(r["offending"]) == bad, TEXTS[r["doc_id"]]


def test_toxicity_learns_by_the_gradient_of_its_loss():
    """Adam by numeric gradients of the balanced log loss, over the features that tell the labels apart."""
    texts = ["We are all well. You rude grub are bad."] * 20 + ["We are all well. It is a good day."] * 30 + ["It is a bad day."] * 10
    y = np.array([1] * 20 + [0] * 40, bool)
    model = mil_toxicity.NoisyOrModel.fit(texts, list(y.astype(int)), rounds=4)
    bags = [plain_sentences(t) for t in texts]
    n1, n0 = y.sum(), (~y).sum()
    used = []
    for f in sorted(set().union(*(s for bag in bags for s in bag))):
        there = np.array([any(f in s for s in bag) for bag in bags])
        share = there.mean()
        apart = abs(there[y].mean() - there[~y].mean()) / math.sqrt(max(share * (1 - share), 1e-18) * (1 / n1 + 1 / n0))
        if there.sum() >= mil_toxicity.LEAST_DOCUMENTS and apart >= mil_toxicity.LEAST_Z:
            used.append(f)
    assert used and sorted(np.flatnonzero(model.weight)) == used
    rows = [np.array([[f in s for f in used] for s in bag], float) for bag in bags]

    def loss(x):
        totals = np.array([np.log1p(np.exp(x[-1] + r @ x[:-1])).sum() for r in rows])
        return 0.5 * totals[~y].sum() / n0 - 0.5 * np.log(-np.expm1(-totals[y])).sum() / n1 + 0.5e-4 * (x[:-1] ** 2).sum()

    x = np.append(np.zeros(len(used)), mil_toxicity.START_BIAS)
    m, v = np.zeros_like(x), np.zeros_like(x)
    for t in range(1, 5):
        g = numeric_gradient(loss, x)
        m, v = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g
        x = x - 0.15 * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-8)
    assert np.allclose(np.append(model.weight[used], model.bias), x, atol=1e-4)
