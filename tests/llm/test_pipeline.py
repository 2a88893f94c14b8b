"""The pipeline's rows against the same five steps in plain Python."""

import hashlib
import re

import pytest
from checks import SMALL
from test_text_operators import base_model, fingerprint_model, overlap_model

import corpus_pipeline as P
from setstream.llm import bpe, contextual_pii, learning, mil_toxicity

TABLES = SMALL.replace("sf0.001", "sf0.01")  # the smaller tables hold too few toxic labels to learn from
MAIL = [(9_000_000 + i, f"Write to me number {w} at {w}@mail.example or call +44 20 7946 095{i} now.") for i, w in enumerate("abc")]


def without_personal_data(text):
    """Base matches replaced by their kind; of matches that overlap the first, longest on ties, names the whole."""
    out, at = "", 0
    spans = [s.split(":") for s in base_model(text).split(",") if s]
    regions = []
    for kind, start, end in sorted(((k, int(a), int(b)) for k, a, b in spans), key=lambda s: (s[1], -s[2])):
        if regions and start < regions[-1][2]:
            regions[-1][2] = max(regions[-1][2], end)
        else:
            regions.append([kind, start, end])
    for kind, start, end in regions:
        out += f"{text[at:start]}[{kind.upper()}]"
        at = end
    return out + text[at:]


@pytest.fixture
def tables(spark, tmp_path):
    docs = spark.read.parquet(f"{TABLES}/documents.parquet")
    rows = [r.asDict() for r in docs.collect()]
    first = next(r for r in rows if r["text"])
    rows += [{**first, "doc_id": i, "text": t, "n_chars": len(t)} for i, t in MAIL]
    rows += [{**first, "doc_id": 9_100_000, "text": None, "n_chars": None}, {**first, "doc_id": 9_100_001, "text": "", "n_chars": 0}]
    spark.createDataFrame(rows, docs.schema).write.parquet(f"{tmp_path}/documents.parquet")
    for name in ("labels", "benchmark"):
        spark.read.parquet(f"{TABLES}/{name}.parquet").write.parquet(f"{tmp_path}/{name}.parquet")
    return str(tmp_path), rows


def test_pipeline_equals_its_steps_in_plain_python(spark, tables):
    import public_tokenizers
    import tiktoken

    sf_dir, rows = tables
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    model = mil_toxicity.NoisyOrModel.fit(*learning.training_sample(docs, labels, "toxic"))
    toxic = {r["doc_id"] for r in mil_toxicity.score(docs, model).where("score >= 0.5").collect()}  # scores have a plain model of their own
    left = [r for r in rows if r["doc_id"] not in toxic]

    fps = [fingerprint_model(r["text"]) for r in left]
    group = list(range(len(left)))
    for i in range(len(left)):
        for j in range(i):
            if (fps[i] ^ fps[j]).bit_count() <= 4 and group[i] != group[j]:
                old, new = group[i], group[j]
                group = [new if g == old else g for g in group]
    best = {}
    for g, r in zip(group, left, strict=True):
        best[g] = min(best.get(g, r["doc_id"]), r["doc_id"])
    kept = {*best.values()}
    left = [r for r in left if r["doc_id"] in kept]

    items = [(r["item_id"], r["text"]) for r in spark.read.parquet(f"{sf_dir}/benchmark.parquet").collect()]
    hits = overlap_model([r["text"] for r in left], items)
    left = [r for r, (_, n_hit, _) in zip(left, hits, strict=True) if not n_hit]
    assert toxic and 0.6 * len(rows) < len(left) < len(rows) - len(toxic)

    clean = spark.createDataFrame([(r["doc_id"], r["text"]) for r in left], "doc_id long, text string")
    assert contextual_pii.found_spans(contextual_pii.prepare(clean)).count() == 0  # here masking is of base matches alone
    path = public_tokenizers.path("byte_bpe_50k.tiktoken")
    theirs = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks={t: i for i, t in enumerate(bpe.read_ranks(path))}, special_tokens={})
    expected = {}
    for r in left:
        text = without_personal_data(r["text"] or "")
        expected[r["doc_id"]] = (r["lang"], r["source"], len(text), theirs.encode_ordinary(text), hashlib.sha256(text.encode()).hexdigest())
    got = P.run(spark, sf_dir).collect()
    assert len(got) == len(expected)
    for r in got:
        assert (r["lang"], r["source"], r["n_chars"], list(r["token_ids"]), r["decoded_sha256"]) == expected[r["doc_id"]] and r["n_tokens"] == len(r["token_ids"])
    masked = sum(without_personal_data(r["text"] or "") != (r["text"] or "") for r in left)
    assert masked >= 3 and not any(re.search("@mail.example", theirs.decode(list(r["token_ids"]))) for r in got)
