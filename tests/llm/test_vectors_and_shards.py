"""Nearest neighbours against brute force, packing against its laws, and the whole pipeline."""

import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from checks import SMALL

from setstream.llm import multi_index_hash, queries, shard_packing


def test_neighbours_recall_and_scores(spark):
    rows = queries.op8_multi_index(spark, SMALL.replace("0.001", "0.1")).collect()
    table = spark.read.parquet(SMALL.replace("0.001", "0.1") + "/embeddings.parquet").collect()
    ids, x = np.array([r["vec_id"] for r in table]), np.array([r["embedding"] for r in table], np.float64)
    place, found = {int(v): i for i, v in enumerate(ids)}, defaultdict(list)
    for r in rows:
        found[r["query_id"]].append((r["rank"], r["vec_id"]))
        assert r["vec_id"] != r["query_id"] and abs(r["score"] - x[place[r["query_id"]]] @ x[place[r["vec_id"]]]) < 1e-12
    assert set(found) == {int(v) for v in ids if v % 20 == 0} and all(sorted(r for r, _ in f) == list(range(1, 21)) for f in found.values())
    hits = 0
    for q, f in found.items():
        score = x @ x[place[q]]
        score[place[q]] = -np.inf
        hits += len(set(ids[np.argsort(-score)[:20]].tolist()) & {v for _, v in f})
    assert hits / (20 * len(found)) >= 0.9


def test_odd_vectors(spark):
    schema = "vec_id long, embedding array<float>, id string, score double"
    rows = [(0, [1.0, 0.0]), (1, [1.0, 0.0]), (2, [0.5, 0.5]), (3, None), (4, [0.0, 0.0]), (5, [float("nan"), 1.0]), (6, [1.0, None]), (7, []), (20, [0.0, 1.0]), (20, [0.0, 1.0]), (None, [1.0, 1.0])]
    got = [(r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in multi_index_hash.search(spark.createDataFrame([(*r, "x", 1.0) for r in rows], schema)).collect()]
    assert sorted(got) == [(0, 1, 1, 1.0), (0, 2, 2, 0.5), (0, 3, 20, 0.0), (20, 1, 2, 0.5), (20, 2, 0, 0.0), (20, 3, 1, 0.0)]
    assert multi_index_hash.search(spark.createDataFrame([], schema)).count() == 0


def test_ties_and_repeated_ids(spark):
    """Copies of one vector beyond k, which go by id; ids with two vectors count once."""
    rng = np.random.default_rng(2)
    x = rng.standard_normal(6)
    rows = [(i, x.tolist(), "x") for i in range(100)] + [(i, (x * 0.5).tolist(), "y") for i in range(100, 130)] + [(40, (x * 2).tolist(), "z"), (40, (x * 3).tolist(), "z")]
    got = {}
    for r in multi_index_hash.search(spark.createDataFrame(rows, "vec_id long, embedding array<double>, rank string")).collect():
        got.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
    assert set(got) == set(range(0, 130, 20))
    least = {i: v for i, v, _ in sorted(((i, v, s) for i, v, s in rows), reverse=True)}
    for q, found in got.items():
        want = sorted((-sum(a * b for a, b in zip(least[q], v, strict=True)), i) for i, v in least.items() if i != q)[:20]
        assert [v for _, v, _ in sorted(found)] == [i for _, i in want] and [s for _, _, s in sorted(found)] == pytest.approx([-s for s, _ in want])


def test_multi_index_finds_every_code_in_the_radius():
    rng = np.random.default_rng(1)
    codes = rng.integers(0, 1 << 16, (400, 4), dtype=np.uint16)
    codes[200:] = codes[:200] ^ (1 << rng.integers(0, 16, (200, 4))).astype(np.uint16)
    index = multi_index_hash.MultiIndex(codes)
    for radius in (0, 3, 8, 20, 64):
        for q in codes[:20]:
            assert index.within(q, radius).tolist() == np.flatnonzero(np.bitwise_count(codes ^ q).sum(1) <= radius).tolist()


def best_fit_model(sizes, capacity):
    bins = []
    for s in sorted(sizes, reverse=True):
        fits = [b for b in range(len(bins)) if bins[b] >= s]
        if fits:
            bins[min(fits, key=lambda b: (bins[b], b))] -= s
        else:
            bins.append(max(capacity, s) - s)
    return sorted(bins)


@pytest.mark.parametrize("seed", range(4))
def test_best_fit_decreasing(seed):
    sizes = np.random.default_rng(seed).integers(0, 60, 300).tolist()
    runs, used = shard_packing.best_fit_decreasing(list(Counter(sizes).items()), 100)
    left = defaultdict(lambda: 100)
    for size, a, b, which in runs:
        left[which] -= size * (b - a)
    assert sorted(left.values()) == best_fit_model(sizes, 100) and used == len(left) and min(left.values()) >= 0


def check_packing(rows, shards):
    by = defaultdict(list)
    for r in rows:
        by[r["shard"]].append(r)
    assert set(by) <= set(range(shards))
    assert all(sorted(r["slot"] for r in rs) == list(range(len(rs))) for rs in by.values())
    return [sum(r["size"] for r in by[s]) for s in range(shards)]


def test_packing_of_documents(spark):
    rows = queries.op10_shard_packing(spark, SMALL.replace("0.001", "0.01")).collect()
    texts = {r["doc_id"]: r["text"] for r in spark.read.parquet(SMALL.replace("0.001", "0.01") + "/documents.parquet").collect()}
    assert len(rows) == len(texts)
    assert all(r["size"] == len(texts[r["doc_id"]].encode()) + 16 and r["text_crc32"] == zlib.crc32(texts[r["doc_id"]].encode()) for r in rows)
    sizes, together = check_packing(rows, 40), defaultdict(set)
    for r in rows:
        together[texts[r["doc_id"]]].add(r["shard"])
    assert max(sizes) <= 1.02 * sum(sizes) / 40 and all(len(s) == 1 for s in together.values())


def test_packing_of_odd_rows(spark, dirty, empty):
    rows = shard_packing.pack(dirty, shards=3).collect()
    assert len(rows) == 12
    check_packing(rows, 3)
    assert shard_packing.pack(empty).count() == 0
    copies = spark.createDataFrame([(i, "same text of many copies") for i in range(900)] + [(1000 + i, f"other {i}") for i in range(600)], "doc_id long, text string")
    sizes = check_packing(shard_packing.pack(copies, shards=10).collect(), 10)
    assert max(sizes) <= 1.1 * sum(sizes) / 10
    fixed = shard_packing.pack(copies.where("doc_id >= 1000"), capacity=1000).collect()
    assert max(check_packing(fixed, 1 + max(r["shard"] for r in fixed))) <= 1000


def test_pipeline_stages(spark, dirty):
    import corpus_pipeline as P

    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    assert [n for n, _ in P.STAGES] == ["toxicity", "near_duplicates", "decontamination", "personal_data", "byte_bpe"]
    before = docs.count()
    for name, stage in P.STAGES[:-1]:
        out = stage(spark, docs, SMALL)
        assert out.columns == docs.columns
        after = out.count()
        assert after == before if name == "personal_data" else 0.7 * before < after <= before
        docs, before = out, after
    last = P.STAGES[-1][1](spark, docs, SMALL)
    assert last.count() == before == P.run(spark, SMALL).count()
    odd = dirty.selectExpr("doc_id", "text", "cast(null as string) as lang", "score as source", "cast(length(text) as bigint) as n_chars", "spans")
    for _, stage in P.STAGES:
        assert stage(spark, odd, SMALL).count() >= 0
        assert stage(spark, odd.limit(0), SMALL).count() == 0
