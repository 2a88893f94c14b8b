"""Tokens, leaks, copies, passages, pages and personal data, against plain Python."""

import hashlib
import html
import re
from itertools import combinations

import numpy as np
import pyarrow.parquet as pq
import pytest
from checks import SMALL, same_rows
from pyspark.sql import functions as F

from setstream.llm import bpe, contextual_pii, decontam, oracles, queries, simhash_trie, suffix_dedup, template_html

LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


@pytest.mark.parametrize("name", sorted(oracles.ORACLES))
def test_queries_match_sql(spark, duck, name):
    same_rows(queries.QUERIES[name](spark, SMALL), duck, oracles.ORACLES[name])


def test_byte_bpe_equals_tiktoken(spark, dirty, empty):
    import public_tokenizers as P
    import tiktoken

    path = P.path("byte_bpe_50k.tiktoken")
    theirs = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks={t: i for i, t in enumerate(bpe.read_ranks(path))}, special_tokens={})
    docs = dirty.select("doc_id", "text").union(spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "text"))
    rows = bpe.encode_decode(docs.withColumn("copy", F.col("text")), path, P.PATTERN).collect()
    assert len(rows) == docs.count()
    for r in rows:
        assert list(r["token_ids"]) == theirs.encode_ordinary(r["copy"] or "") and bytes(r["decoded"]) == (r["copy"] or "").encode()
    assert bpe.encode_decode(empty, path, P.PATTERN).count() == 0
    rng = np.random.default_rng(1)
    encoder = bpe.Encoder(bpe.Vocabulary(bpe.read_ranks(path)), P.PATTERN)
    for n in (3, 50, 20_000):
        for letters in ("ab", "the rinsd", "!?*\n \t", "éü日"):
            text = "".join(rng.choice(list(letters), n))
            assert encoder.encode(text) == theirs.encode_ordinary(text)


def overlap_model(texts, items, width=10):
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(LOWER))
    windows = {}
    for i, t in items:
        w = words(t)
        for at in range(max(1, len(w) - width + 1)) if w else ():
            windows.setdefault(tuple(w[at : at + width]), set()).add(i)
    out = []
    for t in texts:
        w, hit, ids = words(t), set(), set()
        for n in {len(x) for x in windows}:
            for at in range(len(w) - n + 1):
                if tuple(w[at : at + n]) in windows:
                    hit |= set(range(at, at + n))
                    ids |= windows[tuple(w[at : at + n])]
        out.append((len(w), len(hit), tuple(sorted(ids))))
    return out


@pytest.mark.parametrize("block", [decontam.ITEM_BYTES, 60])
def test_decontamination(spark, dirty, empty, monkeypatch, block):
    monkeypatch.setattr(decontam, "ITEM_BYTES", block)
    rng = np.random.default_rng(3)
    vocabulary = ["a", "b", "Cé", "d1"]
    made = [" ".join(rng.choice(vocabulary, rng.integers(0, 30))) for _ in range(40)]
    items = [(i, " ".join(rng.choice(vocabulary, n))) for i, n in enumerate([3, 4, 10, 12, 0, 11])] + [(7, None), (8, "plain SHORT"), (8, "plain SHORT"), (None, "a")]
    docs = dirty.select("doc_id", "text").union(spark.createDataFrame([(100 + i, t) for i, t in enumerate(made)], "doc_id long, text string")).withColumn("copy", F.col("text"))
    table = spark.createDataFrame(items, "item_id long, text string")
    rows = decontam.overlaps(docs, table).withColumn("n_hit", decontam.hit_words(F.col("spans"))).collect()
    expected = overlap_model([r["copy"] for r in rows], [(i, t) for i, t in items if i is not None])
    assert [(r["n_words"], r["n_hit"], tuple(r["item_ids"])) for r in rows] == expected
    clean = decontam.decontaminate(dirty, table)
    assert clean.columns == dirty.columns and sorted(r["doc_id"] or 0 for r in clean.collect()) == [0, 1, 2, 3, 6, 7, 8, 9]
    assert decontam.overlaps(empty, table).count() == 0 and decontam.overlaps(dirty, table.limit(0)).where("size(spans) > 0").count() == 0


def longest_model(text, items, starts):
    """(words, from_word, item_id, item_word) of the longest verbatim match that begins at one of the hits."""
    words = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate(LOWER))
    w, best = words(text), None
    for s in starts:
        for i, t in items:
            v = words(t)
            for j in range(len(v)):
                n = 0
                while s + n < len(w) and j + n < len(v) and w[s + n] == v[j + n]:
                    n += 1
                best = min(best or (0, 0, 0, 0), (-n, s, i, j)) if n else best
    return None if best is None else (-best[0], *best[1:])


@pytest.mark.parametrize("block", [decontam.ITEM_BYTES, 120])
def test_longest_matches_and_their_places(spark, monkeypatch, block):
    monkeypatch.setattr(decontam, "ITEM_BYTES", block)
    rng = np.random.default_rng(8)
    items = [(10 - i, " ".join(rng.choice(["a", "b", "c"], n))) for i, n in enumerate([30, 14, 5, 60, 60, 3])] + [(3, "z " * 25), (2, "y " * 10)]
    made = [" ".join(rng.choice(["a", "b", "c", "other"], 40, p=[0.35, 0.35, 0.25, 0.05])) for _ in range(40)]
    made += [f"x {items[3][1]} b {items[4][1]}", "z " * 30, "q", f"{items[0][1]} {items[0][1]}"]
    docs = spark.createDataFrame(list(enumerate(made)), "doc_id long, text string")
    rows = {r["doc_id"]: r for r in decontam.overlaps(docs, spark.createDataFrame(items, "item_id long, text string")).collect()}
    for i, text in enumerate(made):
        r = rows[i]
        w = re.findall("[a-z]+", text)
        starts = [s for s in range(len(w)) for _, t in items for v in [t.split()] for n in [min(10, len(v))] for j in range(len(v) - n + 1) if w[s : s + n] == v[j : j + n]]
        assert (tuple(r["longest"]) if r["longest"] else None) == longest_model(text, items, sorted(set(starts))), text


def test_benchmarks_need_little_memory():
    """Items in memory take a few times their text, at their peak too."""
    import tracemalloc

    import pyarrow as pa

    from setstream.llm.text import chunks

    rng = np.random.default_rng(1)
    vocabulary = np.array([f"word{i}" for i in range(20_000)])
    texts = pa.array([" ".join(rng.choice(vocabulary, 400)) for _ in range(600)])
    size = sum(len(t.as_py()) for t in texts)
    decontam.chunks, before = (lambda column: chunks(column, 1 << 18)), decontam.chunks
    decontam.Windows([1], pa.array(["tables that stay are made first"]), 10)
    tracemalloc.start()
    windows = decontam.Windows(list(range(600)), texts, 10)
    held, peak = tracemalloc.get_traced_memory()
    tracemalloc.stop()
    decontam.chunks = before
    assert len(windows) == 600 * 391 and held < 6 * size and peak < 25 * size


def fingerprint_model(text, shingle=4):
    import xxhash

    w = re.findall(r"[^\x20\x09-\x0D]+", (text or "").translate(LOWER))
    hashes = [xxhash.xxh64_intdigest(" ".join(w[i : i + shingle]).encode(), 42) for i in range(max(1, len(w) - shingle + 1))] if w else []
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def test_simhash_groups(spark, dirty, empty):
    docs = dirty.select("doc_id", "text").union(spark.read.parquet(f"{SMALL}/documents.parquet").select(F.col("doc_id") + 1000, "text"))
    rows = docs.collect()
    fps = [fingerprint_model(r["text"]) for r in rows]
    group = list(range(len(rows)))

    def root(i):
        while group[i] != i:
            i = group[i]
        return i

    for i, j in combinations(range(len(rows)), 2):
        if (fps[i] ^ fps[j]).bit_count() <= 4:
            group[root(j)] = root(i)
    least = {}
    for i, r in enumerate(rows):
        if r["doc_id"] is not None:
            least[root(i)] = min(least.get(root(i), 1 << 60), r["doc_id"])
    expected = sorted(((r["doc_id"] or -1, fps[i], least.get(root(i), -1)) for i, r in enumerate(rows)))
    got = [(r["doc_id"] or -1, r["fp"] % (1 << 64), -1 if r["component_id"] is None else r["component_id"]) for r in simhash_trie.near_duplicates(docs).collect()]
    assert sorted(got) == expected
    assert simhash_trie.near_duplicates(empty).count() == 0
    kept = simhash_trie.keep_one(dirty)
    assert kept.columns == dirty.columns and kept.count() == len({root(i) for i in range(12)})
    assert sum(r["doc_id"] == 4 for r in kept.collect()) == 1


def test_trie_links_equal_brute_force():
    rng = np.random.default_rng(0)
    for radius in (0, 1, 4):
        base = rng.integers(0, 1 << 63, 6, dtype=np.uint64)
        fp = np.unique([int(base[rng.integers(6)]) ^ sum(1 << int(b) for b in set(rng.integers(0, 64, rng.integers(0, 8)).tolist())) for _ in range(250)]).astype(np.uint64)
        a, b = simhash_trie.walk_tries(np.zeros(len(fp), int), fp, radius)
        one, two = simhash_trie.Forest(len(fp)), simhash_trie.Forest(len(fp))
        one.join(a, b)
        two.join(*np.where(np.bitwise_count(fp[:, None] ^ fp) <= radius))
        assert (one.roots(np.arange(len(fp))) == two.roots(np.arange(len(fp)))).all() and len(a) < len(fp)


def test_hot_buckets_are_split(spark, monkeypatch):
    """Fingerprints that agree on most bits: the bucket is split, and no link is lost."""
    rng = np.random.default_rng(4)
    base = rng.integers(0, 1 << 62, 3)
    made = np.unique([int(base[rng.integers(3)]) ^ sum(1 << int(b) for b in rng.choice(63, rng.integers(0, 6), replace=False)) for _ in range(700)])
    distinct = spark.createDataFrame([(int(x),) for x in made], "fp long")
    want = simhash_trie.Forest(len(made))
    want.join(*np.where(np.bitwise_count(made[:, None] ^ made) <= 4))
    for hot in (1 << 14, 60):
        monkeypatch.setattr(simhash_trie, "HOT", hot)
        sizes = simhash_trie.bucketed(distinct, 4, 5).groupBy("mask", "bucket").count().agg({"count": "max"}).first()[0]
        assert sizes > 60 if hot > 60 else sizes < 200
        links = simhash_trie.hamming_links(distinct, 4).collect()
        got = simhash_trie.Forest(len(made))
        got.join(np.searchsorted(made, [r["src"] for r in links]), np.searchsorted(made, [r["dst"] for r in links]))
        assert (got.roots(np.arange(len(made))) == want.roots(np.arange(len(made)))).all()


def test_blocks_grow_with_the_corpus():
    assert simhash_trie.choose_blocks(10**5, 4) == 5 and simhash_trie.choose_blocks(10**9, 4) > 5


def test_long_chains_are_connected(spark):
    chain = spark.range(200).selectExpr("id as src", "id + 1 as dst")
    assert {r["root"] for r in simhash_trie.connect(chain).collect()} == {0}


def test_repeated_passages(spark, dirty, empty):
    rng = np.random.default_rng(5)
    words = [f"w{i}" for i in range(4000)]
    passage, short = " ".join(rng.choice(words, 70)), " ".join(rng.choice(words, 49))
    own = [" ".join(rng.choice(words, 60)) for _ in range(5)]
    texts = [f"{own[0]} {passage} x", f"{passage} {own[1]}", f"{own[2]} {short}", f"{own[3]} {short}", f"{own[4]} {passage} {passage}", own[0], f"{short} {short} {short}"]
    docs = dirty.select("doc_id", "text").union(spark.createDataFrame([(100 + i, t) for i, t in enumerate(texts)], "doc_id long, text string"))
    got = sorted((r["doc_id"], r["from_word"], r["to_word"], r["first_doc_id"]) for r in suffix_dedup.repeated_passages(docs).collect())
    # A text that repeats itself alone is left alone.
    assert got == [(100, 0, 130, 100), (101, 0, 70, 100), (104, 60, 200, 100), (105, 0, 60, 100)]
    extra = docs.where("doc_id >= 100").selectExpr("*", "1 as _cut", "2 as digest", "'x' as spans")
    again = extra.union(spark.createDataFrame([(102, own[0], 1, 2, "y"), (None, own[0], 1, 2, "z")], extra.schema))
    cut = {(r["doc_id"], r["spans"]): r["text"] for r in suffix_dedup.drop_repeats(again).collect()}
    assert len(cut) == 9 and cut[100, "x"] == texts[0] and cut[101, "x"] == own[1] and cut[102, "x"] == texts[2] and cut[105, "x"] == cut[102, "y"] == cut[None, "z"] == ""
    assert suffix_dedup.repeated_passages(empty).count() == 0


def windows_model(texts, length):
    """(text, start, least) of all windows that another text holds too."""
    held = {}
    for i, t in enumerate(texts):
        w = t.split()
        for s in range(len(w) - length + 1):
            held.setdefault(tuple(w[s : s + length]), []).append((i, s))
    return {(i, s, min(at)[0]) for at in held.values() if len({i for i, _ in at}) > 1 for i, s in at}


@pytest.mark.parametrize("hot", [256, 0, 2])
def test_repeats_equal_brute_force(spark, tmp_path, hot):
    """Few words, so that grams are shared by texts that go on differently on both sides. The worker reads the bound from its own module."""
    rng = np.random.default_rng(7)
    pieces = [" ".join(rng.choice(["a", "bé", "c" * 60], 6)) for _ in range(5)]
    texts = [" ".join(rng.choice(pieces, rng.integers(0, 6))) for _ in range(60)]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    before = suffix_dedup.HOT
    suffix_dedup.HOT = hot
    try:
        got = sorted(tuple(r) for r in suffix_dedup.repeated_passages(docs, length=10, gram=4).collect())
    finally:
        suffix_dedup.HOT = before
    want = []
    found = windows_model(texts, 10)
    for i in range(len(texts)):
        own = sorted((s, least) for d, s, least in found if d == i)
        spans = []
        for s, least in own:
            if spans and s <= spans[-1][1]:
                spans[-1] = (spans[-1][0], s + 10, min(spans[-1][2], least))
            else:
                spans.append((s, s + 10, least))
        want += [(i, *x) for x in spans]
    assert got == sorted(want)


def test_windows_are_compared_by_their_words():
    """Rows that are dealt to one run by an equal hash, though their words differ, don't match."""
    import pyarrow as pa

    words = [f"w{i}" for i in range(60)]
    same, other = " ".join(words), " ".join(f"x{w}" for w in words)
    late = " ".join(words[:40] + ["y"] * 20)
    rows = suffix_dedup.repeated_runs(pa.array([same, other, same, late]), np.array([10, 10, 10, 10]), np.array([0, 1, 2, 3]), np.array([5, 6, 7, 4]), 50, 20)
    assert [tuple(int(v) for v in r) for r in zip(*rows, strict=True)] == [(0, -10, 0, 5), (2, -10, 0, 5)]


def test_given_pages(spark):
    got = {r["page_id"]: r["text"] for r in template_html.extract(spark.read.parquet(f"{SMALL}/pages.parquet")).collect()}
    for p in pq.read_table(f"{SMALL}/pages.parquet").to_pylist():
        article = re.search(r"<article>(.*?)</article>", p["html"], re.S)[1]
        blocks = [re.sub(r"\s+", " ", html.unescape(re.sub(r"<[^>]*>", "", x.replace("<br>", " ")))).strip() for x in re.split(r"</?(?:p|h1|h2|ul|li|div)>", article)]
        assert got[p["page_id"]] == "\n".join(b for b in blocks if b)


def page(i, body):
    return f'<!DOCTYPE html><html><head><title>T{i}</title><style>p{{}}</style></head><body class="site">{body}</body></html>'


def test_pages_of_other_templates(spark):
    def built(i):
        return page(
            i,
            f'<header><h2>The Site</h2></header><div class="menu"><ul><li><a href="/">Home</a><li><a href="/x">More</a></ul></div><div class="cookie-notice">We use cookies</div>'
            f'<div class="post"><h1>Title {i}</h1><p>First&nbsp;para {i} &lt;b&gt; one.<p>Second <i>para</i>\n graph {i * 7} with words.<script>var x="</p>"</script></div>'
            f'<form><label>Name</label><input name=q></form><div id="comments"><p>Nice one {i}, I liked it very much indeed!</div><aside>Side {i}</aside><footer>End</footer>',
        )

    rows = [(i, "http://one.example/a", built(i)) for i in range(6)]
    rows += [(10, None, None), (11, "x", ""), (12, "http://lone.example/", "<p>Alone & <b>bold</b> text<p>two"), (13, "http://lone.example/", "<main><header><h1>Head</h1></header>a<!-- x --> b<div>c</div></main><nav>n</nav>")]
    rows += [(14, "http://t.example/", "<body><article><p>cut &amp; dry <b>never clo")]
    got = {r["page_id"]: r["text"] for r in template_html.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    for i in range(6):
        assert got[i] == f"Title {i}\nFirst para {i} <b> one.\nSecond para graph {i * 7} with words."
    assert got[10] == got[11] == "" and got[12] == "Alone & bold text\ntwo" and got[13] == "Head\na b\nc" and got[14] == "cut & dry never clo"
    assert template_html.extract(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_pages_that_are_copies_keep_their_text(spark):
    text = "".join(f"<p>Sentence {j} of the only story told here, long enough to matter.</p>" for j in range(5))
    want = "\n".join(f"Sentence {j} of the only story told here, long enough to matter." for j in range(5))
    box = '<div class="box"><p>Why people trust us: we were founded long ago.</p></div>'

    def main(i):
        return f"<main><h1>Head {i}</h1><p>Story {i} goes on for some while, with words enough.</p>{box}</main>"

    rows = [(i, f"http://copy.example/?s={i}", page(0, f'<div class="x">{text}</div>')) for i in range(5)]
    rows += [(10 + i, f"http://variant.example/?s={i}", page(i, f'<div class="x" id="n{i}"><a href="?s={i}"></a>{text}</div>')) for i in range(5)]
    rows += [(20 + i, f"http://near.example/{i}", page(i, f'<div class="x">{text}<div class="views">{i} views</div></div>')) for i in range(5)]
    rows += [(30 + i, f"http://main.example/{i}", page(i, main(i))) for i in range(5)]
    rows += [(40 + i, "http://main.example/0", page(0, main(0))) for i in range(9)]
    got = {r["page_id"]: r["text"] for r in template_html.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    for i in range(5):
        assert got[i] == got[10 + i] == want and got[20 + i] == f"{want}\n{i} views"
        assert got[30 + i] == f"Head {i}\nStory {i} goes on for some while, with words enough."


def neutral(i, lines=3):
    """A page whose names say nothing: menu, notice, article, remarks of readers and a foot."""
    remarks = "".join(f'<div class="k7"><div class="k8">Reader {i * 7 + j}</div><p>I have a view on matter {i * 3 + j}, and a long one.</p></div>' for j in range(i % 3 + 1))
    links = "".join(f'<div><a href="/{i}/{j}">See also {i * 5 + j}</a></div>' for j in range(4))
    text = "".join(f"<p>Line {j} of story {i} says something of its own, at some length, as stories do.</p>" for j in range(lines + i % 4))
    return page(
        i,
        f'<div class="a1"><a href="/">Start</a> <a href="/p{i}">Page {i}</a></div><div class="a2">Today only: offer {i * 11}!</div>'
        f'<div class="a3"><div class="b1"><h1>Story number {i}</h1></div><div class="b2">{text}<p>Follow us for more of this.</p><div class="b3">{links}</div><div class="b4">{remarks}</div></div></div>'
        f'<div class="a4">Foot of page {i}</div>',
    )


def test_templates_decide_without_names(spark):
    rows = [(i, f"http://plain.example/{i}", neutral(i)) for i in range(9)]
    frame = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "page_id as host", "url as container", "1 as pages")
    got = {r["page_id"]: r["text"] for r in template_html.extract(frame).collect()}
    for i in range(9):
        want = [f"Story number {i}"] + [f"Line {j} of story {i} says something of its own, at some length, as stories do." for j in range(3 + i % 4)]
        assert got[i] == "\n".join(want)
        # Without the template all of the page stays.
        bare = template_html.main_text(neutral(i), None, None, [], [], set())
        assert bare != got[i] and "Today only" in bare and "Reader" in bare and "See also" in bare
    (template,) = template_html.templates(frame.withColumn("host", F.lit("plain.example"))).collect()
    labels = [x["label"] for x in template["outline"]]
    assert template["pages"] == 9 and labels.index("div.a1") < labels.index("div.a2") < labels.index("h1") and "body.site" in labels


def test_classes_need_order_and_nesting():
    def element(key, up, label, place, vector=1, most=1, chars=10):
        return {"key": key, "up": up, "label": label, "article": False, "token": 0, "pages": 10, "vector": vector, "most": most, "chars": chars, "linked": 0, "own": chars, "place": place * 10}

    base = [element(1, 0, "html", 1, chars=500), element(2, 1, "body", 2, chars=500), element(3, 2, "div.x", 3, chars=100), element(4, 2, "div.y", 4, chars=400)]
    split = [element(5, 3, "p", 5, vector=9, most=3), element(6, 4, "p", 6, vector=9, most=3)]
    found = template_html.deduce(10, 1, [*base, *split], [], [])
    assert [x for x, _ in found.outline] == ["html", "body", "div.x", "div.y"] and found.container == 4  # one class in two slots is not nested
    turned = [{"key": 3, "token": 4, "pages": 5}]
    assert "div.x" not in [x for x, _ in template_html.deduce(10, 1, base, turned, []).outline]


def test_deep_pages_are_read_whole():
    deep = "<div>" * 30_000 + "<p>bottom</p>"
    assert template_html.main_text(deep, None, None, [], [], set()) == "bottom"


BASE = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def luhn(digits):
    return sum((2 * int(d) - 9 * (int(d) > 4)) if i % 2 else int(d) for i, d in enumerate(reversed(digits))) % 10 == 0


def base_model(text):
    out = []
    for kind, pattern in BASE.items():
        for m in re.finditer(pattern, text or ""):
            digits = re.sub("[^0-9]", "", m[0])
            good = {"email": True, "ip": kind == "ip" and all(int(p) <= 255 for p in m[0].split(".")), "card": 13 <= len(digits) <= 19 and luhn(digits or "1"), "phone": 9 <= len(digits) <= 15}[kind]
            if good:
                out.append(f"{kind}:{m.start()}:{m.end()}")
    return ",".join(out)


def test_personal_data_base_spans(spark, dirty, empty, tmp_path):
    rng = np.random.default_rng(2)
    parts = ["a@b.c", "@", ".", "+", "1", "2.3", "255.", "4111 1111 1111 1111", "-", " ", "(", "x_", "é", "😀", "\n", "%", "00", "+1 (555) 123-4567", "1.2.3.4", "@d-e.fr"]
    rows = [(1000 + i, "".join(rng.choice(parts, rng.integers(0, 25)))) for i in range(600)]
    docs = dirty.select("doc_id", "text").union(spark.createDataFrame(rows, "doc_id long, text string"))
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    got = queries.op3_contextual_pii(spark, str(tmp_path)).collect()
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    assert len(got) == docs.count()
    for r in got:
        expected = base_model(texts[r["doc_id"]])
        assert r["base_sha256"] == hashlib.sha256(expected.encode()).hexdigest()
        assert set(filter(None, expected.split(","))) <= set(filter(None, r["spans"].split(",")))
    assert contextual_pii.scan(empty).count() == 0
    masked = contextual_pii.redact(dirty)
    assert masked.columns == dirty.columns and masked.count() == 12
    assert {r["text"] for r in masked.where("doc_id is null or doc_id in (1, 7)").collect()} == {None, "no id here [EMAIL]", "ünï çødé 日本語 text 😀 mail [EMAIL] now"}


def test_contexts_find_unseen_identifiers(spark):
    rows = [(i, f"his home phone +1 555 {1000 + i} {2000 + i} bye") for i in range(9)]
    rows += [(30, "his home phone 0171-8826-123 bye"), (31, "value 0171-8826-123 and code 77-1"), (32, "her lucky number 0171-8826-999 bye")]
    got = {r["doc_id"]: r["text"] for r in contextual_pii.redact(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[0] == "his home phone [PHONE] bye" and got[30] == "his home phone [PHONE] bye" and got[31] == "value [PHONE] and code 77-1" and got[32] == rows[-1][1]


def mention_model(text):
    """(start, end, word, context, seed) of base matches and the mentions between them."""
    cuts = []
    for a, b, order in sorted((int(a), -int(b), contextual_pii.KINDS.index(k)) for k, a, b in (x.split(":") for x in base_model(text).split(",") if x)):
        if cuts and a < cuts[-1][1]:
            cuts[-1][1] = max(cuts[-1][1], -b)
        else:
            cuts.append([a, -b, order])
    inner, found = re.compile(r"(?<!\S)[^\s0-9@]*[0-9@]\S*(?:\x20[(+]?[0-9][0-9()./+-]*(?!\S))*"), []
    for (_, at, _), (end, stop, order) in zip([(0, 0, 0), *cuts], [*cuts, (len(text), len(text), None)], strict=True):
        found += [(at + m.start(), at + m.end(), None) for m in inner.finditer(text[at:end])]
        found += [(end, stop, order)] * (order is not None)
    out, at, left = [], 0, "^ ^ "
    for start, end, order in found:
        words = (left + text[at:start]).split()[-2:]
        context = re.sub(r"[^\w=@#:^]+", " ", re.search(r"\S+(\s+\S+)?$", (left + text[at:start]).rstrip())[0].lower()) if words else ""
        word = text[start:end]
        if order is None:
            bare = re.sub(contextual_pii.OPENING, "", word)
            word = re.sub(contextual_pii.CLOSING, "", bare)
            out.append((end - len(bare), end - len(bare) + len(word), word, context, None))
        else:
            out.append((start, end, word, context, order))
        at, left = end, "# "
    return out


def discovery_model(mentions):
    """(order, word) that ``discover`` should find, in plain sets and sums."""
    graph = {}
    for _, _, word, context, seed in mentions:
        if word:
            graph.setdefault((context, word), set()).update({seed} - {None})
    seeds = {(w, o) for (_, w), orders in graph.items() for o in orders}
    score = dict.fromkeys(seeds, 1.0)

    def plausible(w, o):
        n = len(re.sub("[^0-9]", "", w))
        return (("@" in w and len(w) >= 5), bool(re.match(r"[0-9A-Fa-f]+([.:][0-9A-Fa-f]*){2,}$", w)), 12 <= n <= 19 and not re.search("[A-Za-z]", w), 7 <= n <= 15 and not re.search("[A-Za-z@]", w))[o]

    for _ in range(contextual_pii.ROUNDS):
        doubt = {}
        for context in {c for c, _ in graph}:
            words = [w for c, w in graph if c == context]
            for o in range(4):
                share = sum(score.get((w, o), 0) for w in words) / len(words)
                if sum(o in graph[context, w] for w in words) >= contextual_pii.LEAST_SEEDS and share >= contextual_pii.LEAST_SHARE:
                    for w in words:
                        if not graph[context, w] and plausible(w, o):
                            doubt[w, o] = doubt.get((w, o), 1.0) * max(1e-9, 1 - share)
        score = dict.fromkeys(seeds, 1.0) | {k: 1 - d for k, d in doubt.items() if 1 - d >= contextual_pii.LEAST_SCORE and k not in seeds}
    return {(o, w) for w, o in set(score) - seeds}


def test_discovery_equals_brute_force(spark):
    rng = np.random.default_rng(11)
    lead = ["we call him", "pay by card", "to reach me at", "from the address", "box", "ref", "the"]
    marks = ["+1 555 {} 2000", "0171 882 {}", "{}-882-61", "411111111111{}", "4111 1111 1111 1111", "a{}@b.co", "a{}@b", "10.0.0.{}", "10.0.{}", "{}", "(0{}) 77 88, "]
    rows = []
    for i in range(600):
        # Some leads come with base matches nearly always, others with anything.
        def one(j):
            usual = [[0], [4], [5], [7]][j % 4] if j < 4 and rng.random() < 0.9 else range(len(marks))
            return f"{lead[j]} {marks[rng.choice(usual)].format(rng.integers(100, 250))}"

        rows.append((i, rng.choice([" ", " and ", "; ", ". "]).join(one(rng.integers(0, len(lead))) for _ in range(rng.integers(0, 4)))))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    prepared = contextual_pii.prepare(docs)
    mentions = {r["doc_id"]: [tuple(m) for m in r["mentions"]] for r in prepared.collect()}
    for i, text in rows:
        assert mentions[i] == mention_model(text), text
    want = discovery_model([m for i, _ in rows for m in mentions[i]])
    assert {(r["order"], r["word"]) for r in contextual_pii.discover(prepared).collect()} == want and want


def test_long_texts_of_numbers(spark):
    """Work grows with the text, not with its square."""
    docs = spark.createDataFrame([(1, "1.2.3.4 12345 " * 20_000)], "doc_id long, text string")
    assert contextual_pii.scan(docs).selectExpr("size(base)").first()[0] == 20_000
    assert contextual_pii.redact(docs).first()["text"] == "[IP] 12345 " * 20_000


def test_groups_and_beginnings(spark):
    rows = [(i, f"+1 555 {1000 + i} {2000 + i} is his") for i in range(9)] + [(20 + i, f"Phone: +1 555 {3000 + i} {2000 + i}") for i in range(9)]
    rows += [(40, "0171 882 6123 is hers"), (41, "Phone: 0171 882 6124"), (42, "Room 0171 882 6125")]
    got = {r["doc_id"]: r["text"] for r in contextual_pii.redact(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[40] == "[PHONE] is hers" and got[41] == "Phone: [PHONE]" and got[42] == rows[-1][1]
