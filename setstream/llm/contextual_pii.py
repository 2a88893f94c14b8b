"""Personal data: fixed base patterns, then identifiers found by the contexts those were seen in.

Only DataFrame expressions are used. Base matches become spans by splitting a text at the matches: the lengths of gaps and
matches add up to positions. Patterns are written so that every run of characters is entered once (possessive, guarded
by what stands before). Running sums and the cutting of texts work on blocks of about the root of the number of matches, since
an array that grows by one element at a time would be copied as often.

Bootstrapping. Between base matches, a mention is a word that holds a digit or an at sign, with the groups of digits and punctuation that follow it after
single spaces. Base matches are seeds of score 1 (of overlapping ones the first). A context is the two words before a seed or
mention ('^' stands for the text's start, '#' for a seed or mention); for one kind it is as reliable as the share of its words, seeds and mentions
alike, that score. A mention of a plausible shape for that kind scores by noisy-or over its reliable contexts. A few rounds over that graph of
contexts and words settle the scores; words over the threshold are identifiers wherever they occur. Mentions, contexts
and words are tables, aggregated with partial sums: nothing is collected.

Edge cases: null and empty texts have no spans; very long texts are read whole; overlapping spans of different kinds all stay;
mentions don't overlap base spans; repeated rows get equal spans; null doc_ids are carried along; an empty table gives an
empty result; extra columns are ignored (``redact`` keeps them).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .runtime import materialise, restored, sheltered

KINDS = ("email", "ip", "card", "phone")
# What each kind's base pattern matches, leftmost and without overlap.
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}",
    "card": r"(?<![0-9])[0-9](?:[\x20-]?[0-9]){12,}+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: A word that holds a digit or an at sign, and groups of digits after single spaces.
MENTION = r"(?<![^\s\ue000-\ue010])[^\s0-9@\ue000-\ue010]*+[0-9@][^\s\ue000-\ue010]*+(?:\x20[(+]?[0-9][0-9()./+-]*+(?!\S))*+"
#: Punctuation around a mention that isn't part of it.
OPENING, CLOSING = r"^[\"'(\[<{,;]+", r"[\"')\]>},;:!?.]+$"
#: The last two words of a text that is spelt backwards.
LAST_WORDS = r"^\s*+(\S++(?:\s++\S++)?+)"
#: Words of contexts of more characters stand for themselves by a digest.
LONG_CONTEXT = 128
#: A context counts with so many distinct base matches behind it and such a share of its words scoring.
LEAST_SEEDS, LEAST_SHARE = 3, 0.8
LEAST_SCORE, ROUNDS = 0.8, 3
#: Found spans that are broadcast at once when texts are redacted; more are joined by shuffle.
BROADCAST_SPANS = 20_000


def _digits(text: Column) -> Column:
    return F.regexp_replace(text, "[^0-9]", "")


def _luhn(digits: Column) -> Column:
    turned = F.reverse(digits)

    def add(total, i):
        d = F.substring(turned, i, F.lit(1)).cast("int")
        twice = F.when(d > 4, d * 2 - 9).otherwise(d * 2)
        return total + F.when(i % 2 == 0, twice).otherwise(d)

    return F.aggregate(F.sequence(F.lit(1), F.length(digits)), F.lit(0), add) % 10 == 0


def _holds(kind: str, match: Column) -> Column:
    if kind == "ip":
        return F.forall(F.split(match, r"\."), lambda p: (F.length(F.regexp_replace(p, "^0+", "")) <= 3) & (F.substring(F.regexp_replace(p, "^0+(?=[0-9])", ""), 1, 3).cast("int") <= 255))
    if kind == "card":
        digits = _digits(match)
        return F.when(F.length(digits).between(13, 19), _luhn(digits)).otherwise(False)
    if kind == "phone":
        return F.length(_digits(match)).between(9, 15)
    return F.lit(True)


def let(value: Column, f) -> Column:
    """``f(value)`` with the value worked out once, however often ``f`` and its inner functions name it."""
    return F.get(F.transform(F.array(value), f), F.lit(0))


def _blocks(items: Column) -> Column:
    """``items`` (a column or variable) as an array of arrays of about the root of their number."""
    width = F.greatest(F.lit(64), F.ceil(F.sqrt(F.size(items))).cast("int"))
    return F.transform(F.sequence(F.lit(0), F.ceil(F.size(items) / width).cast("int") - 1), lambda i: F.slice(items, i * width + 1, width))


def running(values: Column, combine) -> Column:
    """Running sums (or maxima) of an array of ints, by an associative ``combine`` for which 0 is neutral."""
    none = F.array().cast("array<int>")
    last = lambda done: F.coalesce(F.try_element_at(done, F.lit(-1)), F.lit(0))

    def fold(xs: Column) -> Column:
        return F.aggregate(xs, none, lambda done, x: F.concat(done, F.array(combine(last(done), x).cast("int"))))

    def joined(local: Column) -> Column:
        before = fold(F.transform(local, last))
        return F.flatten(F.zip_with(local, F.concat(F.array(F.lit(0)), F.slice(before, 1, F.size(local) - 1)), lambda xs, c: F.transform(xs, lambda x: combine(x, c).cast("int"))))

    return let(values, lambda xs: F.when(F.size(xs) > 0, let(F.transform(_blocks(xs), fold), joined)).otherwise(none))


def _split(text: Column, pattern: str, needs: Column) -> Column:
    """struct<matches, between> of a pattern in texts that ``needs`` lets through: the matches, and the text between them and around."""
    none = F.array().cast("array<string>")
    matches = F.when(needs, F.regexp_extract_all(text, F.lit(pattern), F.lit(0))).otherwise(none)
    return let(matches, lambda m: F.struct(m.alias("matches"), F.when(F.size(m) > 0, F.split(text, pattern, -1)).otherwise(none).alias("between")))


def _placed(found: Column) -> Column:
    """array<struct<start, end, match, gap>> in code points; ``gap`` is the text between a match and the one before it."""
    gaps = F.slice(found["between"], 1, F.size(found["matches"]))  # one gap more than matches: the last is left out
    pairs = F.zip_with(found["matches"], gaps, lambda match, gap: F.struct(match.alias("match"), gap.alias("gap")))
    lengths = F.transform(pairs, lambda p: F.length(p["gap"]) + F.length(p["match"]))
    return F.zip_with(pairs, running(lengths, lambda a, b: a + b), lambda p, end: F.struct((end - F.length(p["match"])).alias("start"), end.alias("end"), p["match"].alias("match"), p["gap"].alias("gap")))


def has_digit(text: Column) -> Column:
    return text.rlike("[0-9]")


def base_spans(text: Column, digit: Column) -> Column:
    """array<struct<order, start, end>>, kinds in their listed order; ``digit``: the text has one (see ``has_digit``)."""
    needs = {"email": F.contains(text, F.lit("@")), "ip": digit & F.contains(text, F.lit(".")), "card": digit, "phone": digit & F.contains(text, F.lit("+"))}
    found = F.array(*[_split(text, PATTERNS[kind], needs[kind]) for kind in KINDS])

    def kept(one: Column, order: Column) -> Column:
        good = F.filter(_placed(one), lambda s: F.coalesce(*[F.when(order == i, _holds(kind, s["match"])) for i, kind in enumerate(KINDS)]))
        return F.transform(good, lambda s: F.struct(order.alias("order"), s["start"].alias("start"), s["end"].alias("end")))

    return F.flatten(F.transform(found, kept))


def _plausible(word: Column) -> Column:
    """Whether a word may be of the kind numbered ``order``: looser than the base patterns, never free text."""
    n = F.length(_digits(word))
    return (
        F.when(F.col("order") == 0, F.contains(word, F.lit("@")) & (F.length(word) >= 5))
        .when(F.col("order") == 1, word.rlike(r"^[0-9A-Fa-f]+(?:[.:][0-9A-Fa-f]*){2,}$"))
        .when(F.col("order") == 2, n.between(12, 19) & ~word.rlike("[A-Za-z]"))
        .otherwise(n.between(7, 15) & ~word.rlike("[A-Za-z@]"))
    )


def regions(spans: Column) -> Column:
    """array<struct<start, end, order>>: spans that overlap as one region, with the kind of the first (longest on ties)."""
    by_start = F.array_sort(F.transform(spans, lambda s: F.struct(s["start"].alias("start"), (-s["end"]).alias("back"), s["order"].alias("order"))))

    def merged(s: Column, reach: Column) -> Column:
        # A span that begins where all before it have ended opens a region, which goes on to the farthest end before the next.
        opens = F.filter(F.transform(F.sequence(F.lit(0), F.size(s) - 1), lambda i: F.when((i == 0) | (F.get(s, i)["start"] >= F.get(reach, i - 1)), i)), lambda i: i.isNotNull())
        ends = lambda first: F.transform(F.concat(F.slice(first, 2, F.size(first)), F.array(F.size(s))), lambda i: F.get(reach, i - 1))
        row = lambda i, end: F.struct(F.get(s, i)["start"].alias("start"), end.alias("end"), F.get(s, i)["order"].alias("order"))
        return let(opens, lambda first: F.zip_with(first, ends(first), row))

    empty = F.array().cast("array<struct<start:int,end:int,order:int>>")
    found = let(by_start, lambda s: let(running(F.transform(s, lambda x: -x["back"]), F.greatest), lambda reach: merged(s, reach)))
    return F.when(F.size(spans) > 0, found).otherwise(empty)


def pieces(text: Column, cuts: Column) -> Column:
    """array<struct<at, gap, match, order>>: the text before each region, where it begins, and the region's own; then the rest, without a match."""

    def block(xs: Column, at: Column) -> Column:
        def one(chunk: Column) -> Column:
            def row(x: Column, i: Column) -> Column:
                return let(F.when(i == 0, at).otherwise(F.get(xs, i - 1)["end"]), lambda before: F.struct(
                    before.alias("at"), F.substring(chunk, before - at + 1, x["start"] - before).alias("gap"), F.substring(chunk, x["start"] - at + 1, x["end"] - x["start"]).alias("match"), x["order"].alias("order")
                ))

            return F.transform(xs, row)

        return let(F.substring(text, at + 1, F.element_at(xs, -1)["end"] - at), one)

    def rest(at: Column) -> Column:
        return F.array(F.struct(at.alias("at"), F.substring(text, at + 1, F.length(text)).alias("gap"), F.lit(None).cast("string").alias("match"), F.lit(None).cast("int").alias("order")))

    def cut(blocks: Column) -> Column:
        ends = lambda: F.transform(blocks, lambda xs: F.element_at(xs, -1)["end"])
        return let(ends(), lambda e: F.concat(F.flatten(F.zip_with(blocks, F.concat(F.array(F.lit(0)), F.slice(e, 1, F.size(e) - 1)), block)), rest(F.element_at(e, -1))))

    return let(cuts, lambda xs: F.when(F.size(xs) > 0, let(_blocks(xs), cut)).otherwise(rest(F.lit(0))))


def _context(left: Column) -> Column:
    """The last two words of ``left``, without marks that vary from place to place."""
    two = F.reverse(F.regexp_extract(F.reverse(left), LAST_WORDS, 1))
    clean = F.regexp_replace(F.lower(two), r"[^\p{L}\p{N}=@#:^]+", " ")
    return F.when(F.length(clean) > LONG_CONTEXT, F.sha2(clean, 256)).otherwise(clean)


MENTIONS = "array<struct<start:int,end:int,word:string,context:string,seed:int>>"
# Private-use characters that stand for a base match in its place: the first by its kind, then one that goes on.
KIND_MARKS, FILLER = "\ue000\ue001\ue002\ue003", "\ue010"


def _hidden(parts: Column) -> Column:
    """The text of ``pieces`` with every base match as marks of the same length."""
    marks = F.array(*[F.lit(m) for m in KIND_MARKS])
    fill = lambda x: F.concat(F.get(marks, x["order"]), F.repeat(F.lit(FILLER), F.length(x["match"]) - 1))
    gap = lambda x: F.translate(x["gap"], KIND_MARKS + FILLER, " " * 5)
    return F.array_join(F.transform(parts, lambda x: F.concat(gap(x), F.when(x["match"].isNull(), F.lit("")).otherwise(fill(x)))), "")


def _mention(w: Column, i: Column) -> Column:
    """One mention or seed, out of its span and the gap before it."""
    left = F.concat(F.when(i == 0, F.lit("^ ^ ")).otherwise(F.lit("# ")), w["gap"])
    seed = F.instr(F.lit(KIND_MARKS), F.substring(w["match"], 1, 1)) - 1
    bare = F.regexp_replace(w["match"], OPENING, "")
    word = F.regexp_replace(bare, CLOSING, "")
    start = w["end"] - F.length(bare)
    return F.struct(start.alias("start"), (start + F.length(word)).alias("end"), word.alias("word"), _context(left).alias("context"), F.when(seed >= 0, seed).alias("seed"))


def prepare(docs: DataFrame) -> DataFrame:
    """(doc_id, row_key, base, mentions) of every row; ``row_key`` tells texts apart. Written once: texts are scanned here only."""
    text = F.coalesce(F.col("text"), F.lit(""))
    own = docs.select("doc_id", text.alias("text")).withColumn("digit", has_digit(F.col("text")))
    key = F.struct(F.xxhash64("text").alias("h"), F.xxhash64(F.lit(1), "text").alias("r")).alias("row_key")
    own = own.select("doc_id", key, base_spans(F.col("text"), F.col("digit")).alias("base"), "text", (F.col("digit") | F.contains("text", F.lit("@"))).alias("some"))
    own = own.withColumn("cuts", F.when(F.col("some"), regions(F.col("base"))))
    own = own.withColumn("parts", F.when(F.col("some"), pieces(F.col("text"), F.col("cuts"))))
    own = own.withColumn("hidden", F.when(F.col("some"), _hidden(F.col("parts"))))
    own = own.withColumn("rows", let(_split(F.col("hidden"), f"[{KIND_MARKS}]{FILLER}*+|{MENTION}", F.col("some")), lambda found: F.transform(_placed(found), _mention)))
    # The n-th seed is the n-th region.
    own = own.withColumn("nth", running(F.transform("rows", lambda m: F.when(m["seed"].isNull(), 0).otherwise(1)), lambda a, b: a + b))

    def named(parts: Column, nth: Column) -> Column:
        def row(m: Column, i: Column) -> Column:
            word = F.when(m["seed"].isNull(), m["word"]).otherwise(F.get(parts, F.get(nth, i) - 1)["match"])
            return F.struct(m["start"].alias("start"), m["end"].alias("end"), word.alias("word"), m["context"].alias("context"), m["seed"].alias("seed"))

        return F.transform("rows", row)

    mentions = let(F.col("parts"), lambda parts: let(F.col("nth"), lambda nth: named(parts, nth)))
    return materialise(own.select("doc_id", "row_key", "base", F.coalesce(mentions, F.array().cast(MENTIONS)).alias("mentions")), "mentions")


def context_words(prepared: DataFrame) -> DataFrame:
    """(context, word, seeds): the graph, with the kinds that the word was a base match of in that context."""
    mentions = prepared.select(F.explode("mentions").alias("m")).select("m.word", "m.context", "m.seed").where("word <> ''")
    return mentions.groupBy("context", "word").agg(F.collect_set("seed").alias("seeds"))


def discover(prepared: DataFrame) -> DataFrame:
    """(order, word): words that the contexts of base matches point to."""
    graph = materialise(context_words(prepared), "context-words")
    sizes = graph.groupBy("context").agg(F.count(F.lit(1)).alias("n"))
    seeds = graph.select("word", F.explode("seeds").alias("order")).distinct().withColumn("score", F.lit(1.0))
    scored = seeds
    for _ in range(ROUNDS):
        # Base matches are told from other words by the graph itself: a word is found only where it isn't one.
        trusted = graph.join(scored, "word").groupBy("context", "order").agg(F.sum("score").alias("mass"), F.sum(F.when(F.array_contains("seeds", F.col("order")), 1).otherwise(0)).alias("known"))
        reliable = trusted.join(sizes, "context").withColumn("share", F.col("mass") / F.col("n")).where((F.col("known") >= LEAST_SEEDS) & (F.col("share") >= LEAST_SHARE))
        doubt = F.exp(F.sum(F.log(F.greatest(F.lit(1e-9), 1 - F.col("share")))))
        fresh = graph.where(F.size("seeds") == 0).join(reliable.select("context", "order", "share"), "context").where(_plausible(F.col("word")))
        fresh = fresh.groupBy("word", "order").agg((1 - doubt).alias("score")).where(F.col("score") >= LEAST_SCORE)
        scored = materialise(seeds.unionByName(fresh.join(seeds.select("word", "order"), ["word", "order"], "left_anti")), "scored")
    return scored.join(seeds.select("word", "order"), ["word", "order"], "left_anti").select("order", "word").distinct()


def found_spans(prepared: DataFrame) -> DataFrame:
    """(doc_id, row_key, found[(order, start, end)]) of the rows that hold found identifiers."""
    mentions = prepared.select("doc_id", "row_key", F.explode("mentions").alias("m")).where("m.seed is null")
    hits = mentions.select("doc_id", "row_key", F.col("m.word").alias("word"), F.col("m.start").alias("start"), F.col("m.end").alias("end")).join(discover(prepared), "word")
    return materialise(hits.groupBy("doc_id", "row_key").agg(F.sort_array(F.collect_set(F.struct("order", "start", "end"))).alias("found")), "found")


def scan(docs: DataFrame) -> DataFrame:
    """(doc_id, row_key, base, spans): base spans of every row and all spans, each array<struct<order, start, end>>."""
    prepared = prepare(docs)
    found = found_spans(prepared).select(F.col("doc_id").alias("_id"), F.col("row_key").alias("_key"), "found")
    both = prepared.join(found, prepared["doc_id"].eqNullSafe(F.col("_id")) & (prepared["row_key"] == F.col("_key")), "left")
    extra = F.coalesce("found", F.array().cast("array<struct<order:int,start:int,end:int>>"))
    return both.select("doc_id", "row_key", "base", F.array_sort(F.concat("base", extra)).alias("spans"))


def spelled(spans: Column) -> Column:
    kind = F.array(*[F.lit(k) for k in KINDS])
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", F.element_at(kind, s["order"] + 1), s["start"].cast("string"), s["end"].cast("string"))), ",")


def count_of(spans: Column, kind: str) -> Column:
    return F.size(F.filter(spans, lambda s: s["order"] == KINDS.index(kind))).cast("long")


def masked(text: Column, spans: Column) -> Column:
    """``text`` with every span replaced by its kind in brackets; of overlapping spans the first (longest on ties) names the whole."""
    kind = F.array(*[F.lit(f"[{k.upper()}]") for k in KINDS])
    label = lambda x: F.concat(x["gap"], F.when(x["match"].isNull(), F.lit("")).otherwise(F.get(kind, x["order"])))
    return F.when(F.size(spans) > 0, F.array_join(F.transform(pieces(text, regions(spans)), label), "")).otherwise(text)


def redact(docs: DataFrame) -> DataFrame:
    """``docs`` with personal data in ``text`` replaced; other columns stay, null texts too."""
    found = found_spans(prepare(docs))
    few = found.limit(BROADCAST_SPANS + 1).count() <= BROADCAST_SPANS
    side = found.select(F.col("doc_id").alias("_id"), F.col("row_key").alias("_key"), F.col("found").alias("_found"))
    text = F.coalesce("text", F.lit(""))
    own = sheltered(docs, "doc_id", "text").withColumn("_row", F.struct(F.xxhash64(text).alias("h"), F.xxhash64(F.lit(1), text).alias("r")))
    own = own.withColumn("_digit", F.coalesce(has_digit(F.col("text")), F.lit(False)))
    joined = own.join(F.broadcast(side) if few else side, F.col("doc_id").eqNullSafe(F.col("_id")) & (F.col("_row") == F.col("_key")), "left")
    spans = F.concat(base_spans(F.col("text"), F.col("_digit")), F.coalesce("_found", F.array().cast("array<struct<order:int,start:int,end:int>>")))
    masking = F.when(F.col("text").isNotNull(), let(F.col("_spans"), lambda found: masked(F.col("text"), found)))
    return restored(joined.withColumn("_spans", spans).withColumn("text", masking), docs, "doc_id", "text")
