"""The registered query of each operator: production parameters, whole tables, and the digest columns asked for."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .runtime import table


def op1_subword_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .subword_quality import classify

    return classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), threshold=0.3)


def op2_template_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .template_html import extract

    return extract(table(spark, sf_dir, "pages")).withColumn("n_chars", F.length("text").cast("long"))


def op3_contextual_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .contextual_pii import KINDS, count_of, scan, spelled

    found = scan(table(spark, sf_dir, "documents"))
    return found.select(
        "doc_id",
        *[count_of(F.col("base"), kind).alias(f"n_{kind}") for kind in KINDS],
        F.sha2(spelled(F.col("base")), 256).alias("base_sha256"),
        spelled(F.col("spans")).alias("spans"),
    )


def op4_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    from .bpe import encode_decode

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    out = encode_decode(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)
    return out.select(
        "doc_id",
        F.size("token_ids").cast("long").alias("n_tokens"),
        F.sha2(F.array_join(F.col("token_ids").cast("array<string>"), " "), 256).alias("ids_sha256"),
        F.sha2(F.col("decoded"), 256).alias("decoded_sha256"),
    )


def op5_suffix_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .suffix_dedup import repeated_passages

    return repeated_passages(table(spark, sf_dir, "documents").select("doc_id", "text"), length=50)


def op6_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .decontam import hit_words, overlaps

    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = overlaps(docs, table(spark, sf_dir, "benchmark"))
    names = F.array_sort(F.col("item_ids").cast("array<string>"))
    return found.select(
        "doc_id",
        "n_words",
        hit_words(F.col("spans")).alias("n_hit"),
        F.size("item_ids").cast("long").alias("n_items"),
        F.sha2(F.array_join(names, ","), 256).alias("items_sha256"),
        (F.size("spans") > 0).alias("contaminated"),
    )


def op7_mil_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .mil_toxicity import classify

    return classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), threshold=0.5)


def op8_multi_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .multi_index_hash import search

    return search(table(spark, sf_dir, "embeddings"), every=20, k=20)


def op9_simhash_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .simhash_trie import near_duplicates

    found = near_duplicates(table(spark, sf_dir, "documents").select("doc_id", "text"), shingle=4, radius=4)
    return found.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def op10_shard_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    from .shard_packing import pack

    placed = pack(table(spark, sf_dir, "documents").select("doc_id", "text"), shards=40)
    return placed.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


QUERIES = {f.__name__: f for f in (op1_subword_quality, op2_template_text, op3_contextual_pii, op4_byte_bpe, op5_suffix_repeats, op6_decontaminate, op7_mil_toxicity, op8_multi_index, op9_simhash_groups, op10_shard_packing)}
