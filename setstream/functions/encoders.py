"""From values to elements of the universe, as columns; each has an equal SQL text where queries are checked by SQL."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from .hashing import UNIVERSE


def string_id(s: Column) -> Column:
    """The first 32 bits of the md5 digest, below the universe's bound."""
    return F.conv(F.substring(F.md5(s.cast("binary")), 1, 8), 16, 10).cast("bigint") % F.lit(UNIVERSE).cast("bigint")


def string_id_sql(s: str) -> str:
    return f"(('0x' || substr(md5({s}), 1, 8))::BIGINT % {UNIVERSE})"


def words(text: Column) -> Column:
    return F.filter(F.split(F.lower(F.coalesce(text, F.lit(""))), r"\s+"), lambda w: w != "")


def words_sql(text: str) -> str:
    return f"list_filter(string_split_regex(lower(coalesce({text}, '')), '\\s+'), lambda w: w <> '')"


def shingles(text: Column, width: int = 3) -> Column:
    """Runs of ``width`` words; a shorter text has none."""

    def runs(w: Column) -> Column:
        n = F.size(w) - (width - 1)
        return F.when(n > 0, F.transform(F.sequence(F.lit(1), n), lambda i: F.array_join(F.slice(w, i, F.lit(width)), " "))).otherwise(F.array().cast("array<string>"))

    # The words are bound once as a variable of the outer lambda; named inside the inner one they would be split again for every run.
    return F.flatten(F.transform(F.array(words(text)), runs))


def links(html: Column) -> Column:
    return F.regexp_extract_all(F.coalesce(html, F.lit("")), F.lit('href="([^"]*)"'), F.lit(1))


def json_key(props: Column, key: str = "k") -> Column:
    return F.from_json(props, f"{key} INT")[key].cast("bigint")


def top_dims(vector: Column, t: int = 8) -> Column:
    """Positions (from 0) of the ``t`` largest coordinates, ties to the smaller position."""
    ranked = F.array_sort(F.transform(vector, lambda x, i: F.struct((-x).alias("x"), i.alias("i"))))
    return F.transform(F.slice(ranked, 1, t), lambda s: s["i"].cast("bigint"))
