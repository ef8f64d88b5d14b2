"""Bags (multisets) of tokens in forms that array and map functions can work on."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from .tokens import let

ALPHABET = "abcdefghijklmnopqrstuvwxyz0123456789"


def count_in(tokens: Column, token: Column) -> Column:
    return F.size(F.filter(tokens, lambda x: x == token))


def bag_tags(tokens: Column) -> Column:
    """Each token with its ordinal among equal ones, so that set functions count repeats."""
    return let(tokens, lambda w: F.flatten(F.transform(F.array_distinct(w), lambda t: F.transform(F.sequence(F.lit(1), count_in(w, t)), lambda i: F.concat(t, F.lit("#"), i.cast("string"))))))


def bag_histogram(tokens: Column) -> Column:
    """Map of each token to its number."""
    return let(tokens, lambda w: F.map_from_entries(F.transform(F.array_distinct(w), lambda t: F.struct(t, count_in(w, t)))))


def bag_vector(text: Column, alphabet: str = ALPHABET) -> Column:
    """How often each character of a fixed alphabet stands in a (folded) text."""
    return F.transform(F.array(*map(F.lit, alphabet)), lambda c: F.length(text) - F.length(F.replace(text, c)))


def bag_size(tokens: Column) -> Column:
    return F.size(tokens)


def char_bag(text: Column, other: str) -> Column:
    """Character bag for scoring: counts over letters and digits of ASCII, ordinal tags for the rest, and the size.

    ``other`` is the pattern of characters that don't count.
    """
    def made(kept: Column) -> Column:
        rest = F.filter(F.split(F.regexp_replace(kept, "[a-z0-9]", ""), ""), lambda c: c != "")
        return F.struct(bag_vector(kept).alias("v"), bag_tags(rest).alias("t"), F.length(kept).alias("n"))

    return let(F.regexp_replace(F.lower(text), other, ""), made)


def char_overlap(a: Column, b: Column) -> Column:
    """Characters that two bags of ``char_bag`` have in common, repeats counted."""
    return F.aggregate(F.zip_with(a["v"], b["v"], lambda x, y: F.least(x, y)), F.lit(0), lambda x, y: x + y) + F.size(F.array_intersect(a["t"], b["t"]))
