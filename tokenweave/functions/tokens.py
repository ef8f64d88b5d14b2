"""Tokens of free text, as native columns: text in, array of tokens out."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

from ..config import OTHER, WORD

ACCENTED, PLAIN = "àáâãäåçèéêëìíîïñòóôõöùúûüýÿ", "aaaaaaceeeeiiiinooooouuuuyy"


def let(value: Column, make: Callable[[Column], Column]) -> Column:
    """``make(value)`` with the value worked out once, however often and deep inside other lambdas it's named."""
    return F.element_at(F.transform(F.array(value), make), 1)


def as_text(*columns: Column) -> Column:
    """One line of text from the fields of a segmented address; null fields leave nothing."""
    return F.concat_ws(" ", *columns)


def fold(text: Column, accents: bool = False) -> Column:
    """Lower case, and letters without their accents on request. No rewriting of words."""
    low = F.lower(text)
    return F.translate(low, ACCENTED, PLAIN) if accents else low


def words(text: Column, alphabet: str = "unicode") -> Column:
    """Maximal runs of letters and digits, in order."""
    return F.regexp_extract_all(F.lower(text), F.lit(WORD[alphabet]), F.lit(0))


def chars(text: Column, keep_separators: bool = False, alphabet: str = "unicode") -> Column:
    """Single characters, without those between words unless asked for."""
    low = F.lower(text)
    kept = low if keep_separators else F.regexp_replace(low, OTHER[alphabet], "")
    return F.filter(F.split(kept, ""), lambda c: c != "")


def runs(tokens: Column, n: int) -> Column:
    """All runs of n consecutive tokens, joined by a blank."""
    def made(w: Column) -> Column:
        at = F.sequence(F.lit(1), F.size(w) - (n - 1))
        return F.when(F.size(w) >= n, F.transform(at, lambda i: F.array_join(F.slice(w, i, n), " "))).otherwise(F.array().cast("array<string>"))

    return let(tokens, made)


def phrases(text: Column, n: int = 2, alphabet: str = "unicode", mode: str = "all") -> Column:
    """Ordered phrases of n consecutive words. ``two_pass`` models phrase sets that come from two sweeps, each taking
    non-overlapping word pairs, where the second one stumbles over separators of more than one character."""
    if mode == "two_pass":
        return two_pass(text, alphabet)
    return runs(words(text, alphabet), n)


def two_pass(text: Column, alphabet: str = "unicode") -> Column:
    def every_other(w: Column) -> Column:
        at = F.sequence(F.lit(1), F.size(w) - 1, F.lit(2))
        return F.when(F.size(w) >= 2, F.transform(at, lambda i: F.array_join(F.slice(w, i, 2), " "))).otherwise(F.array().cast("array<string>"))

    low = F.lower(text)
    first = let(words(low, alphabet), every_other)
    rest = F.regexp_replace(low, f"^{OTHER[alphabet]}*{WORD[alphabet]}", "")
    second = F.flatten(F.transform(F.split(rest, OTHER[alphabet] + "{2,}"), lambda part: let(words(part, alphabet), every_other)))
    return F.array_union(first, second)


def pairs(text: Column, scope: str = "adjacent", alphabet: str = "unicode") -> Column:
    """Unordered pairs of words: neighbours, or any two of the text."""
    def made(w: Column) -> Column:
        at = F.sequence(F.lit(1), F.size(w) - 1)
        if scope == "adjacent":
            all_pairs = F.transform(at, lambda i: F.array_join(F.array_sort(F.slice(w, i, 2)), " "))
        else:
            all_pairs = F.flatten(F.transform(at, lambda i: F.transform(F.slice(w, i + 1, F.size(w)), lambda x: F.concat_ws(" ", F.least(F.element_at(w, i), x), F.greatest(F.element_at(w, i), x)))))
        return F.when(F.size(w) >= 2, all_pairs).otherwise(F.array().cast("array<string>"))

    return let(words(text, alphabet), made)


def qgrams(text: Column, q: int = 2, keep_separators: bool = False, alphabet: str = "unicode") -> Column:
    """Character q-grams of the text."""
    low = F.lower(text)
    s = low if keep_separators else F.regexp_replace(low, OTHER[alphabet], "")

    def made(x: Column) -> Column:
        at = F.sequence(F.lit(1), F.length(x) - (q - 1))
        return F.when(F.length(x) >= q, F.transform(at, lambda i: F.substring(x, i, F.lit(q)))).otherwise(F.array().cast("array<string>"))

    return let(s, made)


def numeric_tokens(text: Column, digits_in_words: bool = False) -> Column:
    """Distinct words of digits alone; or all runs of digits, also those inside words."""
    if digits_in_words:
        return F.array_distinct(F.regexp_extract_all(text, F.lit("[0-9]+"), F.lit(0)))
    return F.array_distinct(F.filter(words(text), lambda w: w.rlike("^[0-9]+$")))


TOKENISERS: dict[str, Callable[..., Column]] = {
    "words": words, "chars": chars, "phrases": phrases, "phrases3": lambda t, alphabet="unicode": phrases(t, 3, alphabet), "two_pass": two_pass,
    "pairs_adjacent": pairs, "pairs_any": lambda t, alphabet="unicode": pairs(t, "any", alphabet), "qgrams": lambda t, alphabet="unicode": qgrams(t, 2, False, alphabet),
    "numbers": lambda t, alphabet="unicode": numeric_tokens(t), "chars_spaced": lambda t, alphabet="unicode": chars(t, True, alphabet),
    "whole": lambda t, alphabet="unicode": F.array(F.array_join(words(t, alphabet), " ")),
}


def register_tokeniser(name: str, make: Callable[..., Column]) -> None:
    """Make a tokeniser, ``make(text, alphabet=...) -> array of tokens``, known by name."""
    TOKENISERS[name] = make


def tokenise(name: str, text: Column, alphabet: str = "unicode") -> Column:
    return TOKENISERS[name](text, alphabet=alphabet)
