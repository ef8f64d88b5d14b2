"""Similarities of two addresses. All are columns; null where both bags are empty.

Two measures go by one name in the literature: ``ratio`` divides the common tokens by the union, ``pooled`` counts
a common token once for each side, 2i / (n1 + n2). They rank alike: pooled = 2 ratio / (1 + ratio).
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

from .bags import bag_histogram, bag_tags
from .tokens import let, numeric_tokens, tokenise, words


def overlap(a: Column, b: Column, bag: bool = True) -> Column:
    """Tokens that two arrays share; as bags the lesser of their multiplicities counts."""
    return F.size(F.array_intersect(bag_tags(a), bag_tags(b)) if bag else F.array_intersect(a, b))


def _sizes(a: Column, b: Column, bag: bool) -> tuple[Column, Column]:
    return (F.size(a), F.size(b)) if bag else (F.size(F.array_distinct(a)), F.size(F.array_distinct(b)))


def union_size(n1: Column, n2: Column, i: Column) -> Column:
    return n1 + n2 - i


def from_counts(measure: str, n1: Column, n2: Column, i: Column) -> Column:
    """A measure from the bags' sizes and their overlap."""
    n1, n2, i = n1.cast("double"), n2.cast("double"), i.cast("double")
    return {
        "pooled": lambda: F.try_divide(2 * i, n1 + n2), "ratio": lambda: F.try_divide(i, union_size(n1, n2, i)),
        "containment": lambda: F.try_divide(i, n1), "overlap": lambda: F.try_divide(i, F.least(n1, n2)),
    }[measure]()


def pooled(a: Column, b: Column, bag: bool = True) -> Column:
    return from_counts("pooled", *_sizes(a, b, bag), overlap(a, b, bag))


def ratio(a: Column, b: Column, bag: bool = True) -> Column:
    return from_counts("ratio", *_sizes(a, b, bag), overlap(a, b, bag))


def containment(a: Column, b: Column) -> Column:
    return from_counts("containment", F.size(a), F.size(b), overlap(a, b))


def overlap_coef(a: Column, b: Column) -> Column:
    return from_counts("overlap", F.size(a), F.size(b), overlap(a, b))


def cosine_bag(a: Column, b: Column) -> Column:
    """Cosine of two histograms."""
    norm = lambda m: F.aggregate(F.map_values(m), F.lit(0).cast("long"), lambda s, v: s + v * v)
    dot = lambda x, y: F.aggregate(F.map_keys(x), F.lit(0).cast("long"), lambda s, k: s + F.coalesce(F.element_at(x, k) * F.element_at(y, k), F.lit(0)))
    return let(bag_histogram(a), lambda x: let(bag_histogram(b), lambda y: F.try_divide(dot(x, y).cast("double"), F.sqrt((norm(x) * norm(y)).cast("double")))))


def weighted_ratio(a: Column, b: Column, idf: Column) -> Column:
    """Share of the union's weight that is common; ``idf`` maps tokens to weights, unknown tokens weigh 1."""
    weigh = lambda t: F.aggregate(t, F.lit(0.0), lambda s, k: s + F.coalesce(F.element_at(idf, k), F.lit(1.0)))
    return F.try_divide(weigh(F.array_intersect(a, b)), weigh(F.array_union(a, b)))


def to_ratio(d: Column | float):
    return d / (2 - d)


def to_pooled(j: Column | float):
    return 2 * j / (1 + j)


def equivalent(score: Column, tau: float) -> Column:
    """The score exceeds the threshold."""
    return score > F.lit(tau)


def two_round(left: Column, right: Column, outer: str = "phrases", inner: str = "chars", measure: Callable = pooled) -> Column:
    """The inner tokens' similarity if the outer bags share a token, else 0."""
    shared = F.arrays_overlap(tokenise(outer, left), tokenise(outer, right))
    return F.when(shared, measure(tokenise(inner, left), tokenise(inner, right))).otherwise(F.lit(0.0))


def edit(a: Column, b: Column) -> Column:
    return F.levenshtein(a, b)


def edit_similarity(a: Column, b: Column) -> Column:
    return 1 - F.try_divide(F.levenshtein(a, b).cast("double"), F.greatest(F.length(a), F.length(b)))


def monge_elkan(left: Column, right: Column, sym: str = "mean") -> Column:
    """Mean over the words of one side of the best edit similarity on the other; made symmetric by mean, or max, or not."""

    def one_way(x: Column, y: Column) -> Column:
        best = F.transform(x, lambda a: F.array_max(F.transform(y, lambda b: 1 - F.levenshtein(a, b).cast("double") / F.greatest(F.length(a), F.length(b)))))
        return F.when((F.size(x) > 0) & (F.size(y) > 0), F.aggregate(best, F.lit(0.0), lambda s, v: s + v) / F.size(x))

    both = {"none": one_way, "mean": lambda x, y: (one_way(x, y) + one_way(y, x)) / 2, "max": lambda x, y: F.greatest(one_way(x, y), one_way(y, x))}[sym]
    return let(words(left), lambda x: let(words(right), lambda y: both(x, y)))


def numbers_consistent(left: Column, right: Column, require_nonempty: bool = False, digits_in_words: bool = False) -> Column:
    """One set of numeric tokens holds the other. An empty set is held by any, unless it's asked to be non-empty."""
    x, y = numeric_tokens(left, digits_in_words), numeric_tokens(right, digits_in_words)
    held = (F.size(F.array_except(x, y)) == 0) | (F.size(F.array_except(y, x)) == 0)
    return held & (F.size(x) > 0) & (F.size(y) > 0) if require_nonempty else held


MEASURES: dict[str, Callable[[Column, Column], Column]] = {
    "pooled": pooled, "ratio": ratio, "containment": containment, "overlap": overlap_coef, "cosine": cosine_bag,
    "pooled_set": lambda a, b: pooled(a, b, False), "ratio_set": lambda a, b: ratio(a, b, False),
}


def register_measure(name: str, make: Callable[[Column, Column], Column]) -> None:
    """Make a measure of two token arrays known by name. Blocking loses no link above a threshold only where the
    measure implies a shared token there."""
    MEASURES[name] = make
