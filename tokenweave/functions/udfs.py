"""Functions that built-in ones can't express, and SQL names for the rest."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType


def jaro(a: str, b: str) -> float:
    """Jaro similarity: matches within half the longer length, and transpositions among them."""
    if not a and not b:
        return 1.0
    reach = max(len(a), len(b)) // 2 - 1
    used, matched = [False] * len(b), []
    for i, c in enumerate(a):
        for j in range(max(0, i - reach), min(len(b), i + reach + 1)):
            if not used[j] and b[j] == c:
                used[j] = True
                matched.append(c)
                break
    m = len(matched)
    if not m:
        return 0.0
    swapped = sum(x != y for x, y in zip(matched, [c for c, u in zip(b, used) if u])) // 2
    return (m / len(a) + m / len(b) + (m - swapped) / m) / 3


def jaro_winkler_plain(a: str, b: str, p: float = 0.1) -> float:
    """Jaro similarity raised for a common beginning of up to four characters where it is over 0.7."""
    x, same = jaro(a, b), 0
    while same < min(4, len(a), len(b)) and a[same] == b[same]:
        same += 1
    return x + same * p * (1 - x) if x > 0.7 else x


@F.pandas_udf(DoubleType())
def jaro_winkler(a: pd.Series, b: pd.Series) -> pd.Series:
    return pd.Series([None if x is None or y is None else jaro_winkler_plain(x, y) for x, y in zip(a, b)], dtype="float64")


@F.pandas_udf(DoubleType())
def median_of(scores: pd.Series) -> float:
    """Middle score of a group, as an aggregate over Arrow batches."""
    return float(scores.median())


class Tokens:
    """Words of a text with their places, as a table function."""

    def eval(self, text: str):
        import re

        for k, m in enumerate(re.finditer(r"[^\W_]+", (text or "").lower())):
            yield m.group(), k, m.start()


def register(spark: SparkSession) -> None:
    """SQL functions tw_pooled, tw_ratio (of token arrays), tw_numbers_consistent; table function tw_tokens."""
    tags = "flatten(transform(array_distinct({0}), t -> transform(sequence(1, size(filter({0}, y -> y = t))), i -> concat(t, '#', i))))"
    i = f"size(array_intersect({tags.format('a')}, {tags.format('b')}))"
    for name, expression in (("tw_pooled", f"try_divide(2.0D * {i}, size(a) + size(b))"), ("tw_ratio", f"try_divide(1.0D * {i}, size(a) + size(b) - {i})")):
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(a ARRAY<STRING>, b ARRAY<STRING>) RETURNS DOUBLE RETURN {expression}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION tw_numbers_consistent(a ARRAY<STRING>, b ARRAY<STRING>) RETURNS BOOLEAN RETURN size(array_except(a, b)) = 0 OR size(array_except(b, a)) = 0")
    spark.udtf.register("tw_tokens", F.udtf(Tokens, returnType="token string, place int, at int"))
