"""From scored pairs to links: thresholds, best matches, top N, consistent numbers."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.similarity import numbers_consistent


def accept(scored: DataFrame, tau: float) -> DataFrame:
    return scored.where(F.col("score") > tau)


def ladder(scored: DataFrame, taus: tuple[float, ...] = (0.6, 0.7, 0.8)) -> DataFrame:
    """Each pair once for each threshold that it exceeds; scored once for all."""
    steps = F.filter(F.array(*map(F.lit, taus)), lambda t: F.col("score") > t)
    return scored.withColumn("tau", F.explode(steps))


def with_edits(scored: DataFrame, left: DataFrame, right: DataFrame) -> DataFrame:
    """Edit distances of those pairs that tie for the best place of their ``id_1``; null elsewhere."""
    top = scored.groupBy("id_1").agg(F.max("score").alias("top"))
    first = scored.join(top, "id_1").where("score = top").select("id_1", "id_2")
    tied = first.join(first.groupBy("id_1").agg(F.count("*").alias("ties")).where("ties > 1"), "id_1", "left_semi")
    texts = tied.join(left.select(F.col("id").alias("id_1"), F.lower("address").alias("x")), "id_1").join(right.select(F.col("id").alias("id_2"), F.lower("address").alias("y")), "id_2")
    return scored.join(texts.select("id_1", "id_2", F.levenshtein("x", "y").alias("edit")), ["id_1", "id_2"], "left")


def best_match(scored: DataFrame, ties: str = "id") -> DataFrame:
    """The best ``id_2`` of each ``id_1``. Ties: ``id`` takes the smallest, ``edit`` the least ``edit`` column, ``all`` keeps them."""
    if ties == "all":
        return scored.withColumn("r", F.rank().over(Window.partitionBy("id_1").orderBy(F.desc("score")))).where("r = 1").drop("r")
    order = [F.desc("score"), *([F.asc_nulls_last("edit")] if ties == "edit" else []), F.asc("id_2")]
    return scored.withColumn("r", F.row_number().over(Window.partitionBy("id_1").orderBy(*order))).where("r = 1").drop("r")


def top_n(scored: DataFrame, n: int = 3) -> DataFrame:
    """The n best of each ``id_1`` with their ranks; the rank filter reaches into the window's sort."""
    return scored.withColumn("rank", F.row_number().over(Window.partitionBy("id_1").orderBy(F.desc("score"), "id_2"))).where(F.col("rank") <= n)


def first_consistent(top: DataFrame, left: DataFrame, right: DataFrame, require_nonempty: bool = False) -> DataFrame:
    """For every left address the best-ranked of its top matches with consistent numbers; null ``id_2`` where none is."""
    texts = top.join(left.select(F.col("id").alias("id_1"), F.col("address").alias("x")), "id_1").join(right.select(F.col("id").alias("id_2"), F.col("address").alias("y")), "id_2")
    good = texts.where(numbers_consistent(F.col("x"), F.col("y"), require_nonempty)).groupBy("id_1").agg(F.min(F.struct("rank", "id_2", "score")).alias("m"))
    return left.select(F.col("id").alias("id_1")).join(good, "id_1", "left").select("id_1", F.col("m.id_2").alias("id_2"), F.col("m.score").alias("score"), F.col("m.rank").alias("rank"))


def cleanse(raw: DataFrame, reference: DataFrame, best: DataFrame) -> DataFrame:
    """Every raw address with its reference form (null without a link)."""
    found = best.join(reference.select(F.col("id").alias("id_2"), F.col("address").alias("clean")), "id_2").select(F.col("id_1").alias("id"), "id_2", "clean", "score")
    return raw.select("id", "address").join(found, "id", "left")


def mutual_best(scored: DataFrame) -> DataFrame:
    """Pairs that are each other's best match."""
    back = best_match(scored.select(F.col("id_2").alias("id_1"), F.col("id_1").alias("id_2"), "score")).select(F.col("id_2").alias("id_1"), F.col("id_1").alias("id_2"))
    return best_match(scored).join(back, ["id_1", "id_2"])


def pick_tau(report: DataFrame) -> DataFrame:
    """The threshold of a ladder report with the largest F (the smaller one of equals)."""
    return report.orderBy(F.desc("f"), "tau").limit(1).select("tau", "f")
