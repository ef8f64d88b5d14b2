"""Inverted indexes: postings, document frequencies, the recurrence cut."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.tokens import tokenise


@dataclass
class Index:
    """``postings``: token, id, tf, n (the bag's size); where known, ``bags``: id, tokens (each once), of which they were made.
    Nothing runs until it's used."""

    postings: DataFrame
    bags: DataFrame | None = None

    def frequencies(self) -> DataFrame:
        """``token, df``: in how many addresses each token stands; summed up before it moves, so that hot tokens don't."""
        return self.postings.groupBy("token").agg(F.count("*").alias("df"))

    def prune(self, k: int | None) -> Index:
        """Without tokens in more than k addresses. Counting first, restricting second: no array of a hot token's ids arises."""
        if k is None:
            return self
        return Index(self.postings.join(self.frequencies().where(F.col("df") <= k).select("token"), "token", "left_semi"))

    def common(self, k: int) -> DataFrame:
        """The tokens that the cut removes."""
        return self.frequencies().where(F.col("df") > k)

    def nested(self, max_df: int) -> DataFrame:
        """``token, ids, df`` with sorted ids, for tokens in up to ``max_df`` addresses, which bounds the arrays."""
        return self.prune(max_df).postings.groupBy("token").agg(F.sort_array(F.collect_list("id")).alias("ids"), F.count("*").alias("df"))

    def save(self, path: str, buckets: int = 64) -> None:
        """Parquet, partitioned by a bucket of the token's hash and sorted in it, so that a lookup prunes files and row groups."""
        keyed = self.postings.withColumn("bucket", F.pmod(F.xxhash64("token"), F.lit(buckets)).cast("int"))
        keyed.repartition("bucket").sortWithinPartitions("bucket", "token", "id").write.mode("overwrite").partitionBy("bucket").parquet(path)

    @staticmethod
    def load(spark: SparkSession, path: str) -> Index:
        return Index(spark.read.parquet(path).select("token", "id", "tf", "n"))

    def append(self, addresses: DataFrame, tokeniser: str = "phrases") -> Index:
        """This index and that of further addresses."""
        return Index(self.postings.unionByName(build_index(addresses, tokeniser).postings))


def build_index(addresses: DataFrame, tokeniser: str = "phrases", alphabet: str = "unicode") -> Index:
    """Postings of ``id, address``. Repeats of a token in one address are counted there, without a shuffle."""
    rows = addresses.where("id IS NOT NULL AND address IS NOT NULL")
    bags = rows.select("id", F.array_distinct(tokenise(tokeniser, F.col("address"), alphabet)).alias("tokens")).where(F.size("tokens") > 0)
    return Index(counted(rows, F.col("id"), tokenise(tokeniser, F.col("address"), alphabet)), bags)


def counted(rows: DataFrame, key: Column, tokens: Column) -> DataFrame:
    """``token, id, tf, n``: the distinct tokens of each row with their numbers, and the bag's size.

    Equal tokens stand side by side in the sorted bag; their numbers are the distances between the runs' first
    places, so that a text of any length takes a sort and a pass.
    """
    bags = rows.select(key.alias("id"), F.array_sort(tokens).alias("s")).where(F.size("s") > 0)
    first = F.transform("s", lambda x, i: F.when((i == 0) | (F.get(F.col("s"), i - 1) != x), i))
    bags = bags.withColumn("at", F.filter(first, lambda p: p.isNotNull()))
    once = F.transform("at", lambda p, j: F.struct(F.get(F.col("s"), p).alias("token"), (F.coalesce(F.get(F.col("at"), j + 1), F.size("s")) - p).alias("tf")))
    return bags.select("id", F.size("s").alias("n"), F.inline(once)).select("token", "id", "tf", "n")
