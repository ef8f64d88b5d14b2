"""One query address against an index."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.similarity import from_counts
from ..functions.tokens import tokenise
from .batch import scored_pairs
from .index import Index, counted
from .tally import bag_overlaps

#: Queries that a scan takes at most: they are broadcast. Pairs that are compared at once.
MOST_QUERIES, SCANNED = 10_000, 1 << 21


def query_bags(queries: DataFrame, tokeniser: str, alphabet: str = "unicode") -> DataFrame:
    """``query_id, nq, token, tf_q`` of queries ``id, address``."""
    found = counted(queries, F.col("id"), tokenise(tokeniser, F.col("address"), alphabet))
    return found.select(F.col("id").alias("query_id"), F.col("n").alias("nq"), "token", F.col("tf").alias("tf_q"))


def query_classes(index: Index, bags: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Queries that can't be told apart by the index: ``class_id, nq, nk, token, tf_q`` of the smallest query of each class,
    and ``query_id, class_id``. They have equal bags of the index's tokens and equal sizes (``nk`` counts these tokens only),
    so that each class is answered once and its answer holds for all members."""
    known = bags.join(index.postings.select("token").distinct(), "token", "left_semi")
    whole = known.groupBy("query_id").agg(F.array_sort(F.collect_list(F.struct("token", "tf_q"))).alias("bag"), F.first("nq").alias("nq"), F.sum("tf_q").alias("nk"))
    same = whole.groupBy("bag", "nq", "nk").agg(F.min("query_id").alias("class_id"))
    members = whole.join(same, ["bag", "nq", "nk"]).select("query_id", "class_id")
    return same.select("class_id", "nq", "nk", F.inline("bag")), members


def lookup(index: Index, queries: DataFrame, tokeniser: str, measure: str = "pooled", query_size: str = "full") -> DataFrame:
    """``query_id, id, overlap, score`` of all addresses that share a token with a query.

    The overlap is counted along the tokens' postings and the union follows from the sizes. ``indexed`` counts only
    those tokens of a query that the index has.
    """
    asked, members = query_classes(index, query_bags(queries, tokeniser))
    size = F.first("nk" if query_size == "indexed" else "nq").alias("nq")
    counted = asked.join(index.postings, "token").groupBy("class_id", "id").agg(F.sum(F.least("tf_q", "tf")).alias("overlap"), size, F.first("n").alias("n"))
    scored = counted.select("class_id", "id", "overlap", from_counts(measure, F.col("nq"), F.col("n"), F.col("overlap")).alias("score"))
    return scored.join(members, "class_id").select("query_id", "id", "overlap", "score")


def scan_lookup(addresses: DataFrame, queries: DataFrame, tokeniser: str, measure: str = "pooled") -> DataFrame:
    """The same scores by comparing each query with every address, as matrix products of their bags; a few queries only, which
    are broadcast once counted."""
    if queries.limit(MOST_QUERIES + 1).count() > MOST_QUERIES:
        raise ValueError(f"a scan takes up to {MOST_QUERIES} queries; link the lists instead")
    bag = F.sort_array(F.coalesce(tokenise(tokeniser, F.col("address")), F.array().cast("array<string>")))
    context = addresses.sparkSession.sparkContext
    asked = context.broadcast(queries.select("id", bag.alias("x")).toArrow().combine_chunks())
    value = {
        "pooled": lambda n1, n2, i: 2 * i / (n1 + n2), "ratio": lambda n1, n2, i: i / (n1 + n2 - i),
        "containment": lambda n1, n2, i: i / n1, "overlap": lambda n1, n2, i: i / np.minimum(n1, n2),
    }[measure]

    def run(batches):
        known = asked.value
        ids, bags = (known.column(n).chunk(0) if known.num_rows else None for n in ("id", "x"))
        step = max(1, SCANNED // max(1, known.num_rows))
        for batch in batches:
            for begin in range(0, batch.num_rows if known.num_rows else 0, step):
                part = batch.slice(begin, step)
                shared, (n2, n1) = bag_overlaps(part.column(1), bags)
                at, which = np.nonzero(shared)
                score = value(n1[which], n2[at], shared[at, which].astype(np.float64))
                yield pa.RecordBatch.from_arrays([ids.take(pa.array(which)), part.column(0).take(pa.array(at)), pa.array(score)], ["query_id", "id", "score"])

    spread = addresses.select("id", "address").repartition(max(8, 2 * context.defaultParallelism))
    kinds = (dict(df.dtypes)["id"] for df in (queries, addresses))
    return spread.select("id", bag.alias("y")).mapInArrow(run, "query_id {}, id {}, score double".format(*kinds))


def lookup_two_round(index: Index, addresses: DataFrame, queries: DataFrame, tokeniser: str = "phrases", measure: str = "pooled") -> DataFrame:
    """Addresses that share a token of the index with a query, scored on characters: ``query_id, id, score``."""
    short = query_bags(queries, tokeniser).join(index.postings, "token").select(F.col("query_id").alias("id_1"), F.col("id").alias("id_2")).distinct()
    return scored_pairs(short, queries, addresses, measure).select(F.col("id_1").alias("query_id"), F.col("id_2").alias("id"), "score")


def lookup_cost(index: Index, queries: DataFrame, tokeniser: str = "phrases") -> DataFrame:
    """``query_id, postings, addresses`` that a lookup touches."""
    asked, members = query_classes(index, query_bags(queries, tokeniser))
    touched = asked.join(index.postings, "token").groupBy("class_id").agg(F.count("*").alias("postings"), F.count_distinct("id").alias("addresses")).join(members, "class_id")
    return queries.select(F.col("id").alias("query_id")).join(touched, "query_id", "left").select("query_id", F.coalesce("postings", F.lit(0)).alias("postings"), F.coalesce("addresses", F.lit(0)).alias("addresses"))
