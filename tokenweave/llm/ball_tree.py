"""Exact search for the largest inner products by branch and bound over ball trees.

Vectors are dealt to shards; a task builds the shard's ball tree and answers a block of queries. Nodes are visited
in order of their bound on the inner product (centre's product plus radius times the query's length) and left out
once the bound falls below the query's current k-th score. That score is shared: a first shard answers all queries,
and its k-th scores are the floor from which all other shards begin.
"""

from __future__ import annotations

import heapq

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import Scratch

LEAF = 256


class BallTree:
    """Nodes over a shard's rows, which are reordered so that each node owns a run of them; leaves have up to LEAF rows."""

    def __init__(self, points: np.ndarray):
        self.order = np.arange(len(points))
        self.nodes: list[tuple[int, int, np.ndarray, float, int, int]] = []  # begin, end, centre, radius, left, right
        self.points = points
        if len(points):
            self._grow(0, len(points))
        self.points = points[self.order]

    def _grow(self, a: int, b: int) -> int:
        rows = self.points[self.order[a:b]]
        centre = rows.mean(0)
        radius = float(np.sqrt(((rows - centre) ** 2).sum(1).max()))
        k = len(self.nodes)
        self.nodes.append((a, b, centre, radius, -1, -1))
        if b - a > LEAF and radius > 0:
            far = rows[((rows - centre) ** 2).sum(1).argmax()]
            other = rows[((rows - far) ** 2).sum(1).argmax()]
            middle = (b - a) // 2
            self.order[a:b] = self.order[a:b][np.argpartition(rows @ (other - far), middle)]
            left = self._grow(a, a + middle)
            right = self._grow(a + middle, b)
            self.nodes[k] = (a, b, centre, radius, left, right)
        return k

    def search(self, query: np.ndarray, ids: np.ndarray, own: int, k: int, floor: float) -> list[tuple[int, int]]:
        """The best ``(score, id)`` of rows other than ``own``: at most k, none below the floor; ties to smaller ids."""
        size, best = float(np.sqrt(query @ query)), []  # a heap of (score, -id)
        bound = lambda n: float(query @ self.nodes[n][2]) + self.nodes[n][3] * size
        queue = [(-bound(0), 0)] if self.nodes else []
        while queue:
            top, n = heapq.heappop(queue)
            slack = 1e-9 * (1 + abs(top)) + 1e-6
            if -top + slack < floor:
                break
            a, b, _, _, left, right = self.nodes[n]
            if left >= 0:
                for m in (left, right):
                    if (x := bound(m)) + slack >= floor:
                        heapq.heappush(queue, (-x, m))
                continue
            scores = self.points[a:b] @ query
            for p in np.flatnonzero(scores >= floor).tolist():
                if (i := int(ids[self.order[a + p]])) != own:
                    entry = (int(scores[p]), -i)
                    if len(best) < k:
                        heapq.heappush(best, entry)
                    elif entry > best[0]:
                        heapq.heapreplace(best, entry)
                    if len(best) == k:
                        floor = max(floor, best[0][0])
        return [(s, -i) for s, i in best]


def _stack(vectors) -> np.ndarray:
    """Integer components as doubles, in which all products and sums up to 2**53 are exact."""
    return np.array([np.asarray(v) for v in vectors], np.float64).reshape(len(vectors), -1)


def top_products(vectors: DataFrame, k: int = 5, every: int = 50, scale: int = 256, id_col: str = "vec_id", vector_col: str = "embedding", shard_rows: int = 8192, block_rows: int = 2048, scratch: Scratch | None = None) -> DataFrame:
    """``query_id, rank, vec_id, score``: for each query its k largest inner products with other rows.

    Components become floor(scale * x) of doubles; the product is an integer, exact while the sum of absolute
    products stays under 2**53. Queries are the rows whose id is divisible by ``every``. Vectors that are null, empty
    or hold null or non-finite components take no part, nor do null ids; vectors of different lengths don't meet.
    Ties go to the smaller id. Rows that repeat an id are candidates one by one, and a query's own id is none.

    The number of rows decides the number of shards and blocks, so that a task holds one shard and one block at most.
    """
    spark = vectors.sparkSession
    scratch = scratch or Scratch(spark)
    x = F.col(vector_col)
    good = x.isNotNull() & (F.size(x) > 0) & ~F.exists(x, lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == F.lit(float("inf"))))
    rows = vectors.where(F.col(id_col).isNotNull() & good).select(F.col(id_col).cast("long").alias("vec_id"), F.transform(x, lambda v: F.floor(v.cast("double") * scale)).alias("v"))
    rows = scratch.save(rows.withColumn("dim", F.size("v")), "vectors")
    n = max(1, rows.count())
    shards, blocks = -(-n // shard_rows), max(1, -(-n // (every * block_rows)))
    candidates = rows.select("dim", F.pmod(F.xxhash64("vec_id"), F.lit(shards)).alias("shard"), F.col("vec_id").alias("id"), "v")
    queries = rows.where(F.pmod("vec_id", F.lit(every)) == 0).dropDuplicates(["vec_id", "v"]).select("dim", F.pmod(F.xxhash64("vec_id", F.lit(1)), F.lit(blocks)).alias("block"), F.col("vec_id").alias("id"), "v")
    schema = "query_id long, vec_id long, score long"

    def answer(left: pd.DataFrame, right: pd.DataFrame) -> pd.DataFrame:
        out = ([], [], [])
        if len(left) and len(right):
            tree, ids = BallTree(_stack(left["v"])), left["id"].to_numpy()
            for query, own, floor in zip(_stack(right["q_v"]), right["q_id"].tolist(), right["floor"].tolist()):
                for s, i in tree.search(query, ids, own, k, floor):
                    out[0].append(own)
                    out[1].append(i)
                    out[2].append(s)
        return pd.DataFrame({"query_id": np.array(out[0], np.int64), "vec_id": np.array(out[1], np.int64), "score": np.array(out[2], np.int64)})

    def search(some: DataFrame, asked: DataFrame, numbers: list[int]) -> DataFrame:
        left = some.withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)).cast("array<long>")))
        right = asked.withColumn("shard", F.explode(F.lit(numbers).cast("array<long>")))
        keys = ["dim", "shard", "block"]
        right = right.select(*[F.col(c).alias(f"q_{c}") for c in keys], F.col("id").alias("q_id"), F.col("v").alias("q_v"), F.col("floor"))
        return left.groupBy(*keys).cogroup(right.groupBy(*[f"q_{c}" for c in keys])).applyInPandas(lambda a, b: answer(a, b), schema)

    start = F.lit(float("-inf"))
    first = scratch.save(search(candidates.where("shard = 0"), queries.withColumn("floor", start), [0]), "first")
    found = first
    if shards > 1:
        place = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
        floors = first.withColumn("r", F.row_number().over(place)).where(f"r = {k}").select(F.col("query_id").alias("id"), F.col("score").cast("double").alias("floor"))
        asked = queries.join(floors, "id", "left").withColumn("floor", F.coalesce("floor", start)).select("dim", "block", "id", "v", "floor")
        found = first.union(search(candidates.where("shard > 0"), asked, list(range(1, shards))))
    place = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(place)).where(f"rank <= {k}").select("query_id", "rank", "vec_id", "score")
