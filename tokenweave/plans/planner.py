"""Choices that the optimiser can't make: how to de-duplicate, what to broadcast, which cut."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import LinkConfig
from ..operators.blocking import shared_rare
from ..operators.evaluate import coverage
from ..operators.index import Index, build_index


def bounded(df: DataFrame, rows: int = 1_000_000) -> DataFrame:
    """The table with a broadcast hint if it has no more than ``rows`` rows, else as it is. Counts it."""
    return F.broadcast(df) if df.limit(rows + 1).count() <= rows else df


def repeats(left: Index, right: Index, k: tuple[int | None, int | None]) -> float:
    """Mean number of shared rare tokens of a candidate pair, bounded from above by counts alone."""
    row = shared_rare(left, right, k).agg(F.sum(F.col("df_1") * F.col("df_2")).alias("rows"), F.count("*").alias("tokens")).first()
    return float(row["rows"] or 0) / max(1, row["tokens"] or 1)


def auto_k(left: DataFrame, right: DataFrame, cfg: LinkConfig = LinkConfig(), grid: tuple[int, ...] = (20, 50, 100, 200, 500), want: float = 0.995) -> int:
    """The smallest cut of a grid that leaves a rare shared token to a share of the left addresses, else the largest."""
    a, b = build_index(left, cfg.blocker, cfg.alphabet), build_index(right, cfg.blocker, cfg.alphabet)
    for k in grid:
        row = coverage(a, b, left, (k, k)).first()
        if row["n"] and row["covered"] / row["n"] >= want:
            return k
    return grid[-1]


def drop_list(addresses: DataFrame, k: int, tokeniser: str = "phrases", one_in: int = 16, most: int = 100_000) -> DataFrame | None:
    """Tokens that are certain to be over the cut: those in more than k addresses of a hash sample alone.

    Taking them out before the shuffle changes no result; None where there are too many to broadcast.
    """
    sample = addresses.where(F.pmod(F.xxhash64("id"), F.lit(one_in)) == 0)
    sure = build_index(sample, tokeniser).frequencies().where(F.col("df") > k).select("token")
    return F.broadcast(sure) if sure.limit(most + 1).count() <= most else None
