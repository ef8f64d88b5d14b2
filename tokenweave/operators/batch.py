"""Two-round batch linkage: rare tokens propose pairs, tolerant tokens score them."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import OTHER, LinkConfig
from ..functions.bags import char_bag, char_overlap
from ..functions.similarity import MEASURES, from_counts
from ..functions.tokens import tokenise
from .blocking import candidates, self_candidates
from .index import build_index

FROM_COUNTS = ("pooled", "ratio", "containment", "overlap")


def scored_pairs(pairs: DataFrame, left: DataFrame, right: DataFrame, measure: str | Callable = "pooled", scorer: str = "chars", alphabet: str = "unicode", length_filter_tau: float | None = None) -> DataFrame:
    """``id_1, id_2, score`` of candidate pairs; bags are made once for each address, before they meet.

    ``length_filter_tau`` leaves out pairs whose sizes alone keep ``pooled`` from exceeding it.
    """
    by_vector = scorer == "chars" and measure in FROM_COUNTS
    bag = (lambda c: char_bag(c, OTHER[alphabet])) if by_vector else (lambda c: tokenise(scorer, c, alphabet) if scorer else c)
    a = left.select(F.col("id").alias("id_1"), bag(F.col("address")).alias("bag_1"))
    b = right.select(F.col("id").alias("id_2"), bag(F.col("address")).alias("bag_2"))
    both = pairs.join(a, "id_1").join(b, "id_2")
    if by_vector:
        n1, n2 = F.col("bag_1.n"), F.col("bag_2.n")
        if length_filter_tau is not None:
            both = both.where(F.least(n1, n2) > F.greatest(n1, n2) * (length_filter_tau / (2 - length_filter_tau)))
        score = from_counts(measure, n1, n2, char_overlap(F.col("bag_1"), F.col("bag_2")))
    else:
        score = (MEASURES[measure] if isinstance(measure, str) else measure)(F.col("bag_1"), F.col("bag_2"))
    return both.select("id_1", "id_2", score.alias("score"))


def link(left: DataFrame, right: DataFrame, cfg: LinkConfig = LinkConfig()) -> DataFrame:
    """``id_1, id_2, score`` of two lists ``id, address``; with ``cfg.tau``, of pairs over it only."""
    pairs = candidates(build_index(left, cfg.blocker, cfg.alphabet), build_index(right, cfg.blocker, cfg.alphabet), cfg.cuts, cfg.dedup)
    scored = scored_pairs(pairs, left, right, cfg.measure, cfg.scorer, cfg.alphabet, cfg.tau if cfg.length_filter and cfg.measure == "pooled" else None)
    return scored if cfg.tau is None else scored.where(F.col("score") > cfg.tau)


def self_link(addresses: DataFrame, cfg: LinkConfig = LinkConfig()) -> DataFrame:
    """Pairs ``id_1 < id_2`` of one list."""
    scored = scored_pairs(self_candidates(build_index(addresses, cfg.blocker, cfg.alphabet), cfg.cuts[0]), addresses, addresses, cfg.measure, cfg.scorer, cfg.alphabet)
    return scored if cfg.tau is None else scored.where(F.col("score") > cfg.tau)


def link_many(lists: dict[str, DataFrame], cfg: LinkConfig = LinkConfig()) -> DataFrame:
    """``list_1, list_2, id_1, id_2, score`` of all pairs of lists, each linked with its own frequencies."""
    names, out = sorted(lists), None
    for i, x in enumerate(names):
        for y in names[i + 1 :]:
            part = link(lists[x], lists[y], cfg).select(F.lit(x).alias("list_1"), F.lit(y).alias("list_2"), "*")
            out = part if out is None else out.union(part)
    return out


def with_fallback(left: DataFrame, right: DataFrame, cfg: LinkConfig = LinkConfig(), blocker: str = "words") -> DataFrame:
    """Links by ``cfg``, and for addresses of the left list that have none of them, links by another blocker."""
    first = link(left, right, cfg)
    rest = left.join(first.select(F.col("id_1").alias("id")).distinct(), "id", "left_anti")
    return first.union(link(rest, right, LinkConfig(k=cfg.k, tau=cfg.tau, measure=cfg.measure, blocker=blocker, scorer=cfg.scorer, alphabet=cfg.alphabet)))


def blend(a: DataFrame, b: DataFrame, weight: float = 0.5) -> DataFrame:
    """Weighted mean of two systems' scores; a pair that one of them doesn't have scores 0 there."""
    both = a.withColumnRenamed("score", "score_a").join(b.withColumnRenamed("score", "score_b"), ["id_1", "id_2"], "full")
    return both.select("id_1", "id_2", (weight * F.coalesce("score_a", F.lit(0.0)) + (1 - weight) * F.coalesce("score_b", F.lit(0.0))).alias("score"))
