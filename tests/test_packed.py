"""links of long texts in packed blocks against the definition."""

import random
from collections import Counter, defaultdict
from itertools import combinations

import pyarrow as pa
import pytest

from tokenweave.config import LinkConfig
from tokenweave.operators import packed
from tokenweave.operators.batch import self_link
from tokenweave.plans.workloads import QUERIES
from tests.conftest import SMALL


def by_definition(rows, k):
    """Rows of one id are one text; rows without an id count once for the cut."""
    held, bags = defaultdict(set), defaultdict(Counter)
    for i, t in rows:
        words = "".join(c if c.isalnum() else " " for c in (t or "").lower()).split()
        for p in zip(words, words[1:]):
            held[p].add(i)
        bags[i].update("".join(words))
    pairs = {p for ids in held.values() if len(ids) <= k for p in combinations(sorted(i for i in ids if i is not None), 2)}
    return {(a, b): 2 * (bags[a] & bags[b]).total() / (bags[a].total() + bags[b].total()) for a, b in pairs}


def made():
    rng = random.Random(11)
    words = ["a", "b", "Ä", "éa", "x9", "日本", "語", "\U0001d54f", "ß", "d", "e", "common"]
    rows = [(k * 7 - 300, " ".join(rng.choice(words) for _ in range(rng.randint(0, 9))) + rng.choice(["", ".", " -- ", "\n"])) for k in range(160)]
    rows += [(5000 + k, "one group of exact copies, larger than the cut") for k in range(9)] + [(6000 + k, f"only three of Them\tshare {k}") for k in range(3)]
    return rows + [(8000, None), (8001, ""), (8002, "?!"), (8003, "word"), (2**62, "far off id"), (-(2**62), "far off id")]


@pytest.fixture(params=[(1 << 23, 6400, 1 << 18, 128), (200, 9, 7, 3), (60, 40, 50, 0)])
def sizes(request, monkeypatch):
    for name, value in zip(("SLICE", "BLOCK", "PAIRS", "WIDE"), request.param):
        monkeypatch.setattr(packed, name, value)


@pytest.mark.parametrize("k", [2, 6])
def test_packed_links_are_those_of_the_rows(spark, sizes, k):
    df = spark.createDataFrame(made(), "id long, address string").repartition(3)
    got = packed.self_link_packed(df, k).collect()
    want = {(r.id_1, r.id_2): r.score for r in self_link(df, LinkConfig(k=k)).collect()}
    assert len(got) == len(want) and {(r.id_1, r.id_2): r.score for r in got} == want == by_definition(made(), k)


def test_rows_of_one_id_and_rows_without_one(spark, sizes):
    """As the SQL: a text of several rows counts once, and all rows without an id count as one text that has no link."""
    rows = made() + [(6000, "Three of them é日 again"), (6000, "only three of Them"), (None, "three of"), (None, "three of"), (None, "far off"), (None, "d e d e")]
    df = spark.createDataFrame(rows, "id long, address string").repartition(4)
    for k in (2, 3, 4):
        got = packed.self_link_packed(df, k, 0.4).collect()
        want = {p: s for p, s in by_definition(rows, k).items() if s > 0.4}
        assert len(got) == len(want) and {(r.id_1, r.id_2): r.score for r in got} == want


def test_no_texts(spark):
    for rows in ([], [(1, None), (2, "")], [(1, "single"), (2, "words")], [(None, "a b"), (1, "a b")]):
        assert packed.self_link_packed(spark.createDataFrame(rows, "id long, address string"), 5).collect() == []


def test_documents_move_packed(spark):
    """No shuffle holds a row for each phrase or pair, and what a phrase of a text takes there is under 13 bytes."""
    plan = QUERIES["link_documents"](spark, SMALL)._jdf.queryExecution().executedPlan().toString()
    assert "bag_1" not in plan and "token" not in plan and "hashpartitioning(bucket" in plan
    rng = random.Random(2)
    texts = [" ".join(["of the"] + [rng.choice("bcdfgh") + str(rng.randint(0, 3000)) for _ in range(300)]) for _ in range(200)]
    rows = list(packed._posted(pa.table({"id": pa.array(range(200)), "text": texts}), 10, 8))
    n = sum(r["n"] for r in rows if r["kind"] == packed.POSTED)
    assert 59_000 < n < 60_300 and [r["n"] for r in rows if r["kind"] == packed.OVER] == [1]
    assert sum(len(r["ids"]) + len(r["hashes"]) for r in rows) < 13 * n
