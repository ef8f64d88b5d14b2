"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line.

W6 stages: both linkages end to end, the big mention list, and their stages alone. On the smaller tables of
$BENCH_SWEEP_DIR, W7: the reference linkage with one, two, ... cores in sessions of their own; W8: candidates and
seconds as the lists grow alike.
"""

from __future__ import annotations

import json
import os

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

SF = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
#: Tables of the sweeps over shares of common addresses and over cores (they run the linkage several times); empty: no sweeps.
SWEEP_DIR = os.environ.get("BENCH_SWEEP_DIR", "/root/testdata/sf0.01")
CPUS = int(os.environ.get("BENCH_CPUS", os.cpu_count() or 4))


def session(cores: int) -> SparkSession:
    return (
        SparkSession.builder.master(f"local[{cores}]").appName("tokenweave-bench").config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "8g"))
        .config("spark.sql.shuffle.partitions", str(2 * CPUS)).config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    )


def main() -> None:
    from tokenweave.config import LinkConfig
    from tokenweave.operators import batch, blocking, select
    from tokenweave.operators.evaluate import timed
    from tokenweave.operators.index import build_index
    from tokenweave.sources.fixtures import address_list

    spark = session(CPUS)
    spark.sparkContext.setLogLevel("ERROR")
    raw, gaz = address_list(spark, SF, "raw_mentions"), spark.table("gazetteer")
    raw_a, raw_b, big = spark.table("raw_a"), spark.table("raw_b"), spark.table("big_mentions")
    timed(lambda: batch.link(raw, gaz))  # compiles the code
    parts = {
        "link_reference": lambda: select.accept(select.best_match(batch.link(raw, gaz)), 0.7),
        "link_arbitrary": lambda: select.first_consistent(select.top_n(batch.link(raw_b, raw_a)), raw_b, raw_a),
        "link_big_mentions": lambda: batch.link(big, gaz),
        "index_raw": lambda: build_index(raw).frequencies(),
        "candidates": lambda: blocking.candidates(build_index(raw), build_index(gaz)),
        "candidates_owner": lambda: blocking.candidates(build_index(raw), build_index(gaz), dedup="owner"),
        "link_tau_07": lambda: batch.link(raw, gaz, LinkConfig(tau=0.7, length_filter=True)),
        "self_link_urls": lambda: batch.self_link(spark.table("url_lines"), LinkConfig(k=100)),
    }
    seconds = {name: round(timed(make), 3) for name, make in parts.items()}
    rows = {n: spark.table(n).count() for n in ("raw_mentions", "gazetteer", "raw_a", "raw_b", "big_mentions")}
    pairs = blocking.candidates(build_index(raw), build_index(gaz)).count()
    rate = lambda q, *lists: round(sum(rows[x] for x in lists) / seconds[q] / CPUS)
    overlap = {}
    if SWEEP_DIR:
        raw, gaz = address_list(spark, SWEEP_DIR, "raw_mentions"), spark.table("gazetteer")
        timed(lambda: batch.link(raw, gaz))
    for x in (0, 25, 50, 75, 100) if SWEEP_DIR else ():
        same = (F.col("id") * 7919) % 100 < x
        part = gaz.select("id", F.when(same, F.col("address")).otherwise(F.regexp_replace("address", "([A-Z0-9]+)", "$1X")).alias("address"))
        overlap[str(x)] = {"seconds": round(timed(lambda p=part: batch.link(raw, p)), 2), "candidates": batch.link(raw, part).count()}
    out = {
        "metric": "linkage, all headline queries", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": SF.rsplit("sf", 1)[-1], "cpus": CPUS, "rows": rows, "candidates": pairs,
        "rows_per_second_and_core": {"link_reference": rate("link_reference", "raw_mentions", "gazetteer"), "link_arbitrary": rate("link_arbitrary", "raw_b", "raw_a"), "link_big_mentions": rate("link_big_mentions", "big_mentions", "gazetteer")}, "overlap": overlap,
    }
    spark.stop()
    if SWEEP_DIR:
        scaling = {}
        for cores in sorted({1, 2, 4, CPUS}):
            spark = session(cores)
            spark.sparkContext.setLogLevel("ERROR")
            raw, gaz = address_list(spark, SWEEP_DIR, "raw_mentions"), spark.table("gazetteer")
            timed(lambda: batch.link(raw, gaz))
            scaling[str(cores)] = round(timed(lambda: batch.link(raw, gaz)), 2)
            spark.stop()
        out["seconds_by_cores"] = scaling
    print(json.dumps(out))


if __name__ == "__main__":
    main()
