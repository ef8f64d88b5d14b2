"""Addresses that arrive as a stream, looked up in a static index; reports over event time."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import OTHER
from ..functions.bags import char_bag, char_overlap
from ..functions.similarity import from_counts
from ..functions.tokens import tokenise
from ..operators.index import Index
from ..operators.lookup import lookup_two_round


def read_stream(spark: SparkSession, path: str, schema: str, fmt: str = "parquet", files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).format(fmt).option("maxFilesPerTrigger", files_per_trigger).load(path)


def drain(stream: DataFrame, name: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Run a stream over all that is there, into a table in memory; for tests and small reports."""
    writer = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True)
    query = (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start()
    query.awaitTermination()
    return stream.sparkSession.table(name)


def drain_to_files(stream: DataFrame, path: str, mode: str = "append", checkpoint: str | None = None) -> DataFrame:
    """Run a stream over all that is there, into Parquet files below ``path``, however much that is: nothing comes to the
    driver. In complete mode each batch replaces the one before, in update mode all batches' rows stay, as in ``drain``."""
    spark, schema, last = stream.sparkSession, stream.schema, []

    def keep(rows: DataFrame, number: int) -> None:
        rows.write.mode("overwrite").parquet(f"{path}/batch={number}")
        last[:] = [number]

    writer = stream.writeStream.foreachBatch(keep).outputMode(mode).trigger(availableNow=True)
    query = (writer.option("checkpointLocation", checkpoint) if checkpoint else writer).start()
    query.awaitTermination()
    if not last:
        return spark.createDataFrame([], schema)
    return spark.read.schema(schema).parquet(f"{path}/batch={last[0]}" if mode == "complete" else f"{path}/batch=*")


def candidates(stream: DataFrame, index: Index, tokeniser: str = "phrases") -> DataFrame:
    """``event_id, ts, id``: a stream-static join of arrivals (event_id, ts, address) with the index, once for each shared token."""
    tokens = stream.select("event_id", "ts", F.explode(F.array_distinct(tokenise(tokeniser, F.col("address")))).alias("token"))
    return tokens.join(index.postings.select("token", "id"), "token").select("event_id", "ts", "id")


def link_stream(stream: DataFrame, index: Index, addresses: DataFrame, sink: Callable[[DataFrame, int], None], checkpoint: str, tau: float = 0.7):
    """Two-round lookup of each micro-batch against one version of the index; ``sink(links, batch number)``."""

    def batch(rows: DataFrame, number: int) -> None:
        queries = rows.select(F.col("event_id").alias("id"), "address").dropDuplicates(["id"])
        sink(lookup_two_round(index, addresses, queries).where(F.col("score") > tau), number)

    return stream.writeStream.foreachBatch(batch).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def running_best(stream: DataFrame, index: Index, addresses: DataFrame, tokeniser: str = "phrases", alphabet: str = "unicode") -> DataFrame:
    """``event_id, id, score``: the best address so far of each arrival, of equal ones that with the smallest id.

    A native aggregate holds one score an arrival; drain it in complete or update mode.
    """
    known = addresses.select("id", char_bag(F.col("address"), OTHER[alphabet]).alias("bag"))
    bags = stream.select("event_id", char_bag(F.col("address"), OTHER[alphabet]).alias("asked"), F.array_distinct(tokenise(tokeniser, F.col("address"), alphabet)).alias("tokens"))
    asked = bags.select("event_id", "asked", F.explode("tokens").alias("token"))
    pairs = asked.join(index.postings.select("token", "id"), "token").join(known, "id")
    score = from_counts("pooled", F.col("asked.n"), F.col("bag.n"), char_overlap(F.col("asked"), F.col("bag")))
    best = pairs.groupBy("event_id").agg(F.max(F.struct(score.alias("score"), (-F.col("id")).alias("down"))).alias("m"))
    return best.select("event_id", (-F.col("m.down")).alias("id"), "m.score")


def late_rows(query) -> int:
    """Rows that a finished query's stateful operators left out because they came later than the watermark."""
    return sum(state.numRowsDroppedByWatermark for progress in query.recentProgress for state in progress.stateOperators)


def tumbling(rows: DataFrame, width: str = "1 hour", late: str = "1 hour") -> DataFrame:
    """Arrivals per window; on a stream rows later than the watermark are left out."""
    w = F.window("ts", width)
    return rows.withWatermark("ts", late).groupBy(w).agg(F.count("*").alias("n"), F.approx_count_distinct("site_id").alias("about_sites")).select("window.start", "window.end", "n", "about_sites")


def sliding(rows: DataFrame, width: str = "1 hour", step: str = "15 minutes", late: str = "1 hour") -> DataFrame:
    return rows.withWatermark("ts", late).groupBy(F.window("ts", width, step)).agg(F.count("*").alias("n")).select("window.start", "window.end", "n")


def sessions(rows: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Runs of one site's arrivals without a longer gap."""
    return rows.withWatermark("ts", late).groupBy("site_id", F.session_window("ts", gap).alias("s")).agg(F.count("*").alias("n")).select("site_id", "s.start", "s.end", "n")


def without_repeats(rows: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each address once within the watermark."""
    return rows.withWatermark("ts", late).dropDuplicatesWithinWatermark(["address"])


def interval_join(a: DataFrame, b: DataFrame, hours: int = 1, late: str = "2 hours") -> DataFrame:
    """Pairs of arrivals at one site within some hours of each other; both sides forget old rows."""
    x = a.withWatermark("ts", late).select(F.col("event_id").alias("event_1"), F.col("ts").alias("ts_1"), F.col("site_id").alias("site_1"))
    y = b.withWatermark("ts", late).select(F.col("event_id").alias("event_2"), F.col("ts").alias("ts_2"), F.col("site_id").alias("site_2"))
    return x.join(y, F.expr(f"site_1 = site_2 AND ts_2 BETWEEN ts_1 - INTERVAL {hours} HOURS AND ts_1 + INTERVAL {hours} HOURS AND event_1 < event_2"))


def rare_while(stream: DataFrame, k: int, tokeniser: str = "phrases") -> DataFrame:
    """``token, df, crossed``: running frequencies of tokens, one row for each token and micro-batch that has it.

    A token that crosses the cut is reported; pairs made by it before are not taken back: a batch run settles them.
    """
    tokens = stream.select(F.explode(F.array_distinct(tokenise(tokeniser, F.col("address")))).alias("token"))

    def count(key, frames: Iterator[pd.DataFrame], state):
        before = state.get[0] if state.exists else 0
        after = before + sum(len(f) for f in frames)
        state.update((after,))
        yield pd.DataFrame({"token": [key[0]], "df": [after], "crossed": [before <= k < after]})

    return tokens.groupBy("token").applyInPandasWithState(count, "token string, df long, crossed boolean", "df long", "append", "NoTimeout")
