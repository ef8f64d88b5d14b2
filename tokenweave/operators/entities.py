"""Groups of addresses that links hold together."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def entities(links: DataFrame, checkpoint_every: int = 3, max_iter: int = 100) -> DataFrame:
    """``id, entity``: the smallest id that a chain of links (``id_1, id_2`` of one list) reaches.

    Labels take the smallest among neighbours and then jump to their label's label, so that the number of rounds
    is about the logarithm of the longest chain. Every few rounds a checkpoint cuts the plan; where the session has
    no checkpoint folder, the plan stays whole.
    """
    can = links.sparkSession.conf.get("spark.checkpoint.dir", None) or links.sparkSession.sparkContext.getCheckpointDir()
    cut = lambda df: df.checkpoint() if can else df.cache()
    edges = cut(links.select("id_1", "id_2").union(links.select("id_2", "id_1")).where("id_1 <> id_2").distinct().toDF("a", "b"))
    state = edges.select(F.col("a").alias("id")).distinct().withColumn("entity", F.col("id"))
    for k in range(max_iter):
        near = edges.join(state, edges.b == state.id).groupBy(F.col("a").alias("id")).agg(F.min("entity").alias("near"))
        lower = state.join(near, "id").select("id", F.least("entity", "near").alias("entity"))
        jump = lower.join(lower.select(F.col("id").alias("entity"), F.col("entity").alias("up")), "entity", "left").select("id", F.least("entity", "up").alias("entity"))
        new = cut(jump) if k % checkpoint_every == 0 or not can else jump.cache()
        if new.join(state.withColumnRenamed("entity", "old"), "id").where("entity <> old").isEmpty():
            return new
        state = new
    raise RuntimeError("entities did not settle")
