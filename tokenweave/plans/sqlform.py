"""The batch linkage as one short SQL script of temporary views."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

#: One statement each; {0} and {1} are the two lists' views (id, address), {k} the cut.
STATEMENTS = (
    r"CREATE OR REPLACE TEMP VIEW tw_bags AS SELECT side, id, regexp_extract_all(lower(address), '[\\p{{L}}\\p{{N}}]+', 0) AS w FROM (SELECT 1 AS side, id, address FROM {0} UNION ALL SELECT 2, id, address FROM {1})",
    "CREATE OR REPLACE TEMP VIEW tw_tokens AS SELECT side, id, explode(array_distinct(transform(sequence(1, size(w) - 1), i -> concat_ws(' ', w[i - 1], w[i])))) AS token FROM tw_bags WHERE size(w) > 1",
    "CREATE OR REPLACE TEMP VIEW tw_rare AS SELECT token FROM (SELECT token, count_if(side = 1) AS a, count_if(side = 2) AS b FROM tw_tokens GROUP BY token) WHERE a BETWEEN 1 AND {k} AND b BETWEEN 1 AND {k}",
    "CREATE OR REPLACE TEMP VIEW tw_kept AS SELECT * FROM tw_tokens LEFT SEMI JOIN tw_rare USING (token)",
    "CREATE OR REPLACE TEMP VIEW tw_pairs AS SELECT DISTINCT l.id AS id_1, r.id AS id_2 FROM tw_kept l JOIN tw_kept r ON l.token = r.token AND l.side = 1 AND r.side = 2",
    r"CREATE OR REPLACE TEMP VIEW tw_chars AS SELECT side, id, filter(split(array_join(w, ''), ''), c -> c <> '') AS cs FROM tw_bags",
    "SELECT id_1, id_2, tw_pooled(a.cs, b.cs) AS score FROM tw_pairs JOIN tw_chars a ON a.side = 1 AND a.id = id_1 JOIN tw_chars b ON b.side = 2 AND b.id = id_2",
)


def sql_pipeline(spark: SparkSession, left: str, right: str, k: int = 100) -> DataFrame:
    """``id_1, id_2, score`` of two views; the scoring function is the SQL function of ``functions.udfs``."""
    from ..functions.udfs import register

    register(spark)
    for statement in STATEMENTS[:-1]:
        spark.sql(statement.format(left, right, k=k))
    return spark.sql(STATEMENTS[-1])
