"""Derived address lists over the star-schema and text tables, in SQL that Spark and DuckDB read alike."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def _written(kind: str) -> str:
    """The address of a site with one of eight kinds of damage."""
    full = "concat_ws(' ', 'UNIT', unit, num, {street}, st, suburb, nat, reg, {pc})"
    return f"""CASE {kind}
        WHEN 0 THEN {full.format(street="street", pc="pc")}
        WHEN 1 THEN concat_ws(' ', unit, num, street, suburb, nat, reg, pc)
        WHEN 2 THEN concat_ws(' ', concat(unit, '/', num), street, sa, suburb, nat, pc)
        WHEN 3 THEN concat_ws(', ', concat('U-', unit), concat_ws(' ', num, street, sa), suburb, reg, pc)
        WHEN 4 THEN concat_ws(' ', 'UNIT', unit, num, street, st, suburb)
        WHEN 5 THEN {full.format(street="concat(substr(street, 1, 2), substr(street, 4))", pc="pc")}
        WHEN 6 THEN {full.format(street="street", pc="concat(substr(pc, 1, 2), substr(pc, 4, 1), substr(pc, 3, 1))")}
        ELSE lower(concat_ws(', ', concat_ws(' ', num, street, sa), suburb, nat, nat, reg)) END"""


SITE = """
    SELECT c_custkey AS site_id, concat('', 1 + c_custkey % 37) AS unit, concat('', 1 + (7 * c_custkey) % 311) AS num, upper(p_name) AS street,
        CASE c_custkey % 4 WHEN 0 THEN 'STREET' WHEN 1 THEN 'ROAD' WHEN 2 THEN 'AVENUE' ELSE 'PLACE' END AS st,
        CASE c_custkey % 4 WHEN 0 THEN 'ST' WHEN 1 THEN 'RD' WHEN 2 THEN 'AVE' ELSE 'PL' END AS sa,
        c_mktsegment AS suburb, replace(n_name, '_', '') AS nat, r_name AS reg, concat('', 2000 + (131 * c_nationkey + 17 * p_size) % 7000) AS pc
    FROM customer JOIN part ON p_partkey = c_custkey JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey
"""
#: Views by name, each over the tables and the views before it.
VIEWS: dict[str, str] = {
    "site": SITE,
    "gazetteer": f"SELECT site_id AS id, {_written('0')} AS address FROM site",
    "raw_mentions": f"SELECT o_orderkey AS id, {_written('o_orderkey % 8')} AS address, o_custkey AS truth, CAST(o_orderkey % 8 AS INT) AS kind, o_orderstatus AS status FROM orders JOIN site ON site_id = o_custkey",
    "raw_a": "SELECT * FROM raw_mentions WHERE status = 'O' AND truth % 4 <> 0",
    "raw_b": "SELECT * FROM raw_mentions WHERE status = 'F' AND truth % 4 <> 1",
    "url_lines": "SELECT page_id AS id, url AS address FROM pages",
    "doc_lines": "SELECT doc_id, line_no, doc_id * 100000 + line_no AS id, address FROM ({lines}) WHERE length(address) > 20",
    "doc_full": "SELECT doc_id AS id, text AS address, lang, source FROM documents",
    "passages": "SELECT item_id AS id, text AS address FROM benchmark",
    "turns": "SELECT conv_id * 1000 + turn AS id, text AS address, role FROM conversations",
    "small_list": "SELECT s_suppkey AS id, concat_ws(' ', s_name, replace(n_name, '_', ''), r_name) AS address FROM supplier JOIN nation ON n_nationkey = s_nationkey JOIN region ON r_regionkey = n_regionkey",
    "arrivals": f"SELECT event_id, ts, user_id AS site_id, {_written('event_id % 8')} AS address, props FROM events JOIN site ON site_id = user_id",
    "big_mentions": f"""SELECT row_number() OVER (ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_discount, l_tax, l_shipdate) AS id,
        {_written('(l_orderkey + l_linenumber) % 8')} AS address, o_custkey AS truth, CAST((l_orderkey + l_linenumber) % 8 AS INT) AS kind
        FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN site ON site_id = o_custkey""",
}
LINES = {
    "spark": "SELECT doc_id, pos + 1 AS line_no, address FROM documents LATERAL VIEW posexplode(split(text, '\\\\n')) x AS pos, address",
    "duckdb": "SELECT doc_id, unnest(range(1, len(string_split(text, chr(10))) + 1)) AS line_no, unnest(string_split(text, chr(10))) AS address FROM documents",
}


def view_sql(name: str, dialect: str) -> str:
    return VIEWS[name].replace("{lines}", LINES[dialect])


def open_views(spark: SparkSession, sf_dir: str) -> None:
    """Register tables and derived lists as temporary views of the session."""
    for t in TABLES:
        spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(t)
    for name in VIEWS:
        spark.sql(view_sql(name, "spark")).createOrReplaceTempView(name)


def address_list(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One derived list; only the tables that it needs are read when it runs."""
    open_views(spark, sf_dir)
    return spark.table(name)


def with_views(sql: str) -> str:
    """DuckDB SQL with the derived lists that it names in front, as common table expressions."""
    import re

    found, todo = [], [sql]
    while todo:
        text = todo.pop()
        for name in VIEWS:
            if re.search(rf"\b{name}\b", text) and name not in found:
                found.append(name)
                todo.append(view_sql(name, "duckdb"))
    parts = [f"{n} AS ({view_sql(n, 'duckdb')})" for n in VIEWS if n in found]
    body = sql.strip()
    if parts and body.upper().startswith("WITH RECURSIVE"):
        return "WITH RECURSIVE " + ", ".join(parts) + ", " + body[14:]
    if parts and body.upper().startswith("WITH "):
        return "WITH " + ", ".join(parts) + ", " + body[5:]
    return ("WITH " + ", ".join(parts) + " " if parts else "") + body
