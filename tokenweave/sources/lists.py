"""Reading and writing address lists and links."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMA = "id long, address string"


def read_addresses(spark: SparkSession, path: str, fmt: str = "parquet", id_col: str = "id", text_cols: tuple[str, ...] = ("address",), schema: str | None = None, **options) -> DataFrame:
    """``id, address`` from Parquet, ORC, CSV, JSON lines or a JDBC table; several text columns become one line."""
    reader = spark.read.format(fmt).options(**options)
    table = (reader.schema(schema) if schema else reader).load(path) if fmt != "jdbc" else reader.load()
    return as_list(table, id_col, text_cols)


def as_list(table: DataFrame, id_col: str = "id", text_cols: tuple[str, ...] = ("address",)) -> DataFrame:
    kinds = dict(table.dtypes)
    if kinds[id_col] not in ("bigint", "int", "smallint", "tinyint"):
        raise TypeError(f"{id_col} is {kinds[id_col]}; ids are integers")
    text = F.col(text_cols[0]) if len(text_cols) == 1 else F.concat_ws(" ", *text_cols)
    return table.select(F.col(id_col).cast("long").alias("id"), text.cast("string").alias("address"))


def read_checked(spark: SparkSession, path: str, fmt: str = "json", schema: str = SCHEMA, **options) -> tuple[DataFrame, DataFrame]:
    """The list, and the lines ``line`` that don't fit the schema, of files with a JSON object or CSV record a line."""
    parse = {"json": F.from_json, "csv": F.from_csv}[fmt]
    options = {"mode": "PERMISSIVE", "columnNameOfCorruptRecord": "line_", **options}
    table = spark.read.text(path).select("value", parse("value", f"{schema}, line_ string", options).alias("row")).where("trim(value) <> ''")
    bad = F.col("row").isNull() | F.col("row.line_").isNotNull()
    return as_list(table.where(~bad).select("row.*")), table.where(bad).select(F.col("value").alias("line"))


def read_lines(spark: SparkSession, path: str) -> DataFrame:
    """``id, address`` of plain text, a line each; ids are hashes of the line, so that repeated lines share one."""
    return spark.read.text(path).where("trim(value) <> ''").select(F.xxhash64("value").alias("id"), F.col("value").alias("address"))


def list_report(addresses: DataFrame) -> DataFrame:
    """One row: rows, null ids, repeated ids, null texts, texts without a word."""
    by_id = addresses.groupBy("id").agg(F.count("*").alias("n"), F.count_if(F.col("address").isNull()).alias("t"), F.count_if(F.col("address").isNotNull() & ~F.coalesce(F.col("address").rlike(r"[\p{L}\p{N}]"), F.lit(False))).alias("w"))
    return by_id.agg(F.sum("n").alias("n_rows"), F.coalesce(F.sum(F.when(F.col("id").isNull(), F.col("n"))), F.lit(0)).alias("null_ids"), F.count_if((F.col("n") > 1) & F.col("id").isNotNull()).alias("repeated_ids"), F.sum("t").alias("null_texts"), F.sum("w").alias("wordless_texts"))


def write_links(links: DataFrame, path: str, fmt: str = "parquet", partition_by: tuple[str, ...] = (), mode: str = "overwrite") -> None:
    links.write.mode(mode).partitionBy(*partition_by).format(fmt).save(path)
