"""Tables and transaction files."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_transactions(spark: SparkSession, path: str, kind: str = "text", key: str = "tid", item: str = "item") -> DataFrame:
    """Baskets (tid, items) from a file: `text` has one basket a line, items between spaces; csv, json, orc and parquet have rows (key, item) or (key, items)."""
    if kind == "text":
        lines = spark.read.text(path).withColumn("tid", F.monotonically_increasing_id())
        items = F.array_sort(F.array_distinct(F.filter(F.split("value", r"\s+"), lambda x: x != "")))
        return lines.select("tid", items.alias("items"))
    rows = spark.read.format(kind).options(**({"header": "true"} if kind == "csv" else {})).load(path)
    if "items" in rows.columns:
        return rows.select(F.col(key).alias("tid"), F.array_sort(F.array_distinct(F.array_compact("items"))).alias("items"))
    from .baskets import from_rows

    return from_rows(rows, F.col(key), F.col(item))


def write(df: DataFrame, path: str, mode: str = "overwrite", by: list[str] | None = None) -> None:
    """A catalog, cover, trace or report as Parquet, one folder for each value of `by`."""
    (df.write.mode(mode).partitionBy(*by) if by else df.write.mode(mode)).parquet(path)
