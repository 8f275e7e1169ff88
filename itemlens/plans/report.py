"""Lists side by side, and mining results as SQL tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def side_by_side(lists: dict[str, DataFrame], k: int) -> DataFrame:
    """(rank, one column of itemsets for each name); lists have (rank, itemset)."""
    names = list(lists)
    spark: SparkSession = lists[names[0]].sparkSession
    out = spark.range(1, k + 1).select(F.col("id").cast("int").alias("rank"))
    for name in names:
        out = out.join(F.broadcast(lists[name].select("rank", F.col("itemset").alias(name))), "rank", "left")
    return out


def usage_rollup(baskets: DataFrame, itemset: list[str], by: list[str]) -> DataFrame:
    """Baskets that contain a set, rolled up over columns of the baskets."""
    own = F.array(*map(F.lit, itemset))
    return baskets.where(F.size(F.array_except(own, F.col("items"))) == 0).rollup(*by).agg(F.count("*").alias("n"))
