"""Ranking mined itemsets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.expressions import chi2_score


def interestingness(catalog: DataFrame) -> DataFrame:
    """catalog (key, items, size, usage, support, pi) with usage / support; 0 where there is no support."""
    return catalog.withColumn("interestingness", F.when(F.col("support") > 0, F.col("usage") / F.col("support")).otherwise(0.0))


def top_k(catalog: DataFrame, k: int, by: str = "interestingness", singletons: bool = False) -> DataFrame:
    """(rank, itemset, usage, support, interestingness, pi); ties by pi, then by key."""
    rows = interestingness(catalog)
    if not singletons:
        rows = rows.where("size > 1")
    order = [F.desc(by), *([F.desc("pi")] if by != "pi" else [F.desc("interestingness")]), F.asc("key")]
    best = rows.orderBy(*order).limit(k)
    return best.select(
        F.row_number().over(Window.orderBy(*order)).alias("rank"), F.col("key").alias("itemset"), "usage", "support", "interestingness", "pi"
    )


def chi2(itemsets: DataFrame, items: DataFrame, m: int) -> DataFrame:
    """itemsets (key, items, support) with `expected` support under independence and `chi2`.

    items: (item, support).
    """
    long = itemsets.select("key", F.explode("items").alias("item")).join(items.select("item", F.col("support").alias("n")), "item")
    expected = long.groupBy("key").agg((F.lit(float(m)) * F.exp(F.sum(F.log(F.col("n") / F.lit(float(m)))))).alias("expected"))
    return itemsets.join(expected, "key").withColumn("chi2", chi2_score(F.col("support"), F.col("expected"), F.lit(float(m))))


def chi2_pair(n_ab, n_a, n_b, m):
    """The full two-by-two test of a pair, as a column expression of its counts."""
    cells = ((n_ab, n_a * n_b / m), (n_a - n_ab, n_a * (m - n_b) / m), (n_b - n_ab, (m - n_a) * n_b / m), (m - n_a - n_b + n_ab, (m - n_a) * (m - n_b) / m))
    total = F.lit(0.0)
    for observed, expected in cells:
        total = total + F.when(expected > 0, (observed - expected) * (observed - expected) / expected).otherwise(0.0)
    return total
