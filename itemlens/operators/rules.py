"""Association rules that the mined itemsets imply, and the tiles that their covers form."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.expressions import itemset_key, proper_subsets
from .catalog import count_support

#: Sets of up to this many items give all their 2^n - 2 rules; larger ones those with one item on either side.
LARGEST_SET = 12


def from_catalog(itemsets: DataFrame, baskets: DataFrame, min_conf: float = 0.0) -> DataFrame:
    """(antecedent, consequent, support, confidence, lift) of itemsets (key, items, support)."""
    n = F.size("items")
    ones = F.transform("items", lambda i: F.array(i))
    both = F.concat(ones, F.transform(ones, lambda one: F.array_except("items", one)))
    sides = itemsets.where(n > 1).select("key", "items", "support", F.explode(F.when(n <= LARGEST_SET, proper_subsets(F.col("items"))).otherwise(both)).alias("left"))
    sides = sides.select("key", "support", itemset_key(F.col("left")).alias("antecedent"), itemset_key(F.array_except("items", "left")).alias("consequent"), "left")
    distinct = sides.select(F.col("antecedent").alias("key"), F.col("left").alias("items"), F.element_at("left", 1).alias("anchor")).distinct()
    supports = count_support(baskets, distinct)
    m = baskets.agg(F.count("*").alias("m"))
    a = supports.select(F.col("key").alias("antecedent"), F.col("support").alias("sa"))
    c = supports.select(F.col("key").alias("consequent"), F.col("support").alias("sc"))
    rules = sides.join(a, "antecedent").join(c, "consequent").crossJoin(F.broadcast(m))
    conf = F.col("support") / F.col("sa")
    return rules.select("antecedent", "consequent", "support", conf.alias("confidence"), (conf * F.col("m") / F.col("sc")).alias("lift")).where(F.col("confidence") >= min_conf)


def tiles(covered: DataFrame, members: bool = False) -> DataFrame:
    """(key, rows[, tids]): the baskets that each set covers.  The lists of baskets are only for results that fit a row."""
    long = covered.select("tid", F.explode("cover").alias("key"))
    aggs = [F.count("*").alias("rows")] + ([F.array_sort(F.collect_set("tid")).alias("tids")] if members else [])
    return long.groupBy("key").agg(*aggs)
