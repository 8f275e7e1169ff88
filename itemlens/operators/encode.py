"""Dictionary encoding by falling support, and weighted distinct baskets."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def item_support(baskets: DataFrame) -> DataFrame:
    """(item, support)"""
    return baskets.select(F.explode("items").alias("item")).groupBy("item").agg(F.count("*").alias("support"))


def fit(baskets: DataFrame) -> DataFrame:
    """(item, support, item_id): ids rise from 0 as support falls, ties by item, so prefixes of sorted baskets are shared."""
    order = Window.orderBy(F.desc("support"), "item")
    return item_support(baskets).withColumn("item_id", F.row_number().over(order) - 1)


def transform(baskets: DataFrame, items: DataFrame) -> DataFrame:
    """Baskets with ids for items.  The dictionary is joined, by broadcast only where the planner finds it small."""
    long = baskets.select("tid", F.explode_outer("items").alias("item"))
    coded = long.join(items.select("item", "item_id"), "item", "left")
    return coded.groupBy("tid").agg(F.array_sort(F.collect_set("item_id")).alias("items"))


def inverse(coded: DataFrame, items: DataFrame) -> DataFrame:
    long = coded.select("tid", F.explode_outer("items").alias("item_id")).join(items.select("item", "item_id"), "item_id", "left")
    return long.groupBy("tid").agg(F.array_sort(F.collect_set("item")).alias("items"))


def compress(baskets: DataFrame) -> DataFrame:
    """(items, mult): each distinct basket once, with its number; every later pass counts with mult."""
    return baskets.groupBy("items").agg(F.count("*").alias("mult"))
