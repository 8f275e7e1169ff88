"""Supports from a prefix table of baskets: the relational form of an itemset tree."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def build_tree(baskets: DataFrame, items: DataFrame | None = None) -> DataFrame:
    """(path, last, depth, cnt): every prefix of every basket, with the number of baskets that start so.

    Items are ordered by falling support where a dictionary (item, item_id) is given, else by name;
    equal prefixes are one node.
    """
    if items is not None:
        long = baskets.select("tid", F.explode("items").alias("item")).join(items.select("item", "item_id"), "item")
        ordered = long.groupBy("tid").agg(F.transform(F.array_sort(F.collect_list(F.struct("item_id", "item"))), lambda s: s["item"]).alias("items"))
    else:
        ordered = baskets.where(F.size("items") > 0)
    distinct = ordered.groupBy("items").agg(F.count("*").alias("mult"))
    paths = distinct.select("mult", F.explode(F.transform(F.sequence(F.lit(1), F.size("items")), lambda n: F.slice("items", 1, n))).alias("path"))
    return paths.groupBy("path").agg(F.sum("mult").alias("cnt")).select("path", F.element_at("path", -1).alias("last"), F.size("path").alias("depth"), "cnt")


def query(tree: DataFrame, itemsets: DataFrame, items: DataFrame | None = None) -> DataFrame:
    """(key, support) of itemsets (key, items): nodes that end in the set's last item in tree order and hold the rest above it."""
    if items is not None:
        long = itemsets.select("key", "items", F.explode("items").alias("item")).join(items.select("item", "item_id"), "item")
        ends = long.groupBy("key", "items").agg(F.max_by("item", "item_id").alias("last"))
    else:
        ends = itemsets.select("key", "items", F.array_max("items").alias("last"))
    met = tree.join(ends, "last").where(F.size(F.array_except("items", "path")) == 0)
    return met.groupBy("key").agg(F.sum("cnt").alias("support"))


def compress_tree(tree: DataFrame) -> DataFrame:
    """Nodes without those whose only child has the same count: runs of items become one edge."""
    children = tree.where("depth > 1").groupBy(F.slice("path", 1, F.size("path") - 1).alias("path")).agg(F.count("*").alias("n"), F.max("cnt").alias("most"))
    joined = tree.join(children, "path", "left")
    return joined.where(~F.coalesce((F.col("n") == 1) & (F.col("most") == F.col("cnt")), F.lit(False))).select("path", "last", "depth", "cnt")


def query_compressed(tree: DataFrame, itemsets: DataFrame) -> DataFrame:
    """(key, support) over a compressed tree: baskets that end in a node, or split there, are counted at its subtree's leaves."""
    kept = tree.select("path", "cnt", "depth")
    above = F.transform(F.sequence(F.lit(1), F.size("path") - 1), lambda n: F.slice("path", 1, n))
    below = kept.where("depth > 1").select(F.col("path").alias("p"), F.col("cnt").alias("c"), F.explode(above).alias("path"))
    nearest = below.join(kept.select("path", F.size("path").alias("d")), "path").groupBy("p", "c").agg(F.max_by("path", "d").alias("path"))
    taken = nearest.groupBy("path").agg(F.sum("c").alias("taken"))
    own = kept.join(taken, "path", "left").select("path", (F.col("cnt") - F.coalesce("taken", F.lit(0))).alias("ends")).where("ends > 0")
    wide = own.select("path", "ends", F.explode("path").alias("anchor"))
    sets = itemsets.select("key", "items", F.element_at("items", 1).alias("anchor"))
    met = wide.join(sets, "anchor").where(F.size(F.array_except("items", "path")) == 0)
    return met.groupBy("key").agg(F.sum("ends").alias("support"))
