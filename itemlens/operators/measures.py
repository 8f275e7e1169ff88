"""Measures of accuracy, redundancy, cost and use over time."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.expressions import contains, sym_diff_size


def avg_loglik(covered: DataFrame, catalog, weight: str | None = None) -> float:
    """Mean log-likelihood by a direct sum over covers; model.profit has the closed form."""
    from .model import log_joint

    return log_joint(covered, catalog).agg(F.avg("logp")).first()[0]


def n_nonsingleton(catalog: DataFrame) -> DataFrame:
    return catalog.agg(F.sum((F.col("size") > 1).cast("long")).alias("n"))


def curve(mined: DataFrame, truth: DataFrame) -> DataFrame:
    """(k, precision, recall) of the top k sets, for each k; mined: (rank, itemset), truth: (itemset)."""
    known = truth.select("itemset").distinct().withColumn("hit", F.lit(1))
    total = known.agg(F.count("*").alias("total"))
    running = Window.orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)
    hits = mined.join(known, "itemset", "left").withColumn("hits", F.sum(F.coalesce("hit", F.lit(0))).over(running)).withColumn("k", F.row_number().over(Window.orderBy("rank")))
    return hits.crossJoin(F.broadcast(total)).select("k", (F.col("hits") / F.col("k")).alias("precision"), (F.col("hits") / F.col("total")).alias("recall"))


def precision_at_k(mined: DataFrame, truth: DataFrame) -> DataFrame:
    return curve(mined, truth).select("k", "precision")


def recall_at_k(mined: DataFrame, truth: DataFrame) -> DataFrame:
    return curve(mined, truth).select("k", "recall")


def eleven_point(pr: DataFrame) -> DataFrame:
    """At recall 0, 0.1, ... 1: the best precision at that recall or beyond, 0 if none is."""
    levels = pr.sparkSession.range(11).select((F.col("id") / 10).alias("level"))
    met = levels.join(F.broadcast(pr), F.col("recall") >= F.col("level") - 1e-12, "left")
    return met.groupBy("level").agg(F.coalesce(F.max("precision"), F.lit(0.0)).alias("precision")).select(F.col("level").alias("recall"), "precision")


def nearest_distances(itemsets: DataFrame) -> DataFrame:
    """(itemset, distance) to the nearest other listed set, by size of the symmetric difference; lists are short."""
    a = itemsets.select("itemset", "items")
    b = itemsets.select(F.col("itemset").alias("other"), F.col("items").alias("other_items"))
    pairs = a.crossJoin(F.broadcast(b)).where("itemset <> other")
    return pairs.groupBy("itemset").agg(F.min(sym_diff_size(F.col("items"), F.col("other_items"))).alias("distance"))


def iid(itemsets: DataFrame) -> DataFrame:
    """(iid, n): mean distance to the nearest other listed set; null for fewer than two sets."""
    return nearest_distances(itemsets).agg(F.avg("distance").alias("iid"), F.count("*").alias("n"))


def shortfall(listed: DataFrame, k: int) -> DataFrame:
    return listed.agg(F.count("*").alias("n_listed"), (F.count("*") < k).alias("short"))


def mentions(baskets: DataFrame, itemsets: DataFrame, unit: str = "day", fill: bool = True) -> DataFrame:
    """(day, itemset, n): baskets (tid, items, ts) that contain each set (itemset, items), by day; empty days count 0."""
    anchored = itemsets.select("itemset", F.col("items").alias("set"), F.element_at("items", 1).alias("anchor"))
    wide = baskets.select("items", F.to_date(F.date_trunc(unit, "ts")).alias("day"), F.explode("items").alias("anchor"))
    counts = wide.join(F.broadcast(anchored), "anchor").where(contains(F.col("items"), F.col("set"))).groupBy("day", "itemset").agg(F.count("*").alias("n"))
    if not fill:
        return counts
    days = baskets.agg(F.min(F.to_date("ts")).alias("lo"), F.max(F.to_date("ts")).alias("hi"))
    every = {"day": "1 day", "week": "7 days", "month": "1 month"}[unit]
    calendar = days.select(F.explode(F.expr(f"sequence(cast(date_trunc('{unit}', lo) as date), hi, interval {every})")).alias("day"))
    grid = calendar.crossJoin(F.broadcast(itemsets.select("itemset")))
    return grid.join(counts, ["day", "itemset"], "left").select("day", "itemset", F.coalesce("n", F.lit(0)).alias("n"))


def spikes(daily: DataFrame, z: float = 3.0) -> DataFrame:
    """Days on which a set is mentioned more than z standard deviations above its mean (the rule is ours)."""
    w = Window.partitionBy("itemset")
    scored = daily.withColumn("mean", F.avg("n").over(w)).withColumn("sd", F.stddev_pop("n").over(w))
    return scored.where((F.col("sd") > 0) & (F.col("n") > F.col("mean") + z * F.col("sd"))).select("day", "itemset", "n", ((F.col("n") - F.col("mean")) / F.col("sd")).alias("z"))


def shared_spikes(found: DataFrame) -> DataFrame:
    return found.groupBy("day").agg(F.count("*").alias("sets"), F.array_sort(F.collect_set("itemset")).alias("itemsets")).where("sets > 1")


def moving_mentions(daily: DataFrame, days: int = 7) -> DataFrame:
    return daily.withColumn("moving", F.avg("n").over(Window.partitionBy("itemset").orderBy("day").rowsBetween(-(days - 1), 0)))


def series_corr(daily: DataFrame) -> DataFrame:
    """(a, b, corr) of the daily counts of each pair of sets."""
    x, y = daily.select("day", F.col("itemset").alias("a"), F.col("n").alias("x")), daily.select("day", F.col("itemset").alias("b"), F.col("n").alias("y"))
    return x.join(y, "day").where("a < b").groupBy("a", "b").agg(F.corr("x", "y").alias("corr"))


def rank_of(listed: DataFrame, itemsets: list[str]) -> DataFrame:
    """(itemset, rank), rank null where a set is not listed."""
    spark = listed.sparkSession
    wanted = spark.createDataFrame([(i,) for i in itemsets], "itemset string")
    return wanted.join(listed.select("itemset", "rank"), "itemset", "left")


def cover_ratio(greedy: DataFrame, exact: DataFrame) -> DataFrame:
    """(worst, bound_kept): greedy over exact weight of each basket, against ln of its size plus 1."""
    both = greedy.select("tid", F.size("items").alias("n"), F.col("cost").alias("g")).join(exact.select("tid", F.col("cost").alias("e")), "tid")
    ratio = F.when(F.col("e") > 0, F.col("g") / F.col("e")).otherwise(1.0)
    return both.agg(F.max(ratio).alias("worst"), F.min((ratio <= F.log(F.col("n")) + 1 + 1e-9).cast("int")).cast("boolean").alias("bound_kept"))


def throughput(baskets: int, seconds: float, cores: int) -> float:
    """Baskets per second and core."""
    return baskets / seconds / cores if seconds > 0 else math.inf
