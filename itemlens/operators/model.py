"""The generative model: joint probability, cost, profit and sampling."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.expressions import portable_uniform
from .catalog import Catalog, to_df


def entropy(p: float) -> float:
    return 0.0 if p <= 0 or p >= 1 else -p * math.log(p) - (1 - p) * math.log1p(-p)


def profit(usages: dict[str, int], m: int, prior: str = "none", items: int = 0) -> float:
    """Mean log-likelihood per basket when each probability is its usage over m: minus the sum of binary entropies.

    prior="size" also charges each set of several items ln(items) for each of them, once for the database.
    """
    total = -sum(entropy(u / m) for u in usages.values()) if m else 0.0
    if prior == "size" and m:
        total -= sum(k.count("|") + 1 for k, u in usages.items() if u and "|" in k) * math.log(max(2, items)) / m
    return total


def unused_cost(catalog: Catalog) -> float:
    """What a basket pays for all sets if it uses none."""
    return -sum(math.log1p(-s.pi) for s in catalog.values() if 0 < s.pi < 1)


def cover_cost(covered: DataFrame, catalog: Catalog) -> DataFrame:
    """covered (…, items, cover) with `full_cost`: used and unused terms, infinite where the union is not the basket.

    The unused terms of all sets are one constant; each used set replaces its own.
    """
    sets = to_df(covered.sparkSession, catalog).select("key", F.col("items").alias("set"), "pi")
    gain = -F.log("pi") + F.when(F.col("pi") < 1, F.log1p(-F.col("pi"))).otherwise(0.0)
    long = covered.select("tid", "items", F.explode_outer("cover").alias("key")).join(sets.select("key", "set", gain.alias("g")), "key", "left")
    per = long.groupBy("tid", "items").agg(F.coalesce(F.sum("g"), F.lit(0.0)).alias("g"), F.array_distinct(F.flatten(F.collect_list("set"))).alias("union"))
    right = (F.size(F.array_except("items", "union")) == 0) & (F.size(F.array_except("union", "items")) == 0)
    return per.select("tid", F.when(right, F.col("g") + unused_cost(catalog)).otherwise(F.lit(math.inf)).alias("full_cost"))


def log_joint(covered: DataFrame, catalog: Catalog) -> DataFrame:
    """(tid, logp) of basket and cover together."""
    return cover_cost(covered, catalog).select("tid", (-F.col("full_cost")).alias("logp"))


def generate(spark: SparkSession, catalog: Catalog, n: int = 0, seed: int = 42, sampler: str = "md5", tids: DataFrame | None = None) -> DataFrame:
    """n baskets (tid, items) from the model, or one for each row of `tids` (tid): each set is drawn by itself, a basket is the union of those drawn.

    The catalog travels as one row and each basket is drawn within its own; nothing is shuffled.  The
    md5 sampler gives the same baskets in any engine; `xxhash` is faster.
    """
    sets = to_df(spark, catalog).select(F.struct("key", F.col("items").alias("set"), "pi").alias("s"))
    packed = sets.agg(F.collect_list("s").alias("_sets"))
    named = spark.range(n).select(F.col("id").alias("tid")) if tids is None else tids.select("tid")
    rows = named.crossJoin(F.broadcast(packed))

    def u(key):
        if sampler == "md5":
            return portable_uniform(F.lit(seed).cast("string"), F.col("tid").cast("string"), key)
        return F.pmod(F.xxhash64(F.lit(seed), F.col("tid"), key), F.lit(1 << 53)) / F.lit(2.0**53)

    drawn = F.filter("_sets", lambda s: u(s["key"]) < s["pi"])
    return rows.select("tid", F.array_sort(F.array_distinct(F.flatten(F.transform(drawn, lambda s: s["set"])))).alias("items"))
