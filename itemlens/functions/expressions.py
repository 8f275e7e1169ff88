"""Expressions on itemsets and probabilities, also as SQL functions."""

from __future__ import annotations

import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def contains(basket: Column, itemset: Column) -> Column:
    return F.size(F.array_except(itemset, basket)) == 0


def sym_diff_size(a: Column, b: Column) -> Column:
    return F.size(F.array_except(a, b)) + F.size(F.array_except(b, a))


def itemset_key(items: Column) -> Column:
    return F.array_join(F.array_sort(items.cast("array<string>")), "|")


def binary_entropy(p: Column) -> Column:
    """In nats; 0 at 0 and at 1."""
    return F.when((p <= 0) | (p >= 1), 0.0).otherwise(-p * F.log(p) - (1 - p) * F.log(1 - p))


def chi2_score(observed: Column, expected: Column, m: Column) -> Column:
    """Observed against expected support of m baskets, over the two cells of containing the set or not."""
    gap = (observed - expected) * (observed - expected)
    return F.when(expected >= m, 0.0).otherwise(gap / expected + gap / (m - expected))


def bits(logp: Column) -> Column:
    return -logp / F.log(F.lit(2.0))


def implied_logp(length_in_bits: Column) -> Column:
    """The log probability of which a code of that length is optimal, up to a constant."""
    return -length_in_bits * F.log(F.lit(2.0))


def portable_uniform(*parts: Column) -> Column:
    """In [0, 1), from md5 of the parts; other SQL engines give the same value."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 8), 16, 10).cast("long") / F.lit(2.0**32)


#: Temporary SQL functions, inlined by the optimiser.
SQL_FUNCTIONS = {
    "itemset_contains": "(x ARRAY<STRING>, s ARRAY<STRING>) RETURNS BOOLEAN RETURN size(array_except(s, x)) = 0",
    "sym_diff_size": "(a ARRAY<STRING>, b ARRAY<STRING>) RETURNS INT RETURN size(array_except(a, b)) + size(array_except(b, a))",
    "binary_entropy": "(p DOUBLE) RETURNS DOUBLE RETURN CASE WHEN p <= 0 OR p >= 1 THEN 0D ELSE -p * ln(p) - (1 - p) * ln(1 - p) END",
    "itemset_key": "(s ARRAY<STRING>) RETURNS STRING RETURN array_join(array_sort(s), '|')",
    "chi2_score": "(o DOUBLE, e DOUBLE, m DOUBLE) RETURNS DOUBLE RETURN CASE WHEN e >= m THEN 0D ELSE (o - e) * (o - e) / e + (o - e) * (o - e) / (m - e) END",
}


class Subsets:
    """subsets(items): a row for each non-empty proper subset of an array of 20 items at most, in the array's order."""

    def eval(self, items: list):
        items = items or []
        if len(items) > 20:
            raise ValueError(f"{len(items)} items; subsets are for 20 or fewer")
        for mask in range(1, (1 << len(items)) - 1):
            yield [x for i, x in enumerate(items) if mask >> i & 1],


class InterestingItemsets:
    """interesting_itemsets(TABLE(baskets) WITH SINGLE PARTITION, k): the k best non-singletons of baskets (items) that one task can hold, by a plain miner.

    Pairs that raise the profit of the singletons' model, best support first, each accepted pair
    taking its baskets from its items; for small inputs, without supersets of pairs.
    """

    def __init__(self):
        self.baskets, self.k = [], 10

    def eval(self, row, k: int):
        self.baskets.append(frozenset(row["items"] or ()))
        self.k = k

    def terminate(self):
        from collections import Counter
        from itertools import combinations
        from math import log

        m = len(self.baskets)
        h = lambda n: 0.0 if n <= 0 or n >= m else -n / m * log(n / m) - (1 - n / m) * log(1 - n / m)
        usage = Counter(i for b in self.baskets for i in b)
        support = Counter(p for b in self.baskets for p in combinations(sorted(b), 2))
        taken, out = set(), []
        for (a, b), n in sorted(support.items(), key=lambda x: (-x[1], x[0])):
            if not {a, b} & taken and h(usage[a]) + h(usage[b]) - h(n) - h(usage[a] - n) - h(usage[b] - n) > 1e-12:
                taken |= {a, b}
                out.append((f"{a}|{b}", n))
        for rank, (key, n) in enumerate(out[: self.k], 1):
            yield rank, key, n


def register(spark: SparkSession) -> list[str]:
    """Register the SQL functions, the Arrow function jaccard(x, s), the aggregate mean_distance(items) and two table functions."""
    for name, body in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}{body}")

    @F.arrow_udf("double")
    def jaccard(x: pa.Array, s: pa.Array) -> pa.Array:
        pairs = [(set(a or ()), set(b or ())) for a, b in zip(x.to_pylist(), s.to_pylist(), strict=True)]
        return pa.array([len(a & b) / len(a | b) if a | b else 1.0 for a, b in pairs], pa.float64())

    @F.pandas_udf("double")
    def mean_distance(items: pd.Series) -> float:
        sets = [frozenset(x) for x in items]
        nearest = [min((len(a ^ b) for j, b in enumerate(sets) if j != i), default=None) for i, a in enumerate(sets)]
        return float(sum(nearest) / len(nearest)) if len(sets) > 1 else float("nan")

    spark.udf.register("jaccard", jaccard)
    spark.udf.register("mean_distance", mean_distance)
    spark.udtf.register("subsets", F.udtf(Subsets, returnType="subset array<string>"))
    spark.udtf.register("interesting_itemsets", F.udtf(InterestingItemsets, returnType="rank int, itemset string, support long"))
    return [*SQL_FUNCTIONS, "jaccard", "mean_distance", "subsets", "interesting_itemsets"]


def proper_subsets(items: Column) -> Column:
    """All non-empty proper subsets of a short array, each in the array's order."""
    n = F.size(items)
    masks = F.sequence(F.lit(1), (F.pow(F.lit(2), n) - 2).cast("int"))
    chosen = lambda mask: F.filter(items, lambda x, i: F.pmod(F.floor(mask / F.pow(F.lit(2), i)), F.lit(2)) == 1)
    return F.when(n < 2, F.array().cast("array<array<string>>")).otherwise(F.transform(masks, chosen))


def with_row(df: DataFrame, row: DataFrame) -> DataFrame:
    """df beside a single row (a total, a catalog as one array)."""
    return df.crossJoin(F.broadcast(row))
