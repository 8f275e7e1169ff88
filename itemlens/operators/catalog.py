"""The catalog: itemsets with their probabilities.

A catalog has a row for each item and each accepted itemset, so it grows with the vocabulary and
the iterations, never with the baskets.  The driver holds it between passes and sends it along
with each; `LARGEST` checks that it stays of a size to be sent.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Itemsets that one catalog may have.
LARGEST = 2_000_000


def key_of(items) -> str:
    return "|".join(sorted(items))


@dataclass(frozen=True)
class Itemset:
    items: tuple[str, ...]
    pi: float
    usage: int = 0
    support: int = 0
    born_iter: int = 0
    key: str = field(default="", compare=False)

    @staticmethod
    def of(items, pi: float, usage: int = 0, support: int = 0, born_iter: int = 0) -> Itemset:
        items = tuple(sorted(items))
        return Itemset(items, pi, usage, support, born_iter, "|".join(items))

    def with_(self, **changes) -> Itemset:
        return replace(self, **changes)


Catalog = dict[str, Itemset]


def from_support(counts: list[tuple[str, int]], m: int) -> Catalog:
    """Singletons with their relative supports."""
    if len(counts) > LARGEST:
        raise ValueError(f"{len(counts)} items; limit the vocabulary (sources.baskets.limited) to {LARGEST}")
    return {i: Itemset.of((i,), n / m if m else 0.0, n, n) for i, n in counts}


def to_df(spark: SparkSession, catalog: Catalog) -> DataFrame:
    """(key, items, size, pi, usage, support, born_iter)"""
    rows = [(s.key, list(s.items), len(s.items), s.pi, s.usage, s.support, s.born_iter) for s in catalog.values()]
    return spark.createDataFrame(rows, "key string, items array<string>, size int, pi double, usage long, support long, born_iter int")


def from_df(df: DataFrame) -> Catalog:
    return {r["key"]: Itemset.of(r["items"], r["pi"], r["usage"], r["support"], r["born_iter"]) for r in df.toLocalIterator()}


def plain(sets) -> list[tuple]:
    """Itemsets as tuples, for broadcasts: workers may lack the class."""
    return [(s.items, s.pi, s.support) for s in sets]


def unplain(rows: list[tuple]) -> list[Itemset]:
    return [Itemset.of(items, pi, 0, support) for items, pi, support in rows]


def prune(catalog: Catalog, keep_singletons: bool = False, floor: float | None = None) -> Catalog:
    """Without the itemsets of probability 0; singletons may be kept, at a floor, for baskets yet to come."""
    out = {}
    for k, s in catalog.items():
        if s.pi > 0:
            out[k] = s
        elif keep_singletons and len(s.items) == 1:
            out[k] = s.with_(pi=floor or 0.0)
    return out


def count_support(baskets: DataFrame, itemsets: DataFrame, weight: str | None = None) -> DataFrame:
    """(key, support) of itemsets (key, items, anchor) in baskets (items, [weight]); sets without support are absent.

    Each set waits at its anchor, ideally its rarest item: only baskets with that item are compared.
    """
    w = F.col(weight) if weight else F.lit(1)
    wide = baskets.select(F.col("items").alias("basket"), w.alias("w"), F.explode("items").alias("anchor"))
    met = wide.join(itemsets.select("key", "items", "anchor"), "anchor").where(F.size(F.array_except("items", "basket")) == 0)
    return met.groupBy("key").agg(F.sum("w").alias("support"))
