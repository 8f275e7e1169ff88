"""Choices that depend on the size and shape of the baskets."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.cover import NATIVE_SETS


@dataclass(frozen=True)
class Stats:
    baskets: int
    distinct: int
    items: int
    mean_length: float
    longest: int


@dataclass(frozen=True)
class Plan:
    compress: bool
    kernel: str
    batch: int
    em_every: int


def stats(baskets: DataFrame) -> Stats:
    """One pass with sketches; for choices only, never for results."""
    row = baskets.agg(
        F.count("*").alias("n"), F.approx_count_distinct(F.xxhash64("items")).alias("d"), F.avg(F.size("items")).alias("mean"), F.max(F.size("items")).alias("longest")
    ).first()
    items = baskets.select(F.explode("items").alias("i")).agg(F.approx_count_distinct("i").alias("u")).first()["u"]
    return Stats(row["n"], min(row["d"], row["n"]), items, float(row["mean"] or 0), row["longest"] or 0)


def choose(s: Stats, multi_sets: int = 0) -> Plan:
    """Merge equal baskets if that halves them; the native kernel for short baskets and catalogs; fewer EM rounds on large data."""
    kernel = "native" if multi_sets <= NATIVE_SETS and s.items <= NATIVE_SETS and s.mean_length <= 16 else "lazy_heap" if s.mean_length > 100 else "arrow"
    return Plan(s.distinct * 2 <= s.baskets, kernel, 64 if s.baskets < 10**7 else 1024, 1 if s.baskets < 10**6 else 5)
