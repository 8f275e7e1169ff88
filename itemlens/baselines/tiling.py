"""Tilings: sets with all baskets that contain them, chosen for the cells they cover."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.encode import compress


def _gains(cells: DataFrame, tiles: list[tuple[str, ...]], value) -> list[float]:
    """For each tile, the sum of `value` over its uncovered cells; one pass, a row for each tile and partition."""
    spark = cells.sparkSession
    rows = spark.createDataFrame([(n, list(t), t[0]) for n, t in enumerate(tiles)], "n int, tile array<string>, anchor string")
    wide = cells.select("items", "open", "mult", F.explode("items").alias("anchor"))
    met = wide.join(F.broadcast(rows), "anchor").where(F.size(F.array_except("tile", "items")) == 0)
    got = {r["n"]: r["g"] for r in met.groupBy("n").agg(F.sum(value).alias("g")).toLocalIterator()}
    return [got.get(n, 0) for n in range(len(tiles))]


def max_coverage(baskets: DataFrame, tiles: list[tuple[str, ...]], k: int) -> list[tuple[tuple[str, ...], int]]:
    """k tiles, each the one that covers most cells not covered before (ties by key)."""
    cells = compress(baskets).withColumn("open", F.col("items")).persist()
    out = []
    todo = sorted(tuple(sorted(t)) for t in tiles)
    chosen: list[tuple[str, ...]] = []
    for _ in range(k):
        open_ = F.col("items")
        for c in chosen:
            own = F.array(*map(F.lit, c))
            open_ = F.array_except(open_, F.when(F.size(F.array_except(own, F.col("items"))) == 0, own).otherwise(F.array().cast("array<string>")))
        gains = _gains(cells.withColumn("open", open_), todo, F.size(F.array_intersect("tile", "open")) * F.col("mult"))
        best = min(range(len(todo)), key=lambda n: (-gains[n], "|".join(todo[n])), default=None)
        if best is None or gains[best] <= 0:
            break
        chosen.append(todo[best])
        out.append((todo.pop(best), int(gains[best])))
    cells.unpersist()
    return out


def margins(baskets: DataFrame, steps: int = 100) -> tuple[dict[str, float], dict[int, float]]:
    """Log odds of the cells of a random matrix with the expected row and column sums: one term for each item, one for each basket size."""
    sizes = {r["n"]: r["c"] for r in baskets.groupBy(F.size("items").alias("n")).agg(F.count("*").alias("c")).toLocalIterator()}
    items = {r["i"]: r["c"] for r in baskets.select(F.explode("items").alias("i")).groupBy("i").agg(F.count("*").alias("c")).toLocalIterator()}
    names, ns = sorted(items), sorted(sizes)
    col, count = np.array([items[i] for i in names], float), np.array([sizes[n] for n in ns], float)
    a, b = np.zeros(len(names)), np.zeros(len(ns))
    for _ in range(steps):
        p = 1 / (1 + np.exp(-(a[:, None] + b[None, :])))
        a += np.clip((col - p @ count) / np.maximum((p * (1 - p)) @ count, 1e-9), -2, 2)
        p = 1 / (1 + np.exp(-(a[:, None] + b[None, :])))
        b += np.clip((np.array(ns, float) - p.sum(0)) / np.maximum((p * (1 - p)).sum(0), 1e-9), -2, 2)
        a, b = np.clip(a, -30, 30), np.clip(b, -30, 30)
    return dict(zip(names, a.tolist(), strict=True)), dict(zip(ns, b.tolist(), strict=True))


def budgeted(baskets: DataFrame, tiles: list[tuple[str, ...]], budget: float) -> list[tuple[tuple[str, ...], float, float]]:
    """Tiles by surprisal of their new cells per bit of description, while the descriptions fit the budget (bits).

    A tile's description names its items and its baskets: their number times the logs of both totals.
    """
    item_terms, size_terms = margins(baskets)
    spark = baskets.sparkSession
    cells = compress(baskets).persist()
    m = baskets.count()
    odds = spark.createDataFrame([(i, a) for i, a in item_terms.items()], "i string, a double")
    sizes = F.create_map(*[F.lit(x) for n, b in size_terms.items() for x in (n, b)])
    terms = F.create_map(*[F.lit(x) for i, a in item_terms.items() for x in (i, a)]) if len(item_terms) <= 1000 else None
    if terms is None:
        raise ValueError(f"{odds.count()} items; budgeted tiling is for 1000 or fewer")
    todo = sorted(tuple(sorted(t)) for t in tiles)
    support = _gains(cells.withColumn("open", F.col("items")), todo, F.col("mult"))
    out, chosen, spent = [], [], 0.0
    while todo:
        open_ = F.col("items")
        for c in chosen:
            own = F.array(*map(F.lit, c))
            open_ = F.array_except(open_, F.when(F.size(F.array_except(own, F.col("items"))) == 0, own).otherwise(F.array().cast("array<string>")))
        surprise = F.aggregate(
            F.array_intersect("tile", "open"), F.lit(0.0), lambda s, i: s + F.log1p(F.exp(-(F.element_at(terms, i) + F.element_at(sizes, F.size("items")))))
        )
        gains = _gains(cells.withColumn("open", open_), todo, surprise * F.col("mult"))
        cost = [len(t) * math.log2(max(2, len(item_terms))) + s * math.log2(max(2, m)) for t, s in zip(todo, support, strict=True)]
        able = [n for n in range(len(todo)) if gains[n] > 0 and spent + cost[n] <= budget]
        if not able:
            break
        best = min(able, key=lambda n: (-gains[n] / cost[n], "|".join(todo[n])))
        spent += cost[best]
        out.append((todo[best], float(gains[best]), cost[best]))
        chosen.append(todo.pop(best))
        support.pop(best)
    cells.unpersist()
    return out
