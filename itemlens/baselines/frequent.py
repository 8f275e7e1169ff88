"""Frequent and closed itemsets, ranked by support and by chi-square."""

from __future__ import annotations

import heapq
import itertools
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.ml.fpm import FPGrowth
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.expressions import itemset_key
from ..operators import rank
from ..operators.encode import item_support
from ..operators.held import Held
from ..operators.miner import Ready

#: The chi-square list is drawn from this many closed sets of highest support.
CLOSED_KEPT = 100_000
#: By this factor the support falls while too few sets are found.
STEP_DOWN = 0.85
#: A level that cannot have more frequent sets than this is listed at once.
LISTED = 200_000


def frequent(baskets: DataFrame, min_support: float) -> DataFrame:
    """(key, items, size, support) of all sets in a share of min_support or more of the baskets (FP-growth, distributed)."""
    model = FPGrowth(itemsCol="items", minSupport=min_support).fit(baskets.select("items"))
    found = model.freqItemsets.select(F.array_sort("items").alias("items"), F.col("freq").alias("support"))
    return found.select(itemset_key(F.col("items")).alias("key"), "items", F.size("items").alias("size"), "support")


def at_most(baskets: DataFrame, levels: list[float], n: int) -> list[float]:
    """For each of the falling levels, a number that its frequent sets cannot exceed, in one pass.

    A basket holds 2^k - 1 sets of its k frequent items, and each frequent set is in a share `level`
    of the n baskets or more.
    """
    counts = baskets.select(F.explode("items").alias("i")).groupBy("i").agg(F.count("*").alias("c")).where(F.col("c") >= levels[-1] * n * (1 - 1e-9))
    step = {r["i"]: next((k for k, level in enumerate(levels) if r["c"] >= level * n * (1 - 1e-9)), len(levels) - 1) for r in counts.toLocalIterator()}
    shared = baskets.sparkSession.sparkContext.broadcast(step)

    def run(batches):
        of, sums = shared.value, [0.0] * len(levels)
        for b in batches:
            for items in b.column(0).to_pylist():
                held = [0] * len(levels)
                for i in items:
                    if i in of:
                        held[of[i]] += 1
                k = 0
                for at, more in enumerate(held):
                    k += more
                    sums[at] += 2.0 ** min(k, 1000) - 1
        yield pa.RecordBatch.from_arrays([pa.array(range(len(levels)), pa.int32()), pa.array(sums)], ["at", "sets"])

    found = {r["at"]: r["sets"] for r in baskets.select("items").mapInArrow(run, "at int, sets double").groupBy("at").agg(F.sum("sets").alias("sets")).collect()}
    shared.unpersist()
    return [found.get(at, 0.0) / (level * n) if level > 0 else math.inf for at, level in enumerate(levels)]


def held_commonest(near: Held, least: int, most: int) -> Iterator[tuple[tuple[str, ...], int]]:
    """(items, support) of the `most` sets in `least` or more baskets that the driver holds, in the order of `commonest`.

    A set comes before all that extend it, in support and in key, so the best of those known is the next one.
    """

    def grown(items: tuple[str, ...], after: list[int]) -> None:
        rows = near.having(items)
        words, mult, kept = near.words[:, rows], near.mult[rows], []
        for i in after:
            if (n := int(mult[near.having((near.items[i],), words)].sum())) >= least:
                kept.append((i, n))
        for at, (i, n) in enumerate(kept):
            more = (*items, near.items[i])
            heapq.heappush(waiting, (-n, "|".join(more), more, [x for x, _ in kept[at + 1 :]]))

    waiting: list[tuple[int, str, tuple[str, ...], list[int]]] = []
    grown((), list(range(len(near.items))))
    while waiting and most > 0:
        n, _, items, after = heapq.heappop(waiting)
        most -= 1
        yield items, -n
        if after:
            grown(items, after)


def held_closed(near: Held, least: int) -> Iterator[tuple[tuple[str, ...], int]]:
    """(items, support) of all closed sets in `least` or more baskets that the driver holds, best support first, ties by key.

    Each is the closure of one closed set and one item, and is grown from the one it extends without
    changing what comes before that item, so from one only; that one has more support, so it comes earlier.
    """
    width = np.arange(len(near.items))

    def closure(words: np.ndarray) -> frozenset[int]:
        met = np.ascontiguousarray(np.bitwise_and.reduce(words, axis=1))
        return frozenset(width[np.unpackbits(met.view(np.uint8), bitorder="little")[: len(width)] > 0].tolist())

    def add(own: frozenset[int], n: int, core: int, after: list[int]) -> None:
        items = tuple(near.items[i] for i in sorted(own))
        heapq.heappush(waiting, (-n, "|".join(items), items, own, core, after))

    waiting: list[tuple] = []
    total = int(near.mult.sum())
    if total >= least and len(near.mult):
        add(closure(near.words), total, -1, width.tolist())
    while waiting:
        n, _, items, own, core, after = heapq.heappop(waiting)
        if items:
            yield items, -n
        rows = near.having(items)
        words, mult, kept = near.words[:, rows], near.mult[rows], []
        for i in after:
            if i not in own:
                having = near.having((near.items[i],), words)
                if (m := int(mult[having].sum())) >= least:
                    kept.append((i, m, having))
        for at, (i, m, having) in enumerate(kept):
            grown = closure(words[:, having])
            if all(x >= i or x in own for x in grown):
                add(grown, m, i, [x for x, *_ in kept[at + 1 :]])


def all_closed(baskets: DataFrame | Ready, min_support: float) -> DataFrame:
    """(key, items, size, support) of all closed frequent sets, none left out: listed on the driver up to LISTED of them, beyond that by Spark."""
    if isinstance(baskets, Ready):
        least = max(1, math.ceil(min_support * baskets.m))
        if near := baskets.common(least):
            if least not in baskets.closed:
                found = list(itertools.islice(held_closed(near, least), LISTED + 1))
                baskets.closed[least] = found if len(found) <= LISTED else None
            if (found := baskets.closed[least]) is not None:
                return baskets.sparkSession.createDataFrame([("|".join(s), list(s), len(s), n) for s, n in found], "key string, items array<string>, size int, support long")
        baskets = baskets.baskets
    return closed(frequent(baskets, min_support))


def commonest(baskets: DataFrame | Ready, min_support: float, most: int = CLOSED_KEPT) -> DataFrame:
    """The `most` frequent sets of highest support (ties by key), or all of them if there are fewer.

    Where a few dozen words are in most texts, the sets above a low support are too many to list.
    The support falls step by step until enough sets are found; what is below cannot be among them.
    It starts at the last step that cannot have more than LISTED sets.
    """
    if isinstance(baskets, Ready):
        least = max(1, math.ceil(min_support * baskets.m))
        if near := baskets.common(least):
            if (found := baskets.listed.get((least, most))) is None:
                found = baskets.listed[least, most] = list(held_commonest(near, least, most))
            return baskets.sparkSession.createDataFrame([("|".join(s), list(s), len(s), n) for s, n in found], "key string, items array<string>, size int, support long")
        baskets = baskets.baskets
    top = baskets.select(F.explode("items").alias("i")).groupBy("i").agg(F.count("*").alias("n")).agg(F.max("n")).first()[0]
    n = max(1, baskets.count())
    levels = [max(min_support, STEP_DOWN * (top or 0) / n)]
    while levels[-1] > min_support:
        levels.append(max(min_support, STEP_DOWN * levels[-1]))
    few = [level for level, bound in zip(levels, at_most(baskets, levels, n), strict=True) if bound <= max(most, LISTED)]
    level = few[-1] if few else levels[0]
    while True:
        found = frequent(baskets, level).persist()
        if level <= min_support or found.count() >= most:
            return found.orderBy(F.desc("support"), "key").limit(most)
        found.unpersist()
        level = max(min_support, STEP_DOWN * level)


def closed(itemsets: DataFrame) -> DataFrame:
    """Sets without a superset of equal support; supersets are met on support and on one item, one size up."""
    grown = itemsets.select("support", F.col("size").alias("bigger"), F.col("items").alias("superset"), F.explode("items").alias("anchor"))
    keyed = itemsets.withColumn("anchor", F.element_at("items", 1))
    same = (keyed["support"] == grown["support"]) & (keyed["anchor"] == grown["anchor"]) & (grown["bigger"] == keyed["size"] + 1) & (F.size(F.array_except(keyed["items"], grown["superset"])) == 0)
    return keyed.join(grown, same, "left_anti").drop("anchor")


def chi2_list(baskets: DataFrame | Ready, min_support: float, k: int = 50, kept: int | None = CLOSED_KEPT) -> DataFrame:
    """(rank, itemset, support, chi2): the k non-singletons of highest chi-square among the closed ones of the `kept` sets of highest support, or of all.

    Whether a set is closed is decided among those kept; of sets cut off at the last support, ties by key stay.
    """
    m = baskets.m if isinstance(baskets, Ready) else baskets.count()
    items = baskets.sparkSession.createDataFrame(list(baskets.supports.items()), "item string, support long") if isinstance(baskets, Ready) else item_support(baskets)
    best = all_closed(baskets, min_support) if kept is None else closed(commonest(baskets, min_support, kept))
    scored = rank.chi2(best.where("size > 1"), items, m)
    order = [F.desc(F.round("chi2", 6)), F.asc("key")]
    top = scored.orderBy(*order).limit(k)
    return top.select(F.row_number().over(Window.orderBy(*order)).alias("rank"), F.col("key").alias("itemset"), "items", "support", "chi2")
