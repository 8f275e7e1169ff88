"""Candidate itemsets: unions of known sets, highest support first, in a bounded queue."""

from __future__ import annotations

import heapq
import itertools
import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .catalog import Catalog
from .held import Held


#: Up to so many possible pairs of items, all that meet are counted in one pass and kept on the driver; beyond, those in the queue are counted in blocks.
PAIRS_IN_ONE_PASS = 200_000


@dataclass(frozen=True)
class Candidate:
    key: str
    items: tuple[str, ...]
    support: int


def ranked(catalog: Catalog) -> list:
    return sorted(catalog.values(), key=lambda s: (-s.support, s.key))


def pair_unions(catalog: Catalog, rejected: set[str], q: int, order: str = "lexicographic", barren: Callable[[str], bool] = lambda key: False) -> Iterator[tuple[str, ...]]:
    """Unions of two sets, each once, known and rejected ones and those that are `barren` left out, until q have been given.

    `lexicographic`: the best set with all others, then the second best and so on.  `rank_sum`: by
    the sum of both ranks.
    """
    sets, seen, given = ranked(catalog), set(), 0
    n = len(sets)
    if order == "rank_sum":
        pairs = ((i, total - i) for total in range(1, 2 * n - 2) for i in range(max(0, total - n + 1), (total + 1) // 2))
    else:
        pairs = ((i, j) for i in range(n) for j in range(i + 1, n))
    for i, j in pairs:
        union = tuple(sorted({*sets[i].items, *sets[j].items}))
        key = "|".join(union)
        if key in seen or key in catalog or key in rejected or barren(key):
            continue
        seen.add(key)
        yield union
        given += 1
        if given >= q:
            return


def counted(compressed: DataFrame, unions: list[tuple[str, ...]], item_support: dict[str, int]) -> dict[str, int]:
    """Supports of the given sets over weighted baskets; each set is anchored at its rarest item.

    The sets travel to the baskets and each partition adds up its own counts, so no basket is shuffled.
    """
    if not unions:
        return {}
    waiting: dict[str, dict[tuple[str, ...], int]] = {}
    for n, u in enumerate(unions):
        anchor = min(u, key=lambda i: (item_support.get(i, 0), i))
        waiting.setdefault(anchor, {})[tuple(sorted(i for i in u if i != anchor))] = n
    shared = compressed.sparkSession.sparkContext.broadcast(waiting)

    def run(batches):
        by_anchor, sums = shared.value, {}
        # Of each anchor's sets: their sizes without it, and their items.
        sizes = {a: sorted({len(rest) for rest in sets}) for a, sets in by_anchor.items()}
        held = {a: frozenset(i for rest in sets for i in rest) for a, sets in by_anchor.items()}
        for batch in batches:
            for items, mult in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                basket = set(items)
                for i in basket.intersection(by_anchor):
                    sets, others = by_anchor[i], basket & held[i]
                    # Either the sets are looked up in the basket or its subsets among the sets, whichever are fewer.
                    if sum(math.comb(len(others), s) for s in sizes[i]) < len(sets):
                        others = sorted(others)
                        met = (n for s in sizes[i] for rest in itertools.combinations(others, s) if (n := sets.get(rest)) is not None)
                    else:
                        met = (n for rest, n in sets.items() if basket.issuperset(rest))
                    for n in met:
                        sums[n] = sums.get(n, 0) + mult
        if sums:
            yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int64()), pa.array(list(sums.values()), pa.int64())], ["n", "support"])

    parts = compressed.select("items", "mult").mapInArrow(run, "n long, support long")
    found = {"|".join(unions[r["n"]]): r["support"] for r in parts.groupBy("n").agg(F.sum("support").alias("support")).toLocalIterator()}
    shared.unpersist()
    return found


def pair_supports(compressed: DataFrame, at_least: int = 1) -> DataFrame:
    """(a, b, support) of all pairs of items that meet, a before b: the first queue without a list of pairs."""
    i, j = F.posexplode("items"), F.posexplode("items")
    left = compressed.select("items", "mult", i.alias("i", "a"))
    both = left.select("mult", "a", F.explode(F.slice("items", F.col("i") + 2, F.size("items"))).alias("b"))
    return both.groupBy("a", "b").agg(F.sum("mult").alias("support")).where(F.col("support") >= at_least)


def build_queue(
    compressed: DataFrame, catalog: Catalog, rejected: set[str], item_support: dict[str, int], q: int = 100_000, pair_order: str = "lexicographic",
    cap: str = "first", min_support: int = 1, cache: dict[str, int] | None = None, prune: str | None = None, m: int = 0, block: int = 100_000, near: Held | None = None,
) -> list[Candidate]:
    """Up to q candidates, best support first (ties by key); unions without support are left out.

    cap="first" takes the first q unions in pair order, as the method is described; "top_support"
    takes the q of highest support, stopping where the rank bound can no longer be beaten.
    prune="chi2" tests the pair that makes each union and keeps those above the 5 % level.
    near: the same baskets as the driver holds them, if it does.
    """
    cache = {} if cache is None else cache
    only_single = all(len(s.items) == 1 for s in catalog.values())
    if only_single and len(catalog) * (len(catalog) - 1) // 2 > q and cap == "top_support":
        top = pair_supports(compressed, min_support).orderBy(F.desc("support"), "a", "b").limit(q)
        found = [Candidate("|".join(sorted((r["a"], r["b"]))), tuple(sorted((r["a"], r["b"]))), r["support"]) for r in top.toLocalIterator()]
        return sorted((c for c in found if c.key not in rejected), key=lambda c: (-c.support, c.key))
    if "" not in cache and len(catalog) > 2 and len(item_support) * (len(item_support) - 1) // 2 <= PAIRS_IN_ONE_PASS:
        # All pairs of items that meet are counted in one pass; pairs that are absent have no support.
        met = near.pairs() if near else pair_supports(compressed).select("a", "b", "support").toLocalIterator()
        cache |= {f"{a}|{b}": n for a, b, n in met} | {"": 0}
    limit = q if cap == "first" else len(catalog) ** 2
    heap: list[tuple[int, str]] = []
    out: dict[str, Candidate] = {}
    # Unions that an earlier queue found to have no support can never be taken, so this one looks beyond them.
    unions = pair_unions(catalog, rejected, limit, pair_order, lambda key: ("barren", key) in cache)
    while True:
        part = [u for _, u in zip(range(block), unions, strict=False)]
        if not part:
            break
        new = [u for u in part if (len(u) > 2 or "" not in cache) and "|".join(u) not in cache]
        got = near.supports(new) if near else counted(compressed, new, item_support)
        cache.update({"|".join(u): got.get("|".join(u), 0) for u in new})
        for u in part:
            c = Candidate("|".join(u), u, cache.get("|".join(u), 0))
            if not c.support:
                cache["barren", c.key] = 0
            if c.support >= max(1, min_support):
                out[c.key] = c
                if cap != "first":
                    heapq.heappush(heap, (c.support, c.key))
                    if len(heap) > q:
                        out.pop(heapq.heappop(heap)[1])
        if cap != "first" and len(heap) >= q and min(item_support.get(i, 0) for i in part[-1]) < heap[0][0]:
            break
    found = list(out.values())
    if prune == "chi2":
        found = [c for c in found if _dependent(c, item_support, m)]
    return sorted(found, key=lambda c: (-c.support, c.key))


def _dependent(c: Candidate, item_support: dict[str, int], m: int, level: float = 3.841459) -> bool:
    """Whether the observed support differs from independence at the 5 % level of one degree of freedom (a fixed value)."""
    expected = m
    for i in c.items:
        expected *= item_support.get(i, 0) / m
    if expected <= 0 or expected >= m:
        return False
    gap = (c.support - expected) ** 2
    return gap / expected + gap / (m - expected) > level


def apriori_queue(compressed: DataFrame, item_support: dict[str, int], min_support: int, q: int = 100_000, largest: int = 4) -> list[Candidate]:
    """The level-wise alternative: sets grow by one item from those whose subsets are all frequent."""
    level = sorted((i,) for i, n in item_support.items() if n >= min_support)
    frequent = set(level)
    out: list[Candidate] = []
    for size in range(2, largest + 1):
        grown = [a + (b[-1],) for x, a in enumerate(level) for b in level[x + 1 :] if a[:-1] == b[:-1]]
        grown = [g for g in grown if all(g[:i] + g[i + 1 :] in frequent for i in range(size))][:q]
        got = counted(compressed, grown, item_support)
        level = [g for g in grown if got.get("|".join(g), 0) >= min_support]
        frequent.update(level)
        out += [Candidate("|".join(g), g, got["|".join(g)]) for g in level]
        if not level or len(out) >= q:
            break
    return sorted(out, key=lambda c: (-c.support, c.key))[:q]
