"""Covering baskets with itemsets: greedy, lazy greedy, primal-dual and exact kernels.

Two ways to run the greedy cover: `native` is one expression over arrays and stays in the JVM,
for catalogs of a few itemsets; `arrow` runs the kernels below over Arrow batches, for
long baskets and large catalogs.  Both break ties alike.  The ratio of weight to newly covered
items is rounded to 9 decimals; then more newly covered items, larger support and the smaller
key win.
"""

from __future__ import annotations

import heapq
import math
import sys
from collections import defaultdict
from collections.abc import Iterable

import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .catalog import Catalog, Itemset, plain, to_df, unplain

# Executors need no copy of the package: its functions travel with the tasks.
cloudpickle.register_pickle_by_value(sys.modules[__package__.partition(".")[0]])

#: Catalogs of more sets than this go to the lazy queue over Arrow batches under kernel="auto", which measured faster.
NATIVE_SETS = 16


def weight_of(pi: float, mode: str = "neglog") -> float:
    """`neglog`: -ln pi.  `logodds` also counts the saved cost of leaving the set unused, and may be negative."""
    if pi <= 0:
        return math.inf
    if mode == "neglog":
        return -math.log(pi) + 0.0
    return -math.log(pi) + (math.log1p(-pi) if pi < 1 else -math.inf)


class Index:
    """Itemsets by anchor item, for finding those that a basket contains."""

    def __init__(self, catalog: Iterable[Itemset], mode: str = "neglog"):
        self.sets = {s.key: (frozenset(s.items), weight_of(s.pi, mode), s.support) for s in catalog if s.pi > 0}
        frequency = defaultdict(int)
        for items, _, _ in self.sets.values():
            for i in items:
                frequency[i] += 1
        self.single = {next(iter(s[0])): k for k, s in self.sets.items() if len(s[0]) == 1}
        self.negative = any(w < 0 for _, w, _ in self.sets.values())
        self.full_rank = {k: self._rank(k, len(s[0]), None) for k, s in self.sets.items()}
        self.by_anchor: dict[str, list[str]] = defaultdict(list)
        for k, (items, _, _) in self.sets.items():
            if len(items) > 1:
                self.by_anchor[min(items, key=lambda i: (frequency[i], i))].append(k)

    def applicable(self, basket: frozenset) -> list[str]:
        out = [self.single[i] for i in basket if i in self.single]
        for i in basket:
            for k in self.by_anchor.get(i, ()):
                if self.sets[k][0] <= basket:
                    out.append(k)
        return out

    def _rank(self, key: str, new: int, forced: str | None) -> tuple:
        _, weight, support = self.sets[key]
        weight = 0.0 if key == forced else weight
        return (round(weight / new, 9) + 0.0, -new, -support, key)

    def greedy(self, basket: frozenset, usable: list[str], forced: str | None = None) -> list[str] | None:
        """Chosen keys in order; None if the sets do not cover the basket.  `forced` has weight 0 and goes first."""
        left, chosen = set(basket), []
        if forced is not None:
            chosen.append(forced)
            left -= self.sets[forced][0]
        usable = [k for k in usable if k != forced]
        while left:
            best = None
            for k in usable:
                new = len(self.sets[k][0] & left)
                if new and (best is None or (rank := self._rank(k, new, forced)) < best):
                    best = self._rank(k, new, forced)
            if best is None:
                return None
            chosen.append(best[-1])
            left -= self.sets[best[-1]][0]
        return chosen

    def lazy(self, basket: frozenset, usable: list[str], forced: str | None = None) -> list[str] | None:
        """The same cover with a queue: gains only fall, so an entry that is still best after an update is the best."""
        if self.negative:
            return self.greedy(basket, usable, forced)  # a negative ratio improves as fewer items are new
        left, chosen = set(basket), []
        if forced is not None:
            chosen.append(forced)
            left -= self.sets[forced][0]
        queue = [self.full_rank[k] for k in usable if k != forced]
        heapq.heapify(queue)
        while left:
            if not queue:
                return None
            top = queue[0]
            items = self.sets[top[-1]][0]
            new = len(items & left)
            if not new:
                heapq.heappop(queue)
                continue
            if new < -top[1]:
                heapq.heapreplace(queue, self._rank(top[-1], new, None))
                continue
            heapq.heappop(queue)
            chosen.append(top[-1])
            left -= items
        return chosen

    def primal_dual(self, basket: frozenset, usable: list[str]) -> list[str] | None:
        """Raise the price of one uncovered item after another until a set that holds it is paid for."""
        slack = {k: self.sets[k][1] for k in usable}
        holding = defaultdict(list)
        for k in sorted(usable):
            for i in self.sets[k][0]:
                holding[i].append(k)
        left, chosen = set(basket), []
        for item in sorted(basket):
            if item in left:
                if not holding[item]:
                    return None
                paid = min(holding[item], key=lambda k: (round(slack[k], 12), k))
                price = slack[paid]
                for k in holding[item]:
                    slack[k] -= price
                chosen.append(paid)
                left -= self.sets[paid][0]
        return chosen

    def exact(self, basket: frozenset, usable: list[str], max_items: int = 20) -> list[str] | None:
        """A cover of least total weight, by branching on an uncovered item; for small baskets only."""
        if len(basket) > max_items:
            raise ValueError(f"{len(basket)} items; exact covers are for {max_items} or fewer")
        best: list = [math.inf, None]

        def search(left: frozenset, chosen: list[str], total: float) -> None:
            if total >= best[0]:
                return
            if not left:
                best[:] = total, chosen
                return
            item = min(left)
            for k in sorted((k for k in usable if item in self.sets[k][0]), key=lambda k: (self.sets[k][1], k)):
                search(left - self.sets[k][0], [*chosen, k], total + self.sets[k][1])

        search(basket, [], 0.0)
        return best[1]

    def drop_redundant(self, basket: frozenset, chosen: list[str]) -> list[str]:
        kept = list(chosen)
        for k in sorted(chosen, key=lambda k: -self.sets[k][1]):
            rest = [s for s in kept if s != k]
            if frozenset().union(*(self.sets[s][0] for s in rest)) >= basket:
                kept = rest
        return kept

    def cover(self, kernel: str, basket: frozenset) -> list[str] | None:
        usable = self.applicable(basket)
        if kernel in ("arrow", "greedy"):
            return self.greedy(basket, usable)
        return {"lazy_heap": self.lazy, "primal_dual": self.primal_dual, "exact": self.exact}[kernel](basket, usable)


def cover(baskets: DataFrame, catalog: Catalog, weight: str = "neglog", kernel: str = "auto", drop_redundant: bool = False, floor: float | None = None) -> DataFrame:
    """baskets (…, items) with `cover` (keys in the order chosen) and `cost` (total weight).

    A basket that the catalog cannot cover has a null cover; with `floor`, unknown items are
    covered by singletons of that probability instead.
    """
    if kernel == "auto":
        kernel = "native" if len(catalog) <= NATIVE_SETS and not drop_redundant and floor is None and weight == "neglog" else "lazy_heap"
    if kernel == "native":
        return _native(baskets, catalog, weight)
    spark = baskets.sparkSession
    shared = spark.sparkContext.broadcast(plain(catalog.values()))
    names = [f.name for f in baskets.schema]
    at = names.index("items")

    def run(batches):
        index = Index(unplain(shared.value), weight)
        for batch in batches:
            covers, costs = [], []
            for items in batch.column(at).to_pylist():
                basket = frozenset(items)
                extra = [i for i in basket if floor is not None and i not in index.single]
                got = index.cover(kernel, basket.difference(extra)) if extra else index.cover(kernel, basket)
                if got is not None and drop_redundant:
                    got = index.drop_redundant(basket, got)
                if got is not None:
                    costs.append(sum(index.sets[k][1] for k in got) - len(extra) * math.log(floor or 1))
                    covers.append(got + sorted(extra))
                else:
                    covers.append(None)
                    costs.append(None)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(covers, pa.list_(pa.string())), pa.array(costs, pa.float64())], [*names, "cover", "cost"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in baskets.schema)
    return baskets.mapInArrow(run, f"{fields}, cover array<string>, cost double")


def _native(baskets: DataFrame, catalog: Catalog, weight: str) -> DataFrame:
    """The greedy cover as one fold over as many steps as the basket has items."""
    spark = baskets.sparkSession
    rows = to_df(spark, {k: s for k, s in catalog.items() if s.pi > 0})
    w = -F.log("pi") if weight == "neglog" else -F.log("pi") + F.log1p(-F.col("pi"))
    packed = rows.agg(F.collect_list(F.struct(F.col("key").alias("k"), F.col("items").alias("s"), (w + 0.0).alias("w"), F.col("support").alias("n"))).alias("_sets"))
    usable = F.filter("_sets", lambda s: F.size(F.array_except(s["s"], F.col("items"))) == 0)
    met = baskets.crossJoin(F.broadcast(packed)).withColumn("_use", usable).drop("_sets")

    def step(state, _):
        left = state["left"]
        met = F.transform(F.col("_use"), lambda s: F.struct(F.size(F.array_intersect(s["s"], left)).alias("new"), s.alias("set")))
        ranked = F.transform(
            F.filter(met, lambda x: x["new"] > 0),
            lambda x: F.struct(
                (F.round(x["set"]["w"] / x["new"], 9) + 0.0).alias("ratio"), (-x["new"]).alias("new"), (-x["set"]["n"]).alias("n"), x["set"]["k"].alias("k"), x["set"]["s"].alias("s"), x["set"]["w"].alias("w")
            ),
        )
        best = F.array_min(ranked)
        return F.when((F.size(left) == 0) | best.isNull(), state).otherwise(
            F.struct(F.array_except(left, best["s"]).alias("left"), F.array_append(state["cover"], best["k"]).alias("cover"), (state["cost"] + best["w"]).alias("cost"))
        )

    start = F.struct(F.col("items").alias("left"), F.array().cast("array<string>").alias("cover"), F.lit(0.0).alias("cost"))
    steps = F.when(F.size("items") > 0, F.sequence(F.lit(1), F.size("items"))).otherwise(F.array().cast("array<int>"))
    # A generator of one row keeps the optimiser from writing the fold out for each of its three results.
    done = met.select(*baskets.columns, F.inline(F.array(F.aggregate(steps, start, step))).alias("_left", "_cover", "_cost"))
    whole = F.size("_left") == 0
    return done.select(*baskets.columns, F.when(whole, F.col("_cover")).alias("cover"), F.when(whole, F.col("_cost")).alias("cost"))


def usage(covered: DataFrame, weight: str | None = None) -> DataFrame:
    """(key, usage): in how many baskets a set is used; partial counts are added before the shuffle."""
    w = F.col(weight) if weight else F.lit(1)
    return covered.select(F.explode("cover").alias("key"), w.alias("w")).groupBy("key").agg(F.sum("w").alias("usage"))


def applicable(baskets: DataFrame, catalog: Catalog) -> DataFrame:
    """(tid, key) of the sets that each basket contains, by anchor join."""
    sets = to_df(baskets.sparkSession, catalog).select("key", F.col("items").alias("set"), F.element_at("items", -1).alias("anchor"))
    wide = baskets.select("tid", "items", F.explode("items").alias("anchor"))
    return wide.join(sets, "anchor").where(F.size(F.array_except("set", "items")) == 0).select("tid", "key")


def refresh(previous: DataFrame, baskets: DataFrame, catalog: Catalog, changed: set[str], **options) -> DataFrame:
    """Covers after some sets changed: only baskets that contain one of them are covered again."""
    touched = applicable(baskets, {k: s for k, s in catalog.items() if k in changed}).select("tid").distinct()
    again = cover(baskets.join(touched, "tid", "left_semi"), catalog, **options)
    return previous.join(touched, "tid", "left_anti").select(again.columns).unionByName(again)
