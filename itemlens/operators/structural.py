"""One step of structural EM: the first candidate, by support, that raises the profit.

Adding a set changes only the baskets that contain it.  A candidate whose items are in no other
set than their singletons takes the place of those in each of them, and nothing else moves: its gain
follows from its support alone, without a pass.  All others are scored in batches, one pass for
each: what a candidate touches of a basket is covered with the catalog and once more with the
candidate, at probability 1, and the differences in usage are added up.
With probabilities at usage over m the profit needs no further pass.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .candidates import Candidate
from .catalog import Catalog, Itemset, plain, unplain
from .cover import Index
from .em import FRAGMENTS, components
from .held import Held
from .model import entropy, profit

FIRST_BATCH, LARGEST_BATCH = 64, 1024
#: Parts of baskets that a task keeps before it covers them.
LARGEST_FOLD = 200_000


@dataclass
class Step:
    accepted: Candidate | None
    catalog: Catalog
    profit: float
    tried: int
    passes: int
    rejected: set[str] = field(default_factory=set)


def deltas(compressed: DataFrame, catalog: Catalog, batch: list[Candidate], weight: str = "neglog") -> dict[str, dict[str, int]]:
    """For each candidate, how the usage of each set changes if it is forced in.  Sums are folded in each partition first.

    A candidate moves nothing but the items of the components that it touches, so equal parts of
    baskets are covered once.
    """
    spark = compressed.sparkSession
    several = [s for s in catalog.values() if len(s.items) > 1 and s.pi > 0]
    single = {s.items[0]: s for s in catalog.values() if len(s.items) == 1 and s.pi > 0}
    of = components([s.items for s in several])
    touched = {c.key: frozenset(of[i] for i in c.items if i in of) for c in batch}
    near = frozenset().union(*touched.values())
    needed = {i for c in batch for i in c.items} | {i for i, name in of.items() if name in near}
    sets = plain([*several, *(single[i] for i in needed if i in single)])
    shared = spark.sparkContext.broadcast((sets, [(c.items, 1.0, c.support) for c in batch], frozenset(single), of, touched))

    def run(batches):
        sets, new, singles, of, touched = shared.value
        sets, new = unplain(sets), unplain(new)
        index, waiting = Index([*sets, *new], weight), Index(new)
        old, own = Index(sets, weight), {s.key: frozenset(s.items) for s in new}
        sums: dict[tuple[str, str], int] = {}
        parts: dict[tuple[str, tuple[str, ...]], int] = {}

        def fold() -> None:
            known: dict[tuple[str, ...], tuple] = {}
            for (k, part), mult in parts.items():
                basket = frozenset(part)
                if part not in known:
                    usable = old.applicable(basket)
                    known[part] = usable, old.lazy(basket, usable)
                usable, before = known[part]
                after = index.lazy(basket, [*usable, k], k)
                if before is None or after is None:
                    continue
                for used, sign in ((after, mult), (before, -mult)):
                    for s in used:
                        sums[k, s] = sums.get((k, s), 0) + sign
            parts.clear()

        for b in batches:
            for items, mult in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                basket = frozenset(items)
                mine = waiting.applicable(basket)
                if not mine:
                    continue
                bare = basket - singles
                if bare and not bare.issubset({i for k in old.applicable(basket) for i in old.sets[k][0]}):
                    continue  # what cannot be covered uses nothing
                for k in mine:
                    part = k, tuple(i for i in items if i in own[k] or of.get(i) in touched[k])
                    parts[part] = parts.get(part, 0) + mult
            if len(parts) > LARGEST_FOLD:
                fold()
        fold()
        rows = [(k, s, n) for (k, s), n in sums.items() if n]
        if rows:
            k, s, n = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(k), pa.array(s), pa.array(n, pa.int64())], ["cand", "key", "delta"])

    parts = compressed.select("items", "mult").mapInArrow(run, "cand string, key string, delta long")
    out: dict[str, dict[str, int]] = {c.key: {} for c in batch}
    for r in parts.groupBy("cand", "key").agg(F.sum("delta").alias("delta")).collect():
        if r["delta"]:
            out[r["cand"]][r["key"]] = r["delta"]
    shared.unpersist()
    return out


def held_deltas(near: Held, catalog: Catalog, c: Candidate, weight: str = "neglog") -> dict[str, int] | None:
    """The same for one candidate over baskets that the driver holds; None if too many distinct parts are to be covered."""
    several = [s for s in catalog.values() if len(s.items) > 1 and s.pi > 0]
    single = {s.items[0]: s for s in catalog.values() if len(s.items) == 1 and s.pi > 0}
    of = components([s.items for s in several])
    touched = {of[i] for i in c.items if i in of}
    needed = {*c.items} | {i for i, name in of.items() if name in touched}
    sets, new = [*several, *(single[i] for i in needed if i in single)], Itemset.of(c.items, 1.0, 0, c.support)
    index, old = Index([*sets, new], weight), Index(sets, weight)
    rows = near.having(c.items)
    for i in near.items:
        if i not in single:
            # What cannot be covered uses nothing: an item without a singleton needs a set that the basket holds.
            covered = ~near.having((i,))
            for s in several:
                if i in s.items:
                    covered |= near.having(s.items)
            rows &= covered
    words, mult = near.parts(needed, rows)
    if len(mult) > FRAGMENTS:
        return None
    sums: dict[str, int] = {}
    for part, n in zip(near.names(words), mult.tolist(), strict=True):
        basket = frozenset(part)
        usable = old.applicable(basket)
        before, after = old.lazy(basket, usable), index.lazy(basket, [*usable, new.key], new.key)
        if before is None or after is None:
            continue
        for used, sign in ((after, n), (before, -n)):
            for k in used:
                sums[k] = sums.get(k, 0) + sign
    return {k: d for k, d in sums.items() if d}


def replaced(c: Candidate) -> dict[str, int]:
    """The change in usage of a candidate whose items are in no other set than their singletons."""
    return {c.key: c.support} | {i: -c.support for i in c.items}


def step(
    compressed: DataFrame, catalog: Catalog, m: int, queue: list[Candidate], batch: int | None = None, weight: str = "neglog", prior: str = "none", items: int = 0, iteration: int = 0, base: float | None = None,
    near: Held | None = None,
) -> Step:
    """Try the queue in order; the first improving candidate joins the catalog with all probabilities re-estimated.

    The catalog's usages must belong to its probabilities.  Batches double as long as none improves,
    so the work wasted on candidates behind the accepted one stays bounded.  Where the driver holds
    the baskets (near), each candidate is scored at its turn.
    """
    usages = {k: s.usage for k, s in catalog.items()}
    now = profit(usages, m, prior, items)
    before = now if base is None else base
    charge = math.log(max(2, items)) / m if prior == "size" and m else 0.0

    def gain(change: dict[str, int]) -> float:
        out = now - before
        for k, d in change.items():
            old = usages.get(k, 0)
            out += entropy(old / m) - entropy((old + d) / m)
            if charge and "|" in k:
                out -= ((old + d > 0) - (old > 0)) * (k.count("|") + 1) * charge
        return out

    def taken(at: int, change: dict[str, int], passes: int) -> Step:
        c = queue[at]
        new = {k: s.with_(usage=s.usage + change.get(k, 0), pi=(s.usage + change.get(k, 0)) / m) for k, s in catalog.items()}
        used = change.get(c.key, 0)
        new[c.key] = Itemset.of(c.items, used / m, used, c.support, iteration)
        return Step(c, new, before + gain(change), at + 1, passes, {x.key for x in queue[:at]})

    tied = {i for s in catalog.values() if len(s.items) > 1 and s.pi > 0 for i in s.items}
    free = (at for at, c in enumerate(queue) if tied.isdisjoint(c.items) and c.support and gain(replaced(c)) > 1e-12)
    first = next(free, len(queue))
    # Only those before the first improving one that needs no pass are left to try.
    todo = [at for at, c in enumerate(queue[:first]) if not tied.isdisjoint(c.items)]
    size, passes = batch or FIRST_BATCH, 0
    while todo:
        part, todo = todo[:size], todo[size:]
        found = None
        passes += 1
        for n, at in enumerate(part):
            change = held_deltas(near, catalog, queue[at], weight) if near and found is None else None
            if change is None:
                found = deltas(compressed, catalog, [queue[x] for x in part[n:]], weight) if found is None else found
                change = found[queue[at].key]
            if change and gain(change) > 1e-12:
                return taken(at, change, passes)
        size = batch or min(LARGEST_BATCH, 2 * size)
    if first < len(queue):
        return taken(first, replaced(queue[first]), passes)
    return Step(None, catalog, before, len(queue), passes, {c.key for c in queue})


#: Up to so many items, the pairs are counted by name; beyond, by the items' 64-bit hashes.
NAMED_ITEMS = 10_000


def first_step_gains(compressed: DataFrame, m: int, items: int | None = None) -> DataFrame:
    """(a, b, support, gain) of all pairs of items for the singleton model: closed form, no covers.

    items: about how many items there are, if known; it only decides how the pairs are counted.
    """
    from ..functions.expressions import binary_entropy

    counts = compressed.select(F.explode("items").alias("item"), "mult").groupBy(F.xxhash64("item").alias("h")).agg(F.sum("mult").alias("n"), F.count("*").alias("baskets"))
    items = counts.limit(NAMED_ITEMS + 1).count() if items is None else items
    both = _named_pairs(compressed) if items <= NAMED_ITEMS else _hashed_pairs(compressed, counts)
    h = lambda n: binary_entropy(n / F.lit(float(m)))
    gain = h(F.col("na")) + h(F.col("nb")) - h(F.col("support")) - h(F.col("na") - F.col("support")) - h(F.col("nb") - F.col("support"))
    return both.select("a", "b", "support", gain.alias("gain"))


def _named_pairs(compressed: DataFrame) -> DataFrame:
    """(a, b, support, na, nb) of all pairs that meet, with the supports of their items."""
    from .candidates import pair_supports

    counts = compressed.select(F.explode("items").alias("item"), "mult").groupBy("item").agg(F.sum("mult").alias("n"))
    pairs = pair_supports(compressed)
    return pairs.join(counts.select(F.col("item").alias("a"), F.col("n").alias("na")), "a").join(counts.select(F.col("item").alias("b"), F.col("n").alias("nb")), "b")


def _hashed_pairs(compressed: DataFrame, counts: DataFrame) -> DataFrame:
    """The same for many or long items, such as lines: no pair is shuffled by name.

    counts: (h, n, baskets) by the items' hashes.  A pair with an item of one distinct basket meets
    there alone and is written from it.  All others are counted by hash and written from the basket
    of smallest hash that holds them.
    """
    named = compressed.withColumn("basket", F.xxhash64("items"))
    places = named.select("basket", "mult", F.posexplode("items").alias("at", "item")).select("basket", "mult", "at", F.xxhash64("item").alias("h"))
    shared = places.join(counts.where("baskets > 1").select("h", "n"), "h")
    known = shared.groupBy("basket", "mult").agg(F.sort_array(F.collect_list(F.struct("at", "h", "n"))).alias("known"))
    left = known.select("basket", "mult", "known", F.posexplode("known").alias("i", "x"))
    met = left.select("basket", "mult", F.col("x.h").alias("ha"), F.explode(F.slice("known", F.col("i") + 2, F.size("known"))).alias("y"))
    pairs = met.groupBy("ha", F.col("y.h").alias("hb")).agg(F.sum("mult").alias("support"), F.min("basket").alias("basket"))
    due = pairs.groupBy("basket").agg(F.collect_list(F.struct("ha", "hb", "support")).alias("due"))
    whole = named.join(known.drop("mult").join(due, "basket", "left"), "basket", "left")
    by_place = F.map_from_entries(F.transform(F.coalesce("known", F.array().cast("array<struct<at:int,h:bigint,n:bigint>>")), lambda k: F.struct(k["at"], k["n"])))
    ones = whole.withColumn("of", by_place).select("mult", F.transform("items", lambda x, i: F.named_struct(F.lit("item"), x, F.lit("n"), F.try_element_at("of", i))).alias("all"))
    ones = ones.select("mult", "all", F.posexplode("all").alias("i", "x")).select("mult", "x", F.explode(F.slice("all", F.col("i") + 2, F.size("all"))).alias("y"))
    ones = ones.where("x.n is null or y.n is null").select(
        F.col("x.item").alias("a"), F.col("y.item").alias("b"), F.col("mult").alias("support"), F.coalesce("x.n", "mult").alias("na"), F.coalesce("y.n", "mult").alias("nb")
    )
    of = F.map_from_entries(F.transform("known", lambda k: F.struct(k["h"], F.named_struct(F.lit("item"), F.col("items")[k["at"]], F.lit("n"), k["n"]))))
    several = whole.where("due is not null").select(of.alias("of"), F.explode("due").alias("p"))
    several = several.select(F.col("of")[F.col("p.ha")].alias("x"), F.col("of")[F.col("p.hb")].alias("y"), F.col("p.support").alias("support"))
    return ones.unionByName(several.select(F.col("x.item").alias("a"), F.col("y.item").alias("b"), "support", F.col("x.n").alias("na"), F.col("y.n").alias("nb")))
