"""Hard expectation maximisation: cover all baskets, re-estimate all probabilities, repeat."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import cover as covering
from .catalog import Catalog, prune
from .held import Held
from .model import profit

#: Kernels that cover each fragment of a basket as they cover it within the whole.
GREEDY = ("auto", "native", "arrow", "greedy", "lazy_heap")
#: Up to so many distinct fragments, the driver holds them between rounds; beyond, they stay where they are.
FRAGMENTS = 20_000


@dataclass
class EMResult:
    catalog: Catalog
    profit: float
    trace: list[dict] = field(default_factory=list)


def e_step(compressed: DataFrame, catalog: Catalog, weight: str = "neglog", kernel: str = "auto") -> dict[str, int]:
    """Usage of each set over weighted distinct baskets (items, mult).  One row per set reaches the driver."""
    covered = covering.cover(compressed, catalog, weight, kernel)
    return {r["key"]: r["usage"] for r in covering.usage(covered, "mult").toLocalIterator()}


def components(sets) -> dict[str, str]:
    """The items of sets of several items (given by their items), each with the name of its component: sets that share an item belong together."""
    parent: dict[str, str] = {}

    def root(x: str) -> str:
        while parent.setdefault(x, x) != x:
            parent[x] = parent[parent[x]]
            x = parent[x]
        return x

    for items in sets:
        for i in items[1:]:
            parent[root(i)] = root(items[0])
    return {i: root(i) for i in list(parent)}


def fragments(compressed: DataFrame, of: dict[str, str]) -> DataFrame:
    """(items, mult): the distinct parts of baskets within one component each.  Items of no component are left out."""
    shared = compressed.sparkSession.sparkContext.broadcast(of)

    def run(batches):
        known, sums = shared.value, {}
        for b in batches:
            for items, mult in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                parts: dict[str, list[str]] = {}
                for i in items:
                    if (c := known.get(i)) is not None:
                        parts.setdefault(c, []).append(i)
                for part in parts.values():
                    key = tuple(part)
                    sums[key] = sums.get(key, 0) + mult
        if sums:
            yield pa.RecordBatch.from_arrays([pa.array(list(map(list, sums)), pa.list_(pa.string())), pa.array(list(sums.values()), pa.int64())], ["items", "mult"])

    return compressed.select("items", "mult").mapInArrow(run, "items array<string>, mult long").groupBy("items").agg(F.sum("mult").alias("mult"))


class Rounds:
    """E-steps of one catalog whose probabilities move.

    A greedy cover chooses within each component of the sets as if the rest of the basket were not
    there, and items of no component by their singletons.  So the distinct fragments are covered in
    place of the baskets, and items in no set but their own are used as often as they occur.
    """

    def __init__(self, compressed: DataFrame, catalog: Catalog, weight: str, kernel: str, supports: dict[str, int] | None, near: Held | None = None):
        self.compressed, self.weight, self.kernel = compressed, weight, kernel
        self.parts: list[tuple[frozenset, int]] | None = None
        self.rows: DataFrame | None = None
        if supports is None or kernel not in GREEDY:
            return
        self.of = of = components([s.items for s in catalog.values() if len(s.items) > 1])
        self.free = {i: n for i, n in supports.items() if i not in of}
        if any(i not in catalog or catalog[i].pi <= 0 for i in self.free):
            return
        if near is not None and (parts := self._parts(near)) is not None:
            self.parts = parts
            return
        self.rows = fragments(compressed, of).persist()
        if self.rows.count() <= FRAGMENTS:
            self.parts = [(frozenset(r["items"]), r["mult"]) for r in self.rows.collect()]

    def _parts(self, near: Held) -> list[tuple[frozenset, int]] | None:
        """The fragments of baskets that the driver holds; None if there are too many."""
        out: list[tuple[frozenset, int]] = []
        for name in sorted(set(self.of.values())):
            words, mult = near.parts([i for i, c in self.of.items() if c == name])
            if len(out) + len(mult) > FRAGMENTS:
                return None
            out += [(frozenset(part), n) for part, n in zip(near.names(words), mult.tolist(), strict=True) if part]
        return out

    def usage(self, catalog: Catalog) -> dict[str, int]:
        if self.rows is None and self.parts is None:
            return e_step(self.compressed, catalog, self.weight, self.kernel)
        bound = {k: s for k, s in catalog.items() if s.items[0] in self.of}
        if self.parts is not None:
            index, used = covering.Index(bound.values(), self.weight), {}
            covers = ((index.cover("lazy_heap", part), mult) for part, mult in self.parts)
        else:
            covered = covering.cover(self.rows, bound, self.weight, self.kernel).persist()
            whole = covered.where("cover is null").isEmpty()
            used = {r["key"]: r["usage"] for r in covering.usage(covered, "mult").toLocalIterator()} if whole else {}
            covered.unpersist()
            covers = () if whole else [(None, 0)]
        for got, mult in covers:
            if got is None:
                # A basket that cannot be covered uses nothing at all: only whole baskets tell.
                self.close()
                return self.usage(catalog)
            for k in got:
                used[k] = used.get(k, 0) + mult
        return used | self.free

    def close(self) -> None:
        if self.rows is not None:
            self.rows.unpersist()
        self.rows = self.parts = None


def hard_em(
    compressed: DataFrame, catalog: Catalog, m: int, eps: float = 1e-6, max_iter: int = 50, norm: str = "l2", weight: str = "neglog", kernel: str = "auto",
    keep_singletons: bool = False, floor: float | None = None, start: float | None = None, supports: dict[str, int] | None = None,
    near: Held | None = None,
) -> EMResult:
    """Iterate until the probabilities move by eps or less, then drop the sets of probability 0.

    Greedy covers need not improve steadily, so the best state by profit is returned: the given
    one too, if its profit `start` is known and no round comes up to it.

    supports: those of all items, if known; the baskets are then read once for all rounds.  near: the
    same baskets as the driver holds them, if it does.
    """
    best, trace, given = None, [], catalog
    rounds = Rounds(compressed, catalog, weight, kernel, supports, near)
    for k in range(max_iter):
        used = rounds.usage(catalog)
        moved = [abs(used.get(key, 0) / m - s.pi) for key, s in catalog.items()]
        change = max(moved, default=0.0) if norm == "max" else math.sqrt(sum(x * x for x in moved))
        catalog = {key: s.with_(pi=used.get(key, 0) / m, usage=used.get(key, 0)) for key, s in catalog.items()}
        now = profit(used, m)
        trace.append({"iter": k, "profit": now, "change": change})
        if best is None or now >= best[0]:
            best = (now, catalog)
        if change <= eps:
            break
    rounds.close()
    if start is not None and (best is None or best[0] < start - 1e-12):
        best = (start, given)
    return EMResult(prune(best[1], keep_singletons, floor), best[0], trace)
