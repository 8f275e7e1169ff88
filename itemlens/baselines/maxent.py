"""A maximum-entropy summary: a set in the model counts in every basket that contains it.

Items joined by a set of several items form a block; blocks are independent.  Iterative scaling
enumerates the item patterns of a block, so blocks are limited to LARGEST_BLOCK items.
"""

from __future__ import annotations

import math
import warnings
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.candidates import counted, pair_supports
from ..operators.miner import Ready, prepared, ready

LARGEST_BLOCK = 12


@dataclass
class Block:
    items: tuple[str, ...]
    sets: list[tuple[str, ...]]
    log_weights: np.ndarray = field(default=None)
    log_norm: float = 0.0
    patterns: np.ndarray = field(default=None)

    def fit(self, frequency: dict[str, float], steps: int = 200, eps: float = 1e-9) -> Block:
        """Scale each set's weight until its expected frequency is the observed one."""
        n = len(self.items)
        if n > LARGEST_BLOCK:
            raise ValueError(f"a block of {n} items; the limit is {LARGEST_BLOCK}")
        masks = np.arange(1 << n)
        bit = {i: 1 << k for k, i in enumerate(self.items)}
        self.patterns = np.stack([(masks & (m := sum(bit[i] for i in s))) == m for s in self.sets])
        target = np.clip([frequency["|".join(s)] for s in self.sets], 1e-12, 1 - 1e-12)
        logs = np.zeros(len(self.sets))
        for _ in range(steps):
            worst = 0.0
            for k in range(len(self.sets)):
                p = self._p(logs)
                e = float(np.clip(p[self.patterns[k]].sum(), 1e-12, 1 - 1e-12))
                step = math.log(target[k] / e) - math.log((1 - target[k]) / (1 - e))
                logs[k] += step
                worst = max(worst, abs(target[k] - e))
            if worst < eps:
                break
        self.log_weights = logs
        self.log_norm = float(np.logaddexp.reduce((logs[:, None] * self.patterns).sum(0)))
        return self

    def _p(self, logs: np.ndarray) -> np.ndarray:
        score = (logs[:, None] * self.patterns).sum(0)
        p = np.exp(score - score.max())
        return p / p.sum()

    def expected(self, items: frozenset) -> float:
        own = [k for k, i in enumerate(self.items) if i in items]
        mask = sum(1 << k for k in own)
        return float(self._p(self.log_weights)[(np.arange(1 << len(self.items)) & mask) == mask].sum())


@dataclass
class MaxEnt:
    blocks: list[Block]
    frequency: dict[str, float]
    m: int
    #: Sets that mining would have tried next, had their blocks not been too large.
    refused: list[tuple[str, ...]] = field(default_factory=list)

    def __post_init__(self) -> None:
        self.block_of = {i: n for n, b in enumerate(self.blocks) for i in b.items}

    def log_norm(self) -> float:
        return -sum(b.log_norm for b in self.blocks)

    def weights(self) -> list[tuple[tuple[str, ...], float]]:
        return [(s, float(w)) for b in self.blocks for s, w in zip(b.sets, b.log_weights, strict=True)]

    def mean_loglik(self) -> float:
        """Per basket: sets count as often as observed, so supports are enough."""
        return self.log_norm() + sum(w * self.frequency["|".join(s)] for s, w in self.weights())

    def score(self) -> float:
        """Negative log-likelihood of the database plus half of ln m for each set."""
        return -self.m * self.mean_loglik() + 0.5 * len(self.weights()) * math.log(max(2, self.m))

    def expected(self, items: frozenset) -> float:
        out = 1.0
        for n in sorted({self.block_of[i] for i in items if i in self.block_of}):
            out *= self.blocks[n].expected(items.intersection(self.blocks[n].items))
        return out

    def joined_by(self, items: tuple[str, ...]) -> list[int]:
        """The blocks that become one if a set of these items is added."""
        return sorted({self.block_of[i] for i in items})

    def plus(self, items: tuple[str, ...], frequency: float) -> MaxEnt:
        """The model with one more set; only its block is fitted."""
        own = self.joined_by(items)
        known = {**self.frequency, "|".join(items): frequency}
        sets = [s for n in own for s in self.blocks[n].sets] + [items]
        made = Block(tuple(sorted({i for s in sets for i in s})), sets).fit(known)
        return MaxEnt([*(b for n, b in enumerate(self.blocks) if n not in own), made], known, self.m, self.refused)


def _blocks(sets: list[tuple[str, ...]]) -> list[Block]:
    parent: dict[str, str] = {}

    def root(x: str) -> str:
        while parent.setdefault(x, x) != x:
            x = parent[x]
        return x

    for s in sets:
        for i in s[1:]:
            parent[root(i)] = root(s[0])
        root(s[0])
    groups: dict[str, list] = {}
    for s in sets:
        groups.setdefault(root(s[0]), []).append(s)
    return [Block(tuple(sorted({i for s in g for i in s})), g) for g in groups.values()]


def fit(baskets: DataFrame, itemsets: list[tuple[str, ...]]) -> MaxEnt:
    """The model of all singletons and the given itemsets."""
    compressed, m, supports = prepared(baskets)
    multi = [tuple(sorted(s)) for s in itemsets if len(s) > 1]
    got = counted(compressed, multi, supports)
    compressed.unpersist()
    frequency = {i: n / m for i, n in supports.items()} | {"|".join(s): got.get("|".join(s), 0) / m for s in multi}
    return MaxEnt([b.fit(frequency) for b in _blocks([(i,) for i in sorted(supports)] + multi)], frequency, m)


def logp(baskets: DataFrame, model: MaxEnt) -> DataFrame:
    """(tid, logp): the norm and the weight of every contained set."""
    spark = baskets.sparkSession
    sets = spark.createDataFrame([(list(s), s[0], w) for s, w in model.weights()], "set array<string>, anchor string, w double")
    wide = baskets.select("tid", "items", F.explode_outer("items").alias("anchor"))
    met = wide.join(F.broadcast(sets), "anchor", "left").withColumn("w", F.when(F.size(F.array_except("set", "items")) == 0, F.col("w")).otherwise(0.0))
    return met.groupBy("tid").agg((F.sum("w") + F.lit(model.log_norm())).alias("logp"))


def mine(baskets: DataFrame | Ready, k: int = 50, min_support: float = 0.0575, pool: int = 20_000) -> tuple[MaxEnt, list[tuple[str, ...]]]:
    """Grow the summary by the union whose observed frequency diverges most from the expected one, while the score falls.

    All unions are counted, `pool` of them at once.  Unions whose block would have more than
    LARGEST_BLOCK items are passed over; the model lists those in `refused`, and a warning names
    their number.
    """
    given = ready(baskets)
    compressed, m, supports = given.compressed, given.m, given.supports
    frequency = {i: n / m for i, n in supports.items()}
    listed: list[tuple[str, ...]] = []
    least = max(1, math.ceil(min_support * m))
    near = given.common(least)
    try:
        model = MaxEnt([b.fit(frequency) for b in _blocks([(i,) for i in sorted(supports)])], frequency, m)
        frequent = [(i,) for i, n in sorted(supports.items(), key=lambda x: (-x[1], x[0])) if n >= least]
        refused: dict[str, tuple[str, ...]] = {}
        # Supports of the unions that are frequent, and the keys of all that have been counted.
        known: dict[tuple[str, ...], int] = {}
        items = F.array(*(F.lit(i) for (i,) in frequent)).cast("array<string>") if len(frequent) < 1000 else None
        common = compressed if items is None else compressed.select(F.array_intersect("items", items).alias("items"), "mult")
        met = () if len(frequent) < 2 else near.pairs(least) if near else pair_supports(common, least).select("a", "b", "support").toLocalIterator()
        for a, b, n in met:
            known[tuple(sorted((a, b)))] = n
        gaps: dict[tuple[str, ...], float] = {}
        seen: set[tuple[str, ...]] = set()
        fresh: list[tuple[str, ...]] = []
        while len(listed) < k:
            # Pairs of items are known; a set that has joined makes new unions with all others.
            new = sorted({u for a in fresh for b in [*frequent, *listed] if len(u := tuple(sorted({*a, *b}))) > 2} - seen)
            for at in range(0, len(new), pool):
                part = new[at : at + pool]
                got = near.supports(part) if near else counted(compressed, part, supports)
                known.update({u: n for u in part if (n := got.get("|".join(u), 0)) >= least})
            seen.update(new)
            ranked = []
            for u, n in known.items():
                if (key := "|".join(u)) in model.frequency or key in refused:
                    continue
                if u not in gaps:
                    q, e = n / m, min(max(model.expected(frozenset(u)), 1e-12), 1 - 1e-12)
                    gaps[u] = q * math.log(q / e) + (1 - q) * math.log((1 - q) / (1 - e)) if q < 1 and abs(q - e) > 1e-9 else 0.0
                if gaps[u]:
                    ranked.append((-gaps[u], key, u))
            best = None
            for _, key, u in sorted(ranked):
                if sum(len(model.blocks[n].items) for n in model.joined_by(u)) <= LARGEST_BLOCK:
                    best = u
                    break
                refused[key] = u
            if best is None:
                break
            trial = model.plus(best, known[best] / m)
            if trial.score() >= model.score() - 1e-9:
                break
            model, fresh = trial, [best]
            listed.append(best)
            changed = set(model.blocks[-1].items)
            gaps = {u: g for u, g in gaps.items() if changed.isdisjoint(u)}
    finally:
        if given is not baskets:
            compressed.unpersist()
    model.refused = list(refused.values())
    if refused:
        warnings.warn(f"{len(refused)} sets were refused: their blocks would have more than {LARGEST_BLOCK} items", stacklevel=2)
    return model, listed
