"""The full miner: structural steps and hard EM in turn, from singletons on."""

from __future__ import annotations

import json
import time
from dataclasses import dataclass, field, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import candidates, catalog as cat, em, structural
from .catalog import Catalog
from .encode import compress
from .held import Held, held
from .model import profit


@dataclass
class MinerResult:
    catalog: Catalog
    m: int
    profit: float
    rejected: set[str] = field(default_factory=set)
    trace: list[dict] = field(default_factory=list)
    converged: bool = False

    def to_df(self, spark: SparkSession) -> DataFrame:
        return cat.to_df(spark, self.catalog)


@dataclass
class Ready:
    """Baskets that several methods mine in turn: what `prepared` gives, and the distinct baskets if the driver can hold them."""

    baskets: DataFrame
    compressed: DataFrame
    m: int
    supports: dict[str, int]
    near: Held | None
    #: Frequent sets that have been listed, by least support and number.
    listed: dict[tuple[int, int], list[tuple[tuple[str, ...], int]]] = field(default_factory=dict)
    #: Closed sets that have been listed, by least support; None for too many to list.
    closed: dict[int, list[tuple[tuple[str, ...], int]] | None] = field(default_factory=dict)
    parts: dict[int, Held | None] = field(default_factory=dict)

    def common(self, least: int) -> Held | None:
        """The parts of the baskets within the items of `least` or more, which are enough for frequent sets; None if the driver cannot hold them."""
        if self.near:
            return self.near
        if least not in self.parts:
            found = held(self.compressed, [i for i, n in self.supports.items() if n >= least])
            self.parts[least] = found and found.within(found.items)
        return self.parts[least]

    @property
    def sparkSession(self) -> SparkSession:  # noqa: N802
        return self.baskets.sparkSession


def ready(baskets: DataFrame | Ready) -> Ready:
    if isinstance(baskets, Ready):
        return baskets
    compressed, m, supports = prepared(baskets)
    return Ready(baskets, compressed, m, supports, held(compressed, supports))


def prepared(baskets: DataFrame) -> tuple[DataFrame, int, dict[str, int]]:
    """Weighted distinct baskets (kept for all passes), m, and the items' supports."""
    compressed = compress(baskets).persist()
    m = compressed.agg(F.sum("mult")).first()[0] or 0
    counts = compressed.select(F.explode("items").alias("i"), "mult").groupBy("i").agg(F.sum("mult").alias("n"))
    return compressed, m, {r["i"]: r["n"] for r in counts.toLocalIterator()}


def mine(
    baskets: DataFrame | Ready, max_iter: int = 1000, queue_size: int = 100_000, em_every: int = 1, eps: float = 1e-6, em_iter: int = 20, pair_order: str = "lexicographic",
    cap: str = "first", min_support: int = 1, prior: str = "none", prune: str | None = None, batch: int | None = None, weight: str = "neglog", kernel: str = "lazy_heap",
    generator: str = "unions", keep_singletons: bool = False, resume: MinerResult | None = None, save_to: str | None = None,
) -> MinerResult:
    """Mine baskets (tid, items).  One iteration accepts one itemset at most.

    It ends after max_iter, or when a queue that held all unions holds none that improves; a queue
    that was cut at queue_size and holds none is followed by one of the unions beyond it.

    em_every: how many accepted sets pass between rounds of hard EM.  generator: "unions" of known
    sets, or "apriori".  A state saved to `save_to` after each EM round can be resumed.
    """
    given = ready(baskets)
    compressed, m, supports, near, spark = given.compressed, given.m, given.supports, given.near, given.sparkSession
    state = replace(resume, rejected=set(resume.rejected), trace=list(resume.trace)) if resume else MinerResult(cat.from_support(sorted(supports.items()), m), m, 0.0)
    if not resume:
        state.profit = profit({k: s.usage for k, s in state.catalog.items()}, m)
    cache: dict[str, int] = {}
    queue: list[candidates.Candidate] | None = None
    since = 0
    try:
        for iteration in range(len(state.trace), max_iter):
            began, before = time.time(), len(cache)
            if generator == "apriori":
                if queue is None:
                    queue = candidates.apriori_queue(compressed, supports, max(1, min_support), queue_size)
                usable = [c for c in queue if c.key not in state.catalog and c.key not in state.rejected]
            else:
                usable = candidates.build_queue(compressed, state.catalog, state.rejected, supports, queue_size, pair_order, cap, min_support, cache, prune, m, near=near)
            counted, possible = len(cache), len(state.catalog) * (len(state.catalog) - 1) // 2
            cut = generator != "apriori" and possible > queue_size and bool(usable or counted > before)
            done = structural.step(compressed, state.catalog, m, usable, batch, weight, prior, len(supports), iteration, near=near)
            state.rejected |= done.rejected
            if done.accepted is not None:
                state.catalog, state.profit, since = done.catalog, done.profit, since + 1
            last = done.accepted is None and not cut or iteration == max_iter - 1
            if since and (since >= em_every or last):
                fitted = em.hard_em(compressed, state.catalog, m, eps, em_iter, weight=weight, kernel=kernel, keep_singletons=keep_singletons, start=state.profit if prior == "none" else None, supports=supports, near=near)
                state.catalog, state.profit, since = fitted.catalog, fitted.profit, 0
                if save_to:
                    save(spark, state, save_to)
            state.trace.append(
                {"iter": iteration, "secs": time.time() - began, "profit": state.profit, "tried": done.tried, "accepted": done.accepted.key if done.accepted else None, "passes": done.passes}
            )
            if done.accepted is None and not cut:
                state.converged = True
                break
    finally:
        if given is not baskets:
            compressed.unpersist()
    return state


def save(spark: SparkSession, state: MinerResult, path: str) -> None:
    state.to_df(spark).write.mode("overwrite").parquet(f"{path}/catalog")
    spark.createDataFrame([(k,) for k in sorted(state.rejected)], "key string").write.mode("overwrite").parquet(f"{path}/rejected")
    spark.createDataFrame([(json.dumps(state.trace), state.m, state.profit)], "trace string, m long, profit double").write.mode("overwrite").parquet(f"{path}/state")


def load(spark: SparkSession, path: str) -> MinerResult:
    row = spark.read.parquet(f"{path}/state").first()
    rejected = {r["key"] for r in spark.read.parquet(f"{path}/rejected").toLocalIterator()}
    return MinerResult(cat.from_df(spark.read.parquet(f"{path}/catalog")), row["m"], row["profit"], rejected, json.loads(row["trace"]))


def trace_df(spark: SparkSession, state: MinerResult) -> DataFrame:
    rows = [(t["iter"], t["secs"], t["profit"], t["tried"], t["accepted"], t["passes"]) for t in state.trace]
    return spark.createDataFrame(rows, "iter int, secs double, profit double, tried int, accepted string, passes int")
