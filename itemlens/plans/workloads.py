"""The experiment workloads, re-expressed on the given tables.

The given star schema is almost independent and the texts are invented, so published values of
redundancy and lists cannot be met; directions are compared.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines import codetable, frequent, maxent
from ..operators import cover, em, measures, miner, model, rank
from ..operators.catalog import Catalog, Itemset
from ..sources.baskets import SOURCES, source
from ..sources.tables import read

METHODS = ("cover", "maxent", "code_pairs", "code_candidates", "closed_chi2")
#: Options of sources that stand for the published data sets.
STAND_INS: dict[str, dict] = {"doc_words_en": {}, "page_words": {"max_vocab": 194}, "order_geo": {}, "order_parts": {}, "conv_words": {}}
MIN_SUPPORT = 0.0575
#: As many iterations as the method is described with; each mine ends sooner if no candidate improves.
ITERATIONS = 1000
#: Sources whose items are independent, or all in every basket; the last two only from sf0.01 up.
NULLS = ("order_regions", "order_brands", "order_tokens", "part_suppnations", "part_custnations", "cust_brands", "line_attrs", "userday_events", "vec_dims", "page_tags", "part_attrs", "user_props")


def stand_in(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return source(spark, sf_dir, name, **STAND_INS.get(name, {}))


def _keys(sets) -> list[tuple[str, list[str]]]:
    return [("|".join(sorted(s)), sorted(s)) for s in sets]


def listed(spark: SparkSession, baskets: DataFrame | miner.Ready, method: str, k: int = 50, max_iter: int = ITERATIONS, min_support: float = MIN_SUPPORT, queue_size: int = 100_000, kept: int | None = None) -> DataFrame:
    """(rank, itemset, items): the first k non-singletons of a method.

    kept: closed sets are ranked by chi-square among so many frequent sets of highest support, or else among all.
    """
    baskets = miner.ready(baskets)
    if method == "cover":
        top = rank.top_k(miner.mine(baskets, max_iter, queue_size).to_df(spark), k)
        return top.select("rank", "itemset", F.split("itemset", r"\|").alias("items"))
    if method == "closed_chi2":
        return frequent.chi2_list(baskets, min_support, k, kept).select("rank", "itemset", "items")
    if method == "maxent":
        sets = maxent.mine(baskets, k, min_support)[1]
    elif method == "code_pairs":
        sets = codetable.ranked(codetable.mine_pairs(baskets, max_iter), k)
    elif method == "code_candidates":
        sets = codetable.ranked(codetable.mine(baskets, frequent.all_closed(baskets, min_support)), k)
    else:
        raise ValueError(method)
    rows = [(n, key, items) for n, (key, items) in enumerate(_keys(sets), 1)]
    return spark.createDataFrame(rows, "rank int, itemset string, items array<string>")


def mine_all(spark: SparkSession, sf_dir: str, sources: tuple[str, ...] = tuple(STAND_INS), max_iter: int = ITERATIONS, queue_size: int = 100_000) -> DataFrame:
    """(source, items, baskets, n_nonsingleton, iterations, secs)"""
    rows = []
    for name in sources:
        began = time.time()
        found = miner.mine(stand_in(spark, sf_dir, name), max_iter, queue_size)
        items = len({i for s in found.catalog.values() for i in s.items})
        rows.append((name, items, found.m, sum(len(s.items) > 1 for s in found.catalog.values()), len(found.trace), time.time() - began))
    return spark.createDataFrame(rows, "source string, items long, baskets long, n_nonsingleton long, iterations int, secs double")


def self_recovery(spark: SparkSession, sf_dir: str, n: int = 10_000, seed: int = 42, min_support: float = MIN_SUPPORT, methods: tuple[str, ...] = METHODS, max_iter: int = 20, k: int = 50) -> DataFrame:
    """(method, recall, precision) at eleven levels, on baskets that a trained model generates."""
    known = trained(spark, sf_dir, max_iter)
    truth = spark.createDataFrame([(s.key,) for s in known.values() if len(s.items) > 1], "itemset string")
    made = miner.ready(model.generate(spark, known, n, seed).where(F.size("items") > 0).persist())
    out = None
    for method in methods:
        points = measures.eleven_point(measures.curve(listed(spark, made, method, k, max_iter, min_support), truth)).select(F.lit(method).alias("method"), "recall", "precision")
        out = points if out is None else out.unionByName(points)
    return out


def planted_catalog(kind: str = "disjoint") -> Catalog:
    """Known catalogs for recovery: disjoint, overlapping or rare sets, with noise items."""
    sets = {"disjoint": [("a", "b"), ("c", "d", "e"), ("f", "g")], "overlap": [("a", "b"), ("b", "c"), ("c", "d", "e")], "rare": [("a", "b"), ("c", "d"), ("e", "f", "g")]}[kind]
    p = {"disjoint": (0.3, 0.2, 0.25), "overlap": (0.3, 0.25, 0.2), "rare": (0.02, 0.03, 0.01)}[kind]
    made = [Itemset.of(s, q) for s, q in zip(sets, p, strict=True)] + [Itemset.of((x,), q) for x, q in zip("pqrs", (0.1, 0.2, 0.05, 0.15), strict=True)]
    return {s.key: s for s in made}


def trained(spark: SparkSession, sf_dir: str, max_iter: int = 20) -> Catalog:
    """The model whose baskets self-recovery and scaling generate."""
    return miner.mine(stand_in(spark, sf_dir, "order_geo"), max_iter).catalog


def scaling(spark: SparkSession, sizes: tuple[int, ...] = (10_000, 20_000, 40_000), iters: int = 3, kind: str = "disjoint", catalog: Catalog | None = None) -> DataFrame:
    """(m, secs_per_iter, slope, r2): time of an iteration against the number of baskets that `catalog`, or else a planted one, generates."""
    rows = []
    for n in sizes:
        made = model.generate(spark, catalog or planted_catalog(kind), n).where(F.size("items") > 0).persist()
        made.count()
        began = time.time()
        found = miner.mine(made, iters)
        rows.append((n, (time.time() - began) / max(1, len(found.trace))))
        made.unpersist()
    data = spark.createDataFrame(rows, "m long, secs_per_iter double")
    return data.crossJoin(data.agg(F.regr_slope("secs_per_iter", "m").alias("slope"), F.regr_r2("secs_per_iter", "m").alias("r2")))


def redundancy(spark: SparkSession, sf_dir: str, sources: tuple[str, ...] = ("order_geo",), k: int = 50, methods: tuple[str, ...] = METHODS, max_iter: int = ITERATIONS) -> DataFrame:
    """(source, method, iid, n_listed, short)"""
    out = None
    for name in sources:
        baskets = miner.ready(stand_in(spark, sf_dir, name).persist())
        for method in methods:
            found = listed(spark, baskets, method, k, max_iter, kept=frequent.CLOSED_KEPT)
            row = measures.iid(found).crossJoin(measures.shortfall(found, k)).select(F.lit(name).alias("source"), F.lit(method).alias("method"), "iid", "n_listed", "short")
            out = row if out is None else out.unionByName(row)
    return out


def top_lists(spark: SparkSession, sf_dir: str, name: str = "doc_words_en", k: int = 10, methods: tuple[str, ...] = ("cover", "maxent", "code_pairs"), max_iter: int = ITERATIONS) -> DataFrame:
    """(rank, one column for each method)"""
    from .report import side_by_side

    baskets = miner.ready(stand_in(spark, sf_dir, name).persist())
    return side_by_side({m: listed(spark, baskets, m, k, max_iter, kept=frequent.CLOSED_KEPT) for m in methods}, k)


def dated_baskets(spark: SparkSession, sf_dir: str, name: str = "order_geo") -> DataFrame:
    """Baskets with a time: orders by order date, user days by day."""
    if name == "userday_events":
        return source(spark, sf_dir, name).withColumn("ts", F.to_timestamp(F.substring_index("tid", "@", -1)))
    orders = read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("tid"), F.col("o_orderdate").alias("ts"))
    return SOURCES[name](spark, sf_dir).join(orders, "tid")


def mentions_over_time(spark: SparkSession, sf_dir: str, name: str = "order_geo", k: int = 6, unit: str = "day", max_iter: int = 10, methods: tuple[str, ...] = ("cover", "maxent")) -> DataFrame:
    """(day, method, itemset, n)"""
    baskets = dated_baskets(spark, sf_dir, name).persist()
    shared = miner.ready(baskets.select("tid", "items"))
    out = None
    for method in methods:
        top = listed(spark, shared, method, k, max_iter)
        daily = measures.mentions(baskets, top.select("itemset", "items"), unit).select("day", F.lit(method).alias("method"), "itemset", "n")
        out = daily if out is None else out.unionByName(daily)
    return out


def rank_compare(spark: SparkSession, sf_dir: str, name: str = "order_geo", methods: tuple[str, ...] = ("cover", "maxent"), k: int = 50, max_iter: int = ITERATIONS) -> DataFrame:
    """(itemset, one rank for each method)"""
    baskets = miner.ready(stand_in(spark, sf_dir, name).persist())
    out = None
    for method in methods:
        ranks = listed(spark, baskets, method, k, max_iter).select("itemset", F.col("rank").alias(f"rank_{method}"))
        out = ranks if out is None else out.join(ranks, "itemset", "full_outer")
    return out


def ablate(spark: SparkSession, sf_dir: str, name: str = "order_geo", max_iter: int = 6, grid: dict[str, dict] | None = None) -> DataFrame:
    """(option, profit, n_nonsingleton, secs) of cadences and candidate generators."""
    grid = grid or {
        "em_every=1": {}, "em_every=5": {"em_every": 5}, "em_every=20": {"em_every": 20}, "apriori": {"generator": "apriori", "min_support": 2},
        "chi2 pruning": {"prune": "chi2"}, "top support cap": {"cap": "top_support"}, "size prior": {"prior": "size"},
    }
    baskets = stand_in(spark, sf_dir, name).persist()
    rows = []
    for label, options in grid.items():
        began = time.time()
        found = miner.mine(baskets, max_iter, **options)
        rows.append((label, found.profit, sum(len(s.items) > 1 for s in found.catalog.values()), time.time() - began))
    return spark.createDataFrame(rows, "option string, profit double, n_nonsingleton long, secs double")


def cover_ablation(spark: SparkSession, sf_dir: str, name: str = "order_geo", max_iter: int = 8) -> DataFrame:
    """(kernel, weight, cost, ratio, profit): kernels and weights on one trained catalog, against exact covers."""
    baskets = stand_in(spark, sf_dir, name).persist()
    compressed, m, _ = miner.prepared(baskets)
    trained = miner.mine(baskets, max_iter).catalog
    singles = {i: Itemset.of((i,), 0.01, 0, 1) for s in trained.values() for i in s.items}
    catalog = singles | trained
    exact = None
    rows = []
    for kernel, weight in (("exact", "neglog"), ("greedy", "neglog"), ("lazy_heap", "neglog"), ("primal_dual", "neglog"), ("greedy", "logodds")):
        covered = cover.cover(compressed, catalog, weight, "arrow" if kernel == "greedy" else kernel)
        used = {r["key"]: r["usage"] for r in cover.usage(covered, "mult").toLocalIterator()}
        price = {k: cover.weight_of(s.pi) for k, s in catalog.items()}
        total = sum(price[k] * u for k, u in used.items())
        exact = total if exact is None else exact
        rows.append((kernel, weight, total / m, total / exact if exact else 1.0, model.profit(used, m)))
    return spark.createDataFrame(rows, "kernel string, weight string, cost double, ratio double, profit double")


def null_accepts(spark: SparkSession, sf_dir: str, sources: tuple[str, ...] = ("order_regions", "order_brands"), max_iter: int = 3, **options) -> DataFrame:
    """(source, accepted): sets that are mined where items are independent."""
    rows = [(n, sum(len(s.items) > 1 for s in miner.mine(stand_in(spark, sf_dir, n), max_iter, **options).catalog.values())) for n in sources]
    return spark.createDataFrame(rows, "source string, accepted long")


def e_step_throughput(spark: SparkSession, sf_dir: str, name: str = "order_geo", cores: int | None = None, max_iter: int = 10) -> DataFrame:
    """(source, baskets, secs, baskets_per_core_second) of one covering pass with a trained catalog.

    cores: those of the session, unless given.
    """
    cores = cores or spark.sparkContext.defaultParallelism
    baskets = source(spark, sf_dir, name)
    catalog = miner.mine(baskets, max_iter).catalog
    compressed, m, _ = miner.prepared(baskets)
    compressed.count()
    began = time.time()
    em.e_step(compressed, catalog)
    secs = time.time() - began
    return spark.createDataFrame([(name, m, secs, measures.throughput(m, secs, cores))], "source string, baskets long, secs double, baskets_per_core_second double")
