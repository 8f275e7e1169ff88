"""All methods, measures and workloads as queries over the given tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .baselines import codetable, frequent, maxent, tiling
from .functions import expressions as fx
from .operators import candidates, catalog as cat, cover, em, encode, measures, miner, model, rank, rules, structural, support
from .operators.catalog import Catalog, Itemset
from .oracles import oracle_sql  # noqa: F401  part of the interface
from .plans import report, workloads
from .sources.baskets import SOURCES, source
from .sources.tables import read
from .streaming import streams

Query = Callable[[SparkSession, str], DataFrame]
#: The greedy catalogs of the checked queries: every item and, of the pairs, those that this says.
PAIRS = {"order_geo": "implied", "order_regions": "all", "userday_events": "all"}
SEVERAL = ["n15|r0", "n21|r1", "n12|r2"]
#: Pairs whose four cells are all filled: the scaling of a maximum-entropy model then converges fast.
MIXED = ["n15|r1", "n21|r2", "n12|r3"]


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The miner's ranking on nations and regions of orders."""
    found = miner.mine(source(spark, sf_dir, "order_geo"), max_iter=3)
    return rank.top_k(found.to_df(spark), 20, singletons=True)


def _support(name: str) -> Query:
    return lambda s, d: encode.item_support(source(s, d, name))


def _compressed(s: SparkSession, d: str, name: str) -> DataFrame:
    return encode.compress(source(s, d, name))


def _pairs(s: SparkSession, d: str, name: str) -> DataFrame:
    return candidates.pair_supports(_compressed(s, d, name)).select(F.concat_ws("|", "a", "b").alias("itemset"), "support")


def fixed_catalog(s: SparkSession, d: str, name: str) -> tuple[Catalog, DataFrame, int]:
    """Items and pairs with their relative supports; small by construction (few dozen items)."""
    compressed, m, items = miner.prepared(source(s, d, name))
    made = cat.from_support(sorted(items.items()), m)
    for r in candidates.pair_supports(compressed).toLocalIterator():
        if PAIRS[name] == "all" or r["support"] == items[r["a"]]:
            p = Itemset.of((r["a"], r["b"]), r["support"] / m, 0, r["support"])
            made[p.key] = p
    return made, compressed, m


def _covered(s, d, name, kernel="native"):
    made, compressed, m = fixed_catalog(s, d, name)
    return cover.cover(compressed, made, kernel=kernel), made, m


def _greedy(name: str, kernel: str) -> Query:
    def run(s, d):
        covered, _, _ = _covered(s, d, name, kernel)
        return covered.select(F.array_join("items", "|").alias("basket"), "mult", F.array_join("cover", "+").alias("cover"), F.round("cost", 6).alias("cost"))

    return run


def _full_cost(name: str, joint: bool) -> Query:
    def run(s, d):
        covered, made, _ = _covered(s, d, name)
        keyed = covered.select(F.array_join("items", "|").alias("tid"), "items", "cover")
        out = model.log_joint(keyed, made) if joint else model.cover_cost(keyed, made)
        return out.select(F.col("tid").alias("basket"), F.round("logp" if joint else "full_cost", 6).alias("logp" if joint else "full_cost"))

    return run


def profit_closed_form(s, d):
    covered, made, m = _covered(s, d, "order_geo", "auto")
    used = cover.usage(covered, "mult")
    return used.agg(F.round(-F.sum(fx.binary_entropy(F.col("usage") / m)), 6).alias("profit"), F.count("*").alias("used_sets"))


def _usage_ranked(s, d):
    made, compressed, m = fixed_catalog(s, d, "order_geo")
    used = em.e_step(compressed, made, kernel="native")
    return cat.to_df(s, {k: v.with_(usage=used.get(k, 0), pi=used.get(k, 0) / m) for k, v in made.items()})


def interestingness_order_geo(s, d):
    return rank.interestingness(_usage_ranked(s, d)).select("key", "usage", "support", F.round("interestingness", 6).alias("interestingness"), F.round("pi", 6).alias("pi"))


def _rank(by: str, singletons: bool) -> Query:
    return lambda s, d: rank.top_k(_usage_ranked(s, d), 20, by, singletons).select("rank", "itemset", "usage", "support", F.round("interestingness", 6).alias("interestingness"), F.round("pi", 6).alias("pi"))


def _hard_em(name: str) -> Query:
    def run(s, d):
        made, compressed, m = fixed_catalog(s, d, name)
        found = em.hard_em(compressed, made, m, eps=0.0, max_iter=3)
        return cat.to_df(s, found.catalog).select("key", "usage", F.round("pi", 6).alias("pi"))

    return run


def _first_step(name: str) -> Query:
    def run(s, d):
        baskets = source(s, d, name)
        # Both are read off the baskets as they come, for merging equal ones shuffles them.
        m = baskets.count()
        items = baskets.select(F.explode("items").alias("i")).agg(F.approx_count_distinct("i")).first()[0]
        gains = structural.first_step_gains(encode.compress(baskets), m, items).where("gain > 1e-9")
        return gains.select(F.concat_ws("|", "a", "b").alias("itemset"), "support", F.round("gain", 6).alias("gain"))

    return run


def _structural(name: str) -> Query:
    def run(s, d):
        found = miner.mine(source(s, d, name), max_iter=1, em_iter=1)
        return s.createDataFrame([(t["accepted"], round(t["profit"], 6)) for t in found.trace], "accepted string, profit double")

    return run


def _traced(s: SparkSession, baskets: DataFrame) -> DataFrame:
    found = miner.mine(baskets, max_iter=2, em_iter=1)
    return s.createDataFrame([(t["iter"], t["accepted"], round(t["profit"], 6)) for t in found.trace], "iter int, accepted string, profit double")


def mine_small_planted(s, d):
    """Two whole iterations on baskets of a known catalog."""
    return _traced(s, model.generate(s, workloads.planted_catalog(), 400, 7).where(F.size("items") > 0))


def mine_small_userday_events(s, d):
    return _traced(s, source(s, d, "userday_events"))


def mine_small_order_geo(s, d):
    """Two whole iterations on the flagship source."""
    return _traced(s, source(s, d, "order_geo"))


def candidate_queue_order_geo(s, d):
    compressed, m, items = miner.prepared(source(s, d, "order_geo"))
    queue = candidates.build_queue(compressed, cat.from_support(sorted(items.items()), m), set(), items)
    return s.createDataFrame([(n, c.key, c.support) for n, c in enumerate(queue, 1)], "rank int, itemset string, support long")


def apriori_queue_order_geo(s, d):
    compressed, m, items = miner.prepared(source(s, d, "order_geo"))
    queue = candidates.apriori_queue(compressed, items, m // 10, largest=3)
    return s.createDataFrame([(n, c.key, c.support) for n, c in enumerate(queue, 1)], "rank int, itemset string, support long")


def prefix_tree_order_regions(s, d):
    return support.build_tree(source(s, d, "order_regions")).select(F.array_join("path", "|").alias("path"), "last", "depth", "cnt")


def _several(s: SparkSession) -> DataFrame:
    return s.createDataFrame([(k, k.split("|")) for k in SEVERAL], "key string, items array<string>")


def _tree_support(compressed: bool, by_support: bool) -> Query:
    def run(s, d):
        baskets = source(s, d, "order_geo")
        items = encode.fit(baskets) if by_support else None
        tree = support.build_tree(baskets, items)
        return support.query_compressed(support.compress_tree(tree), _several(s)) if compressed else support.query(tree, _several(s), items)

    return run


def batch_support_order_geo(s, d):
    sets = _several(s).withColumn("anchor", F.col("items")[0])
    return cat.count_support(source(s, d, "order_geo"), sets)


def encoded_round_trip(s, d):
    baskets = source(s, d, "order_geo")
    items = encode.fit(baskets)
    back = encode.inverse(encode.transform(baskets, items), items)
    return back.select("tid", F.array_join("items", "|").alias("basket"))


def compressed_baskets(s, d):
    return _compressed(s, d, "userday_events").select(F.array_join("items", "|").alias("basket"), "mult")


def _code_table(s, d):
    made, compressed, _ = fixed_catalog(s, d, "order_geo")
    return {k: (v.items, v.support) for k, v in made.items()}, compressed


def _code_cover(native: bool) -> Query:
    def run(s, d):
        table, compressed = _code_table(s, d)
        covered = (codetable.native_cover if native else codetable.cover)(compressed, table)
        return covered.select(F.array_join("items", "|").alias("basket"), "mult", F.array_join("cover", "+").alias("cover"))

    return run


def codetable_bits(s, d):
    table, compressed = _code_table(s, d)
    used = codetable.usages(compressed, table)
    found = codetable.CodeTable(table, used, 0.0, 0).to_df(s)
    return found.where("usage > 0").select("key", "usage", F.round("bits", 6).alias("bits"))


def _frequent(name: str, only_closed: bool) -> Query:
    def run(s, d):
        sets = frequent.frequent(source(s, d, name), workloads.MIN_SUPPORT)
        return (frequent.closed(sets) if only_closed else sets).select("key", "size", "support")

    return run


def chi2_rank_order_regions(s, d):
    return frequent.chi2_list(source(s, d, "order_regions"), workloads.MIN_SUPPORT, 10).select("rank", "itemset", "support", F.round("chi2", 4).alias("chi2"))


def maxent_pair_logp(s, d):
    fitted = maxent.fit(source(s, d, "order_geo"), [tuple(k.split("|")) for k in MIXED])
    return maxent.logp(source(s, d, "order_geo"), fitted).agg(F.round(F.avg("logp"), 4).alias("mean_logp"))


def maxent_summary(s, d):
    """The list, and how many sets were refused for the size of their blocks."""
    fitted, found = maxent.mine(source(s, d, "order_geo"), 5)
    return s.createDataFrame([(n, "|".join(x), len(fitted.refused)) for n, x in enumerate(found, 1)], "rank int, itemset string, refused long")


def code_table_from_pairs(s, d):
    found = codetable.mine_pairs(source(s, d, "order_geo"), 5)
    return s.createDataFrame([(n, "|".join(x)) for n, x in enumerate(codetable.ranked(found, 10), 1)], "rank int, itemset string")


def code_table_from_candidates(s, d):
    baskets = source(s, d, "order_geo").persist()
    found = codetable.mine(baskets, frequent.closed(frequent.frequent(baskets, workloads.MIN_SUPPORT)))
    return s.createDataFrame([(n, "|".join(x)) for n, x in enumerate(codetable.ranked(found, 10), 1)], "rank int, itemset string")


def _tiles(s, d) -> list[tuple[str, ...]]:
    return [v.items for v in fixed_catalog(s, d, "order_geo")[0].values() if len(v.items) > 1]


def tiling_max_coverage(s, d):
    found = tiling.max_coverage(source(s, d, "order_geo"), _tiles(s, d), 3)
    return s.createDataFrame([(n, "|".join(t), g) for n, (t, g) in enumerate(found, 1)], "rank int, tile string, cells long")


def tiling_budgeted(s, d):
    found = tiling.budgeted(source(s, d, "order_geo"), _tiles(s, d), 500_000.0)
    return s.createDataFrame([(n, "|".join(t), g, c) for n, (t, g, c) in enumerate(found, 1)], "rank int, tile string, surprisal double, bits double")


def generate_md5(s, d):
    """A basket for each order from the items and pairs of regions with their relative supports."""
    known, _, _ = fixed_catalog(s, d, "order_regions")
    made = model.generate(s, known, seed=7, tids=source(s, d, "order_regions"))
    return made.select("tid", F.array_join("items", "|").alias("basket"))


def _curve(s: SparkSession, d: str) -> DataFrame:
    """The 50 pairs of highest support in orders against those of a nation and its region."""
    order = [F.desc("support"), F.asc("itemset")]
    mined = _pairs(s, d, "order_geo").orderBy(*order).limit(50).select(F.row_number().over(Window.orderBy(*order)).alias("rank"), "itemset")
    truth = read(s, d, "nation").select(F.concat(F.lit("n"), F.col("n_nationkey"), F.lit("|r"), F.col("n_regionkey")).alias("itemset"))
    return measures.curve(mined, truth)


def precision_recall(s, d):
    return _curve(s, d).select("k", F.round("precision", 6).alias("precision"), F.round("recall", 6).alias("recall"))


def eleven_point(s, d):
    return measures.eleven_point(_curve(s, d)).select(F.round("recall", 6).alias("recall"), F.round("precision", 6).alias("precision"))


def iid_order_geo(s, d):
    pairs = _pairs(s, d, "order_geo").orderBy(F.desc("support"), "itemset").limit(50).select("itemset", F.split("itemset", r"\|").alias("items"))
    return measures.iid(pairs).select(F.round("iid", 6).alias("iid"), "n")


def _daily(s, d) -> DataFrame:
    return measures.mentions(workloads.dated_baskets(s, d), _several(s).withColumnRenamed("key", "itemset"))


def spikes(s, d):
    return measures.spikes(_daily(s, d)).select("day", "itemset", "n", F.round("z", 6).alias("z"))


def series_corr(s, d):
    return measures.series_corr(_daily(s, d)).select("a", "b", F.round("corr", 6).alias("corr"))


def moving_mentions(s, d):
    return measures.moving_mentions(_daily(s, d)).select("day", "itemset", F.round("moving", 6).alias("moving"))


def rules_order_geo(s, d):
    baskets = source(s, d, "order_geo")
    sets = _pairs(s, d, "order_geo").select(F.col("itemset").alias("key"), F.split("itemset", r"\|").alias("items"), "support")
    found = rules.from_catalog(sets, baskets, 0.3)
    return found.select("antecedent", "consequent", "support", F.round("confidence", 6).alias("confidence"), F.round("lift", 6).alias("lift"))


def tiles_order_regions(s, d):
    made, _, _ = fixed_catalog(s, d, "order_regions")
    return rules.tiles(cover.cover(source(s, d, "order_regions"), made, kernel="arrow"))


def events_windows(s, d):
    return streams.form_baskets(read(s, d, "events")).select("user_id", "start", F.array_join("items", "|").alias("basket"))


def events_sessions(s, d):
    return streams.form_baskets(read(s, d, "events"), gap="2 hours").select("user_id", "start", F.array_join("items", "|").alias("basket"))


def stream_mentions(s, d):
    """The stream's answer, run over all that is there and read from memory."""
    events = read(s, d, "events")
    stream = streams.source(s, d, events, pattern="events.parquet")
    sets = s.createDataFrame([(t, [t]) for t in ("click", "purchase", "view")], "itemset string, items array<string>")
    counts = streams.mentions(stream.select("ts", F.array("event_type").alias("items")), sets)
    name = f"stream_mentions_{abs(hash(d))}"
    streams.to_memory(counts, name, "complete")
    return s.table(name).withColumn("start", F.col("start").cast("timestamp_ntz"))


def usage_rollup(s, d):
    dated = workloads.dated_baskets(s, d).withColumns({"year": F.year("ts"), "month": F.month("ts")})
    return report.usage_rollup(dated, SEVERAL[0].split("|"), ["year", "month"])


def sql_functions(s, d):
    fx.register(s)
    _pairs(s, d, "order_geo").createOrReplaceTempView("_pairs_of_items")
    return s.sql(
        "SELECT itemset_key(split(itemset, '[|]')) AS itemset, sym_diff_size(split(itemset, '[|]'), array('n1', 'r1')) AS distance,"
        " itemset_contains(split(itemset, '[|]'), array('r1')) AS has_r1, round(binary_entropy(0.25), 6) AS h, round(chi2_score(support, 100, 100000), 6) AS chi2 FROM _pairs_of_items"
    )


def table_function_subsets(s, d):
    fx.register(s)
    _support("order_regions")(s, d).agg(F.sort_array(F.collect_list("item")).alias("items")).createOrReplaceTempView("_all_regions")
    return s.sql("SELECT array_join(t.subset, '|') AS subset FROM _all_regions, LATERAL subsets(items) AS t")


def arrow_function_jaccard(s, d):
    fx.register(s)
    _pairs(s, d, "order_geo").createOrReplaceTempView("_pairs_of_items")
    return s.sql("SELECT itemset, round(jaccard(split(itemset, '[|]'), array('n1', 'r1')), 6) AS jaccard FROM _pairs_of_items")


def aggregate_mean_distance(s, d):
    fx.register(s)
    _pairs(s, d, "order_geo").orderBy(F.desc("support"), "itemset").limit(50).createOrReplaceTempView("_top_pairs")
    return s.sql("SELECT round(mean_distance(split(itemset, '[|]')), 6) AS iid FROM _top_pairs")


def shared_spikes(s, d):
    found = measures.spikes(_daily(s, d), 2.0)
    return measures.shared_spikes(found).select("day", "sets", F.array_join("itemsets", "+").alias("itemsets"))


def rank_of_sets(s, d):
    listed = _pairs(s, d, "order_geo").orderBy(F.desc("support"), "itemset").limit(20)
    ranks = listed.withColumn("rank", F.row_number().over(Window.orderBy(F.desc("support"), "itemset")))
    return measures.rank_of(ranks, [*SEVERAL, "a|b"])


def shortfall_order_geo(s, d):
    return measures.shortfall(_pairs(s, d, "order_geo").where("support > 1").limit(50), 50)


def cover_ratio_order_regions(s, d):
    """Greedy against exact covers: the worst ratio, and whether the guarantee holds."""
    made, compressed, _ = fixed_catalog(s, d, "order_regions")
    keyed = compressed.select(F.array_join("items", "|").alias("tid"), "items")
    greedy, exact = (cover.cover(keyed, made, kernel=k) for k in ("lazy_heap", "exact"))
    return measures.cover_ratio(greedy, exact).select(F.round("worst", 6).alias("worst"), "bound_kept")


def trace_planted(s, d):
    """The miner's trace without its times."""
    found = miner.mine(model.generate(s, workloads.planted_catalog(), 400, 7).where(F.size("items") > 0), max_iter=6)
    return miner.trace_df(s, found).select("iter", F.round("profit", 6).alias("profit"), "tried", "accepted", "passes")


def log_odds_weights(s, d):
    made, _, _ = fixed_catalog(s, d, "order_geo")
    rows = [(k, round(cover.weight_of(v.pi, "logodds"), 6)) for k, v in made.items() if 0 < v.pi < 1]
    return s.createDataFrame(rows, "key string, weight double")


def stemmed_words_en(s, d):
    return encode.item_support(source(s, d, "doc_stems_en"))


def events_cube(s, d):
    return read(s, d, "events").cube("event_type", F.to_date("ts").alias("day")).agg(F.count("*").alias("n"))


def null_accepts(s, d):
    return workloads.null_accepts(s, d, ("order_regions", "order_brands", "part_suppnations", "userday_events"))


def description_length(s, d):
    covered, made, m = _covered(s, d, "order_regions")
    keyed = covered.select(F.array_join("items", "|").alias("tid"), "items", "cover")
    logp = model.log_joint(keyed, made).withColumnRenamed("tid", "basket")
    return logp.select("basket", F.round(fx.bits(F.col("logp")), 6).alias("bits"), F.round(fx.implied_logp(fx.bits(F.col("logp"))), 6).alias("logp"))


def queries() -> dict[str, Query]:
    named = {f"item_support_{n}": _support(n) for n in SOURCES}
    named |= {f"pair_support_{n}": (lambda s, d, n=n: _pairs(s, d, n)) for n in ("order_geo", "order_regions", "cust_brands", "part_attrs", "bench_words")}
    for n in PAIRS:
        named |= {f"greedy_cover_{n}": _greedy(n, "native")}
    named |= {"greedy_cover_arrow_order_geo": _greedy("order_geo", "arrow"), "greedy_cover_lazy_order_geo": _greedy("order_geo", "lazy_heap")}
    named |= {f"first_step_{n}": _first_step(n) for n in ("order_geo", "order_regions", "order_brands", "order_tokens", "cust_brands", "userday_events", "part_attrs", "doc_lines")}
    named |= {
        "cover_cost": _full_cost("order_regions", False), "log_joint": _full_cost("userday_events", True), "rank_pi": _rank("pi", True), "top_k": _rank("interestingness", False),
        "hard_em_order_regions": _hard_em("order_regions"), "hard_em_userday_events": _hard_em("userday_events"), "structural_step_order_geo": _structural("order_geo"),
        "tree_support_order_geo": _tree_support(False, False), "tree_support_ranked_order_geo": _tree_support(False, True), "tree_support_compressed_order_geo": _tree_support(True, False),
        "code_cover_order_geo": _code_cover(True), "code_cover_arrow_order_geo": _code_cover(False), "frequent_order_regions": _frequent("order_regions", False), "closed_itemsets_order_regions": _frequent("order_regions", True),
        "frequent_userday_events": _frequent("userday_events", False), "closed_itemsets_userday_events": _frequent("userday_events", True), "mentions_per_day": _daily,
        "mine_order_geo": lambda s, d: rank.top_k(miner.mine(source(s, d, "order_geo"), 20).to_df(s), 50), "mine_planted": lambda s, d: rank.top_k(miner.mine(model.generate(s, workloads.planted_catalog("overlap"), 3000).where(F.size("items") > 0), 10).to_df(s), 20),
        "workload_mine_all": workloads.mine_all, "workload_self_recovery": workloads.self_recovery, "workload_scaling": lambda s, d: workloads.scaling(s, catalog=workloads.trained(s, d)),
        "workload_redundancy": lambda s, d: workloads.redundancy(s, d, tuple(workloads.STAND_INS)), "workload_top_lists": lambda s, d: workloads.top_lists(s, d, methods=workloads.METHODS),
        "workload_top_lists_messages": lambda s, d: workloads.top_lists(s, d, "conv_words", 6, workloads.METHODS), "workload_mentions": lambda s, d: workloads.mentions_over_time(s, d, methods=workloads.METHODS),
        "workload_mentions_userday_events": lambda s, d: workloads.mentions_over_time(s, d, "userday_events", methods=workloads.METHODS), "workload_rank_compare": lambda s, d: workloads.rank_compare(s, d, methods=workloads.METHODS),
        "workload_null_controls": lambda s, d: workloads.null_accepts(s, d, workloads.NULLS), "workload_ablate": workloads.ablate, "workload_cover_ablation": workloads.cover_ablation,
        "workload_throughput": workloads.e_step_throughput,
    }
    plain = (
        mine_small_planted, mine_small_userday_events, mine_small_order_geo, profit_closed_form, interestingness_order_geo, candidate_queue_order_geo, apriori_queue_order_geo, prefix_tree_order_regions, batch_support_order_geo, encoded_round_trip, compressed_baskets, codetable_bits, chi2_rank_order_regions,
        maxent_pair_logp, maxent_summary, code_table_from_pairs, code_table_from_candidates, tiling_max_coverage, tiling_budgeted, generate_md5, precision_recall, eleven_point, iid_order_geo, spikes, series_corr, moving_mentions, rules_order_geo,
        tiles_order_regions, events_windows, events_sessions, stream_mentions, usage_rollup, sql_functions, null_accepts,
        table_function_subsets, arrow_function_jaccard, aggregate_mean_distance, shared_spikes, rank_of_sets, shortfall_order_geo, cover_ratio_order_regions, trace_planted, log_odds_weights, stemmed_words_en, events_cube, description_length,
    )
    return named | {f.__name__: f for f in plain}
