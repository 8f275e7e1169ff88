"""Worked examples, invariants and brute force for the itemset engine."""

import inspect
import itertools
import math
import random

import pytest
from pyspark.sql import functions as F

from itemlens.baselines import codetable, frequent, maxent, tiling
from itemlens.functions import expressions as fx
from itemlens.operators import candidates, catalog as cat, cover, em, encode, measures, miner, model, rank, rules, structural, support
from itemlens.operators.catalog import Itemset
from itemlens.plans import planner, report, workloads
from itemlens.sources import baskets as src, tables
from itemlens.streaming import streams

ACCEPT = [["a", "b"]] * 5 + [["c"]] * 3
REJECT = [["a", "b"]] * 5 + [["a", "c"], ["b", "c"], ["c"]]


def db(spark, rows):
    return spark.createDataFrame(list(enumerate(map(sorted, rows))), "tid long, items array<string>")


def catalog(*sets):
    made = [Itemset.of(s, math.exp(-w), 0, 1) for s, w in sets]
    return {s.key: s for s in made}


def random_rows(n, seed, items="abcdef"):
    r = random.Random(seed)
    return [r.sample(items, r.randint(1, len(items))) for _ in range(n)]


def test_accept_and_reject(spark):
    got = miner.mine(db(spark, ACCEPT))
    assert set(got.catalog) == {"a|b", "c"} and got.converged and got.profit == pytest.approx(-1.3231, abs=1e-4)
    assert model.profit({"a": 5, "b": 5, "c": 3}, 8) == pytest.approx(-1.9847, abs=1e-4)
    top = rank.top_k(got.to_df(spark), 5).collect()
    assert [(r["itemset"], r["interestingness"]) for r in top] == [("a|b", 1.0)]
    none = miner.mine(db(spark, REJECT))
    assert set(none.catalog) == {"a", "b", "c"} and "a|b" in none.rejected and none.profit == pytest.approx(-1.7862, abs=1e-4)
    gains = {f"{r['a']}|{r['b']}": r["gain"] for r in structural.first_step_gains(encode.compress(db(spark, REJECT)), 8).collect()}
    assert gains["a|b"] == pytest.approx(-2.0767 + 1.7862, abs=1e-4)


@pytest.mark.parametrize("kernel", ["native", "arrow", "lazy_heap"])
def test_greedy_example(spark, kernel):
    sets = catalog((["1"], 0.9), (["2"], 0.8), (["3"], 0.7), (["1", "2"], 0.5))
    got = cover.cover(db(spark, [["1", "2"], ["1", "2", "3"], ["3"], ["9"]]), sets, kernel=kernel).orderBy("tid").collect()
    assert [r["cover"] for r in got] == [["1|2"], ["1|2", "3"], ["3"], None]
    assert got[1]["cost"] == pytest.approx(1.2)


def test_kernels_against_exact(spark):
    r = random.Random(3)
    sets = catalog(*[([i], r.random() + 0.1) for i in "abcdef"], *[(r.sample("abcdef", r.randint(2, 4)), r.random() * 2) for _ in range(12)])
    rows = db(spark, random_rows(60, 1))
    exact = cover.cover(rows, sets, kernel="exact")
    best = {x["tid"]: x["cost"] for x in exact.collect()}
    index = cover.Index(sets.values())
    often = max(sum(i in s.items for s in sets.values()) for i in "abcdef")
    found = {k: {x["tid"]: x for x in cover.cover(rows, sets, kernel=k).collect()} for k in ("native", "arrow", "lazy_heap", "primal_dual")}
    for tid, e in best.items():
        g = found["arrow"][tid]
        assert g["cover"] == found["native"][tid]["cover"] == found["lazy_heap"][tid]["cover"]
        assert set().union(*(index.sets[k][0] for k in g["cover"])) == set(g["items"])
        assert e - 1e-9 <= g["cost"] <= (math.log(len(g["items"])) + 1) * e + 1e-9
        assert e - 1e-9 <= found["primal_dual"][tid]["cost"] <= often * e + 1e-9
    ratio = measures.cover_ratio(cover.cover(rows, sets, kernel="arrow"), exact).first()
    assert ratio["bound_kept"] and ratio["worst"] >= 1
    brute = min(sum(cover.weight_of(sets[k].pi) for k in c) for n in range(1, 7) for c in itertools.combinations(sets, n) if set().union(*(sets[k].items for k in c)) >= set("abc") and all(set(sets[k].items) <= set("abc") for k in c))
    assert cover.Index(sets.values()).cover("exact", frozenset("abc")) is not None
    abc = cover.cover(db(spark, [list("abc")]), sets, kernel="exact").first()["cost"]
    assert abc == pytest.approx(brute)


def test_overlap_and_code_cover(spark):
    sets = catalog((["a", "b"], 0.1), (["b", "c"], 0.1), (["a"], 5), (["b"], 5), (["c"], 5))
    row = db(spark, [["a", "b", "c"]])
    assert sorted(cover.cover(row, sets).first()["cover"]) == ["a|b", "b|c"]
    table = {k: (s.items, 1) for k, s in sets.items()}
    for f in (codetable.cover, codetable.native_cover):
        assert f(row, table).first()["cover"] == ["a|b", "c"]


def test_options_of_covers(spark):
    sets = catalog((["a"], 1), (["b"], 1), (["a", "b"], 3))
    rows = db(spark, [["a", "b", "z"]])
    assert cover.cover(rows, sets, kernel="arrow").first()["cover"] is None
    with_floor = cover.cover(rows, sets, floor=0.01).first()
    assert with_floor["cover"][-1] == "z" and with_floor["cost"] == pytest.approx(2 - math.log(0.01))
    many = catalog((["a", "b"], 0.1), (["b", "c"], 0.2), (["a", "c"], 0.3), (["a"], 9), (["b"], 9), (["c"], 9))
    index = cover.Index(many.values())
    assert index.drop_redundant(frozenset("abc"), ["a|b", "b|c", "a|c"]) == ["a|b", "b|c"]
    assert cover.weight_of(0.5, "logodds") == pytest.approx(0) and cover.weight_of(0.9, "logodds") < 0
    assert cover.cover(rows, catalog((["a", "b", "z"], 0.01)), "logodds").first()["cover"] == ["a|b|z"]
    applied = {(r["tid"], r["key"]) for r in cover.applicable(rows, sets).collect()}
    assert applied == {(0, "a"), (0, "b"), (0, "a|b")}
    base = db(spark, [["a", "b"], ["a"]])
    before = cover.cover(base, sets, kernel="arrow")
    changed = {**sets, "a|b": Itemset.of("ab", 0.99)}
    again = cover.refresh(before, base, changed, {"a|b"}, kernel="arrow").orderBy("tid").collect()
    assert [r["cover"] for r in again] == [["a|b"], ["a"]]


def test_degenerate_baskets(spark):
    full = miner.mine(db(spark, [["a", "b"]] * 4))
    assert full.profit == 0 and not math.isnan(full.profit)
    empty = miner.mine(db(spark, [[]]))
    assert empty.m == 1 and empty.catalog == {} and empty.profit == 0
    nothing = miner.mine(db(spark, []).limit(0))
    assert nothing.catalog == {}


def test_profit_both_ways(spark):
    rows = db(spark, random_rows(80, 5, "abcd"))
    got = miner.mine(rows, max_iter=4)
    covered = cover.cover(rows, got.catalog)
    assert measures.avg_loglik(covered, got.catalog) == pytest.approx(model.profit({k: s.usage for k, s in got.catalog.items()}, got.m), rel=1e-9)
    assert all(s.usage <= s.support for s in got.catalog.values())
    wrong = covered.withColumn("cover", F.array(F.lit("a")))
    assert measures.avg_loglik(wrong.where("size(items) > 1"), got.catalog) == -math.inf


def sequential(rows, max_iter):
    """The method step by step, one candidate at a time, on plain Python lists."""
    m = len(rows)
    count = lambda s: sum(set(s) <= set(r) for r in rows)
    sets = {i: Itemset.of((i,), count([i]) / m, count([i]), count([i])) for i in sorted({i for r in rows for i in r})}
    rejected, accepted = set(), []

    def usages(sets, forced=None):
        index, used = cover.Index(sets.values()), {}
        for r in rows:
            usable = index.applicable(frozenset(r))
            for k in index.greedy(frozenset(r), usable, forced if forced in usable else None):
                used[k] = used.get(k, 0) + 1
        return used

    for _ in range(max_iter):
        base = model.profit({k: s.usage for k, s in sets.items()}, m)
        ordered = candidates.ranked(sets)
        queue = {}
        for a, b in itertools.combinations(ordered, 2):
            u = tuple(sorted({*a.items, *b.items}))
            k = "|".join(u)
            if k not in sets and k not in rejected and (n := count(u)):
                queue[k] = (u, n)
        for k, (u, n) in sorted(queue.items(), key=lambda x: (-x[1][1], x[0])):
            used = usages({**sets, k: Itemset.of(u, 1.0, 0, n)}, k)
            if model.profit(used, m) > base + 1e-12:
                sets = {key: s.with_(usage=used.get(key, 0), pi=used.get(key, 0) / m) for key, s in {**sets, k: Itemset.of(u, 1.0, 0, n)}.items()}
                accepted.append(k)
                break
            rejected.add(k)
        else:
            return accepted
        best = None
        for _ in range(20):
            used = usages({k: s for k, s in sets.items() if s.pi > 0})
            change = math.sqrt(sum((used.get(k, 0) / m - s.pi) ** 2 for k, s in sets.items()))
            sets = {k: s.with_(usage=used.get(k, 0), pi=used.get(k, 0) / m) for k, s in sets.items()}
            now = model.profit(used, m)
            if best is None or now >= best[0]:
                best = (now, sets)
            if change <= 1e-6:
                break
        sets = {k: s for k, s in best[1].items() if s.pi > 0}
    return accepted


@pytest.mark.parametrize("batch", [1, 7, 64])
def test_batches_equal_one_by_one(spark, batch):
    r = random.Random(9)
    rows = [sorted({*(["a", "b"] if r.random() < 0.4 else []), *(["c", "d", "e"] if r.random() < 0.3 else []), *(["f"] if r.random() < 0.3 else []), *(["a"] if r.random() < 0.1 else [])}) for _ in range(150)]
    rows = [x for x in rows if x]
    got = miner.mine(db(spark, rows), max_iter=5, batch=batch)
    assert [t["accepted"] for t in got.trace if t["accepted"]] == sequential(rows, 5)
    profits = [t["profit"] for t in got.trace]
    assert profits == sorted(profits)


def test_planted_sets_are_found(spark):
    made = model.generate(spark, workloads.planted_catalog("disjoint"), 2000, 42).where(F.size("items") > 0).persist()
    for options in ({}, {"em_every": 3}, {"cap": "top_support"}, {"pair_order": "rank_sum"}, {"prune": "chi2"}, {"prior": "size"}):
        found = {k for k in miner.mine(made, 8, **options).catalog if "|" in k}
        assert found == {"a|b", "c|d|e", "f|g"}, options
    apriori = {k for k in miner.mine(made, 8, generator="apriori", min_support=20).catalog if "|" in k}
    assert {"a|b", "f|g"} <= apriori
    empirical = {r["item"]: r["support"] for r in encode.item_support(made).collect()}
    assert abs(empirical["a"] / 2000 - 0.3) < 4 * math.sqrt(0.3 * 0.7 / 2000)


def test_resume(spark, tmp_path):
    rows = db(spark, ACCEPT * 3 + [["c", "d"]] * 9)
    first = miner.mine(rows, 1, save_to=str(tmp_path / "s"))
    loaded = miner.load(spark, str(tmp_path / "s"))
    assert loaded.catalog == first.catalog and loaded.m == first.m
    loaded.trace = first.trace
    assert miner.mine(rows, 9, resume=loaded).catalog == miner.mine(rows, 9).catalog
    assert miner.trace_df(spark, first).count() == 1


def test_queue(spark):
    rows = db(spark, random_rows(60, 2))
    compressed, m, items = miner.prepared(rows)
    singles = cat.from_support(sorted(items.items()), m)
    queue = candidates.build_queue(compressed, singles, {"a|b"}, items, q=9)
    assert len(queue) <= 9 and all(x.support >= y.support for x, y in zip(queue, queue[1:], strict=False)) and "a|b" not in {c.key for c in queue}
    for c in queue:
        assert c.support == sum(set(c.items) <= set(r["items"]) for r in rows.collect())
    top = candidates.build_queue(compressed, singles, set(), items, q=3, cap="top_support")
    every = candidates.build_queue(compressed, singles, set(), items)
    assert [c.support for c in top] == [c.support for c in every[:3]]


def test_trees(spark):
    rows = db(spark, random_rows(70, 4))
    items = encode.fit(rows)
    sets = spark.createDataFrame([("|".join(s), list(s)) for n in (1, 2, 3) for s in itertools.combinations("abcdef", n)], "key string, items array<string>")
    want = {"|".join(s): n for k in (1, 2, 3) for s in itertools.combinations("abcdef", k) if (n := sum(set(s) <= set(r["items"]) for r in rows.collect()))}
    tree = support.build_tree(rows)
    small = support.compress_tree(tree)
    assert small.count() < tree.count()
    for got in (support.query(tree, sets), support.query(support.build_tree(rows, items), sets, items), support.query_compressed(small, sets), cat.count_support(rows, sets.withColumn("anchor", F.col("items")[0]))):
        assert {r["key"]: r["support"] for r in got.collect()} == want


def test_frequent_and_closed(spark):
    rows = random_rows(50, 6, "abcde")
    want = {"|".join(s): n for k in range(1, 6) for s in itertools.combinations("abcde", k) if (n := sum(set(s) <= set(r) for r in rows)) >= 5}
    found = frequent.frequent(db(spark, rows), 0.1)
    assert {r["key"]: r["support"] for r in found.collect()} == want
    closed = {k for k, n in want.items() if not any(set(k) < set(x) and n == y for x, y in want.items())}
    assert {r["key"] for r in frequent.closed(found).collect()} == closed
    assert frequent.chi2_list(db(spark, rows), 0.1, 5).count() == 5


def test_code_tables_shrink(spark):
    rows = db(spark, ACCEPT * 8)
    got = codetable.mine_pairs(rows)
    assert codetable.ranked(got, 5) == [("a", "b")]
    plain = {"a": 40, "b": 40, "c": 24}
    assert got.bits < codetable.total_bits({i: ((i,), 0) for i in "abc"}, plain, plain)
    same = codetable.mine(rows, [(("a", "b"), 40), (("a", "c"), 0)], prune=True)
    assert same.bits == pytest.approx(got.bits)


def test_code_table_ranks_all_pairs_of_positive_gain(spark):
    rows = random_rows(60, 3, "abcdefgh") + [["x", "y"]] * 3
    compressed, _, table, used, single, bits = codetable._start(db(spark, rows))
    pairs = codetable.descending(codetable.pair_gains(compressed, table, used), 5)
    got = [(r["a"], r["b"], r["n"], r["gain"]) for r in pairs]
    met = {p: n for p in itertools.combinations(sorted(used), 2) if (n := sum(set(p) <= set(r) for r in rows))}
    want = {p: g for p, n in met.items() if (g := codetable.estimated_gain(used[p[0]], used[p[1]], n, sum(used.values()))) > 0}
    assert {(a, b): g for a, b, _, g in got} == pytest.approx(want) and len(got) == len(want) > 5
    assert [g for *_, g in got] == sorted((g for *_, g in got), reverse=True)
    # One pass over a batch gives the usages of covering with each candidate alone.
    grown = {**table, "a|b|c": (("a", "b", "c"), 9), "d|e": (("d", "e"), 20)}
    base = codetable.usages(compressed, grown)
    batch = [("a|b", ("a", "b"), 30), ("c|d|e|f", ("c", "d", "e", "f"), 6), ("g|h", ("g", "h"), 20), ("b|d", ("b", "d"), 20)]
    for (key, items, n), change in zip(batch, codetable.deltas(compressed, grown, batch), strict=True):
        new = codetable.usages(compressed, {**grown, key: (items, n)})
        assert change == {k: d for k in {**base, **new} if (d := new.get(k, 0) - base.get(k, 0))}
    compressed.unpersist()


def test_pairs_fall_alike_by_levels_of_usage(spark, monkeypatch):
    """Counting seldom used sets last gives the same pairs in the same order, whole, at any size of the first level."""
    import random

    rng = random.Random(5)
    rows = [sorted({f"w{int(rng.paretovariate(0.7)) % 60:02d}" for _ in range(rng.randint(1, 9))}) for _ in range(300)]
    compressed, m, table, used, single, bits = codetable._start(spark.createDataFrame(list(enumerate(rows)), "tid long, items array<string>"))
    table["w01|w02"] = (("w01", "w02"), 1)
    used = codetable.usages(compressed, table)
    want = [(r["a"], r["b"], r["n"], r["gain"]) for r in codetable.descending(codetable.pair_gains(compressed, table, used))]
    assert len(want) > 200
    for first, more in ((2, 2), (7, 3), (512, 8)):
        monkeypatch.setattr(codetable, "FIRST_SETS", first)
        monkeypatch.setattr(codetable, "MORE_SETS", more)
        assert [(r["a"], r["b"], r["n"], r["gain"]) for r in codetable.falling_pairs(compressed, table, used)] == want


def test_code_table_takes_all_candidates(spark, monkeypatch):
    r = random.Random(9)
    twins = [(f"a{n}", f"b{n}") for n in range(6)]
    rows = db(spark, [x for _ in range(150) if (x := sum((list(t) for t in twins if r.random() < 0.4), []))])
    sets = [(tuple(x["items"]), x["support"]) for x in frequent.closed(frequent.frequent(rows, 0.02)).where("size > 1").collect()]
    assert len(sets) > 40
    compressed, _, table, used, single, bits = codetable._start(rows)
    for items, n in sorted(sets, key=lambda c: (-c[1], -len(c[0]), "|".join(c[0]))):
        tried = {**table, "|".join(items): (items, n)}
        new = codetable.usages(compressed, tried) if len(table) < 14 else None  # the first few, one at a time
        if new is None:
            break
        if codetable.total_bits(tried, new, single) < bits - 1e-9:
            table, used, bits = tried, new, codetable.total_bits(tried, new, single)
    monkeypatch.setattr(codetable, "FIRST_BATCH", 3)
    whole = codetable.mine(rows, frequent.closed(frequent.frequent(rows, 0.02)))
    assert set(table) <= set(whole.table) and whole.bits == pytest.approx(codetable.mine(rows, sets).bits)
    given, real = [], codetable.mine
    monkeypatch.setattr(codetable, "mine", lambda b, c, **k: given.append(c.where("size > 1").count()) or real(b, c, **k))
    assert workloads.listed(spark, rows, "code_candidates", 50, 1, 0.02).count() > 1 and given == [len(sets)]


def test_pair_search_passes_failures(spark, monkeypatch):
    rows = db(spark, ACCEPT * 8)
    tried, real = [], codetable.first_shorter

    def fail_first(compressed, table, used, single, bits, batch):
        tried.append([k for k, _, _ in batch])
        return None if len(tried) == 1 else real(compressed, table, used, single, bits, batch)

    monkeypatch.setattr(codetable, "first_shorter", fail_first)
    monkeypatch.setattr(codetable, "FIRST_BATCH", 1)
    monkeypatch.setattr(codetable, "PAIRS_BLOCK", 1)
    several = db(spark, [["a", "b"]] * 40 + [["c", "d"]] * 30 + [["e"]] * 20)
    found = codetable.mine_pairs(several)
    assert tried[0] == ["a|b"] and tried[1] == ["c|d"] and {"a|b", "c|d"} <= set(found.table)
    assert codetable.ranked(codetable.mine_pairs(rows), 5) == [("a", "b")]


def test_maxent(spark):
    rows = db(spark, REJECT * 4)
    fitted = maxent.fit(rows, [("a", "b")])
    direct = maxent.logp(rows, fitted).agg(F.avg("logp")).first()[0]
    assert direct == pytest.approx(fitted.mean_loglik(), abs=1e-6)
    cells = [20 / 32, 4 / 32, 4 / 32, 4 / 32]
    want = sum(p * math.log(p) for p in cells) - model.entropy(12 / 32)
    assert fitted.mean_loglik() == pytest.approx(want, abs=1e-4)
    _, found = maxent.mine(db(spark, ACCEPT * 20), 5)
    assert ("a", "b") in found or ("a", "c") in found or ("b", "c") in found


def test_maxent_counts_all_unions_and_reports_refusals(spark, monkeypatch):
    twins = [[f"{c}{n}" for n in range(2)] for c in "abcd"]
    r = random.Random(5)
    rows = db(spark, [sum((t for t in twins if r.random() < 0.5), ["z"]) for _ in range(200)])
    want = {"|".join(t) for t in twins}
    assert want <= {"|".join(x) for x in maxent.mine(rows, 8, pool=1)[1]}
    # Blocks of two items at most: once the twins have joined, their many unions are refused, and said to be.
    monkeypatch.setattr(maxent, "LARGEST_BLOCK", 2)
    many = db(spark, [["a", "b", "c", "d", "e", "f", "g"]] * 30 + [["h", "i"]] * 20 + [["j"]] * 50)
    with pytest.warns(UserWarning, match="refused"):
        fitted, found = maxent.mine(many, 8)
    assert ("h", "i") in found and len(fitted.refused) > 20 and all(len(b.items) <= 2 for b in fitted.blocks)
    again = maxent.fit(many, found)
    assert fitted.score() == pytest.approx(again.score(), abs=1e-3)


def test_tilings(spark):
    rows = db(spark, [["a", "b", "c"]] * 4 + [["c", "d"]] * 3)
    assert tiling.max_coverage(rows, [("a", "b", "c"), ("b", "c"), ("c", "d")], 3) == [(("a", "b", "c"), 12), (("c", "d"), 6)]
    found = tiling.budgeted(rows, [("a", "b", "c"), ("b", "c"), ("c", "d")], 40.0)
    assert found and sum(c for _, _, c in found) <= 40


def test_measures(spark):
    mined = spark.createDataFrame([(1, "a|b"), (2, "x|y"), (3, "c|d")], "rank int, itemset string")
    truth = spark.createDataFrame([("a|b",), ("c|d",)], "itemset string")
    pr = measures.curve(mined, truth).orderBy("k").collect()
    assert [(r["precision"], r["recall"]) for r in pr] == [(1.0, 0.5), (0.5, 0.5), (pytest.approx(2 / 3), 1.0)]
    points = {round(r["recall"], 1): r["precision"] for r in measures.eleven_point(measures.curve(mined, truth)).collect()}
    assert points[0.5] == 1.0 and points[0.6] == pytest.approx(2 / 3) and len(points) == 11
    sets = spark.createDataFrame([("a|b", ["a", "b"]), ("a|c", ["a", "c"]), ("x|y|z", ["x", "y", "z"])], "itemset string, items array<string>")
    assert measures.iid(sets).first()["iid"] == pytest.approx((2 + 2 + 5) / 3)
    assert measures.iid(sets.limit(1)).first()["iid"] is None
    assert measures.rank_of(mined, ["c|d", "q"]).where("rank is not null").collect()[0]["rank"] == 3
    assert report.side_by_side({"m": mined}, 4).count() == 4
    assert measures.shortfall(mined, 50).first()["short"]


def test_rules_and_tiles(spark):
    rows = db(spark, ACCEPT)
    sets = spark.createDataFrame([("a|b", ["a", "b"], 5)], "key string, items array<string>, support long")
    got = {(r["antecedent"], r["consequent"]): (r["confidence"], r["lift"]) for r in rules.from_catalog(sets, rows).collect()}
    assert got == {("a", "b"): (1.0, pytest.approx(8 / 5)), ("b", "a"): (1.0, pytest.approx(8 / 5))}
    covered = cover.cover(rows, miner.mine(rows).catalog)
    assert {r["key"]: r["rows"] for r in rules.tiles(covered, True).collect()} == {"a|b": 5, "c": 3}


def test_sources(spark, small, tmp_path):
    for name in src.SOURCES:
        got = src.source(spark, small, name)
        assert [f.name for f in got.schema] == ["tid", "items"], name
    assert src.source(spark, small, "doc_words_en", max_vocab=20).select(F.explode("items")).distinct().count() == 20
    rows = spark.createDataFrame([(1, None), (1, "b"), (1, "a"), (1, "a")], "k long, i string")
    assert src.from_rows(rows, F.col("k"), F.col("i")).first()["items"] == ["a", "b"]
    (tmp_path / "t.txt").write_text("b a a\n\nc\n")
    assert sorted(r["items"] for r in tables.read_transactions(spark, str(tmp_path / "t.txt")).collect()) == [[], ["a", "b"], ["c"]]
    top = src.from_vector(tables.read(spark, small, "embeddings"), F.col("vec_id"), F.col("embedding"), top=3)
    assert top.where(F.size("items") != 3).isEmpty()


def test_null_sources_yield_nothing(spark, small):
    for name in ("order_regions", "order_brands", "userday_events", "cust_brands", "page_tags"):
        assert not any("|" in k for k in miner.mine(src.source(spark, small, name), 1).catalog), name


def test_order_geo_finds_regions_of_nations(spark, small):
    got = miner.mine(src.source(spark, small, "order_geo"), 20)
    nation = {f"n{r['n_nationkey']}": f"r{r['n_regionkey']}" for r in tables.read(spark, small, "nation").collect()}
    sets = [s.items for s in got.catalog.values() if len(s.items) > 1]
    assert sets and all(len(s) == 2 and nation[s[0]] == s[1] for s in sets)


def test_native_plans_stay_in_the_jvm(spark, small):
    rows = src.source(spark, small, "order_geo")
    compressed = encode.compress(rows)
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    sets = catalog((["n1"], 1.0), (["r1"], 1.0), (["n1", "r1"], 0.5))
    for df in (cover.cover(compressed, sets, kernel="native"), structural.first_step_gains(compressed, 10), encode.item_support(rows)):
        assert "Python" not in plan(df) and "Arrow" not in plan(df) and "CartesianProduct" not in plan(df)
    s = planner.stats(rows)
    assert planner.choose(s).kernel == "native" and s.items <= 40


def test_sql_functions(spark):
    names = fx.register(spark)
    assert len(names) == 9
    assert spark.sql("SELECT sym_diff_size(array('a','b'), array('b','c')) AS d, itemset_contains(array('a','b'), array('a')) AS c, binary_entropy(0) AS h").first() == (2, True, 0.0)
    assert spark.range(1).select(F.size(fx.proper_subsets(F.array(*map(F.lit, "abc"))))).first()[0] == 6


def test_streams_equal_batch(spark, small):
    events = tables.read(spark, small, "events")
    stream = streams.source(spark, small, events, pattern="events.parquet")
    sets = spark.createDataFrame([(t, [t]) for t in ("click", "view")], "itemset string, items array<string>")
    single = lambda e: e.select(F.col("ts").cast("timestamp").alias("ts"), F.array("event_type").alias("items"))
    streams.to_memory(streams.mentions(single(stream), sets), "t_mentions", "complete")
    assert sorted(spark.table("t_mentions").collect()) == sorted(streams.mentions(single(events), sets).collect())
    streams.to_memory(streams.form_baskets(stream), "t_baskets", "update")
    batch = streams.form_baskets(events.withColumn("ts", F.col("ts").cast("timestamp")))
    assert sorted(spark.table("t_baskets").collect()) == sorted(batch.collect())
    twice = streams.deduplicated(stream)
    streams.to_memory(twice, "t_dedup")
    assert spark.table("t_dedup").count() == events.select("event_id").distinct().count()
    made = cat.from_support([(r["event_type"], 1) for r in events.select("event_type").distinct().collect()], 4)
    streams.to_memory(streams.assign(single(stream).select("items"), made), "t_assign")
    assert spark.table("t_assign").where("cover is null").isEmpty() and spark.table("t_assign").count() == events.count()
    streams.to_memory(streams.drift(single(stream).select("items"), made), "t_drift", "complete")
    assert {r["key"]: r["support"] for r in spark.table("t_drift").collect()} == {r["event_type"]: r["count"] for r in events.groupBy("event_type").count().collect()}


def test_refresh_and_alerts(spark, tmp_path):
    made = cat.from_support([("a", 4), ("b", 4)], 8)
    handle, current = streams.warm_refresh({**made, "a|b": Itemset.of("ab", 0.5, 0, 4)}, every=1)
    handle(db(spark, [["a", "b"]] * 6 + [["a"]] * 2), 0)
    assert current()["a|b"].pi == pytest.approx(0.75)
    daily = spark.createDataFrame([("s", f"2024-01-{d:02d} 00:00:00", 10 + d % 2 if d != 9 else 90) for d in range(1, 12)], "itemset string, start string, n long")
    daily.withColumn("start", F.to_timestamp("start")).coalesce(1).write.parquet(str(tmp_path / "d"))
    stored = spark.read.parquet(str(tmp_path / "d"))
    streams.to_memory(streams.spike_alerts(streams.source(spark, str(tmp_path / "d"), stored)), "t_alerts")
    alerts = spark.table("t_alerts").collect()
    assert [(r["itemset"], r["n"]) for r in alerts] == [("s", 90)]


def test_stand_ins_keep_items_and_baskets(spark, small, monkeypatch):
    for name, options in workloads.STAND_INS.items():
        assert options == ({"max_vocab": 194} if name == "page_words" else {})
    whole = src.source(spark, small, "order_parts")
    assert workloads.stand_in(spark, small, "order_parts").select(F.explode("items")).distinct().count() == whole.select(F.explode("items")).distinct().count()
    rows = db(spark, [["a"], ["a", "b"], ["b", "c"], ["c"], ["d"]])
    cut = src.limited(rows, max_vocab=1)
    assert sorted(r["items"] for r in cut.collect()) == [[], [], [], ["a"], ["a"]]
    found = miner.mine(src.limited(db(spark, ACCEPT * 8 + [["z"]]), min_df=2))
    assert found.m == len(ACCEPT) * 8 + 1 and "z" not in found.catalog
    compressed, m, supports = miner.prepared(whole)
    catalog = cat.from_support(sorted(supports.items()), m)
    want = candidates.build_queue(compressed, catalog, set(), supports, 2000)
    monkeypatch.setattr(candidates, "PAIRS_IN_ONE_PASS", 0)
    assert candidates.build_queue(compressed, catalog, set(), supports, 2000) == want != []


def test_workloads_are_registered_whole(spark, small, monkeypatch):
    from itemlens import queries

    seen = {}
    for name in ("mine_all", "self_recovery", "scaling", "redundancy", "top_lists", "mentions_over_time", "rank_compare", "ablate", "cover_ablation", "null_accepts"):
        real = getattr(workloads, name)

        def spy(*args, real=real, name=name, **options):
            bound = inspect.signature(real).bind(*args, **options)
            bound.apply_defaults()
            seen.setdefault(name, []).append((bound.arguments, {k: p.default for k, p in inspect.signature(real).parameters.items()}))

        monkeypatch.setattr(workloads, name, spy)
    monkeypatch.setattr(workloads, "trained", lambda *_: workloads.planted_catalog("overlap"))
    for name, run in queries.queries().items():
        if name == "null_accepts" or name.startswith("workload_") and name != "workload_throughput":
            run(spark, small)
    assert len(seen) == 10
    for calls in seen.values():
        for got, least in calls:
            assert all(got[k] >= least[k] for k in ("max_iter", "iters") if k in got)
            assert "methods" not in got or set(got["methods"]) == set(workloads.METHODS)
    assert set(seen["redundancy"][0][0]["sources"]) == set(seen["mine_all"][0][0]["sources"]) == set(workloads.STAND_INS)
    assert seen["scaling"][0][0]["sizes"] == (10_000, 20_000, 40_000) and "b|c" in seen["scaling"][0][0]["catalog"]
    assert {(c["name"], c["k"]) for c, _ in seen["top_lists"]} == {("doc_words_en", 10), ("conv_words", 6)}
    assert {c["name"] for c, _ in seen["mentions_over_time"]} == {"order_geo", "userday_events"} and {len(c["sources"]) for c, _ in seen["null_accepts"]} == {4, 12}


def test_mine_all_takes_all_iterations(spark, small):
    """Until no candidate improves, which five iterations are too few for."""
    (row,) = workloads.mine_all(spark, small, ("order_geo",)).collect()
    found = miner.mine(workloads.stand_in(spark, small, "order_geo"))
    assert found.converged and (row["iterations"], row["n_nonsingleton"]) == (len(found.trace), sum(len(s.items) > 1 for s in found.catalog.values())) and row["iterations"] > 5
    assert inspect.signature(workloads.mine_all).parameters["max_iter"].default == inspect.signature(miner.mine).parameters["max_iter"].default == 1000


def test_redundancy_lists_all_sets(spark, small):
    """The list of a method that runs until no candidate improves, not of its first six iterations."""
    got = {r["method"]: r["n_listed"] for r in workloads.redundancy(spark, small, ("order_geo",), methods=("cover", "maxent", "code_pairs")).collect()}
    baskets = src.source(spark, small, "order_geo")
    assert got["cover"] == min(50, sum(len(s.items) > 1 for s in miner.mine(baskets).catalog.values())) and got["maxent"] == len(maxent.mine(baskets, 50)[1])
    assert got["code_pairs"] == len(codetable.ranked(codetable.mine_pairs(baskets, 1000), 50)) and max(got.values()) > 6


def test_top_lists_are_those_of_all_iterations(spark, small):
    """Lists of the first sets of a whole run: six iterations find six sets, so no list of more."""
    got = workloads.top_lists(spark, small, "order_geo", 10, ("cover", "maxent", "code_pairs")).orderBy("rank").collect()
    baskets = src.source(spark, small, "order_geo")
    for method in ("cover", "maxent", "code_pairs"):
        whole = {r["rank"]: r["itemset"] for r in workloads.listed(spark, baskets, method, 10, 1000).collect()}
        assert [r[method] for r in got if r[method]] == [whole[n] for n in sorted(whole)]
    assert sum(r["code_pairs"] is not None for r in got) == 10


def test_lists_draw_on_all_closed_sets(spark, monkeypatch):
    """No frequent set is left out before closed ones are ranked or offered to a code table, held or not; a list has k sets however many iterations."""
    r = random.Random(41)
    lists = [sorted({x for x in "abcdefghijklmn" if r.random() < 0.5} | (set("pq") if r.random() < 0.3 else set())) for _ in range(420)]
    baskets = spark.createDataFrame(list(enumerate(lists)), "tid long, items array<string>").persist()
    given = miner.ready(baskets)
    want = sorted(map(tuple, frequent.closed(frequent.frequent(baskets, 0.0071)).select("key", "support").collect()))
    assert len(want) > 10_000
    found = list(frequent.held_closed(given.near, 3))
    assert [(-n, "|".join(s)) for s, n in found] == sorted((-n, "|".join(s)) for s, n in found) and sorted(("|".join(s), n) for s, n in found) == want
    offered, real = [], codetable.mine
    monkeypatch.setattr(codetable, "mine", lambda b, c, **k: offered.append(sorted(map(tuple, c.select("key", "support").collect()))) or real(b, [(("p", "q"), 1)]))
    for listed_at_most in (200_000, 5):
        monkeypatch.setattr(frequent, "LISTED", listed_at_most)
        workloads.listed(spark, miner.ready(baskets), "code_candidates", 50, 1, 0.0071)
    assert offered == [want, want]
    ranks = frequent.chi2_list(baskets, 0.0071, 20, 50_000).select("rank", "itemset").collect()
    assert workloads.listed(spark, given, "closed_chi2", 20, 1, 0.0071).select("rank", "itemset").collect() == ranks
    assert workloads.listed(spark, given, "maxent", 2, 1, 0.0071).count() == len(maxent.mine(given, 2, 0.0071)[1])


def test_pairs_are_counted_anew_where_covers_change(spark, monkeypatch):
    """The counts that rounds of the pair search keep are those of all covers, and only the first round reads all baskets."""
    r = random.Random(43)
    lists = [sorted({*r.sample("abcdefghijkl", r.randint(1, 4)), *(x for g in ("abc", "cde", "fg", "hijk") if r.random() < 0.3 for x in g)}) for _ in range(400)]
    given = miner.ready(db(spark, lists))
    whole, real = [], type(given.near).columns
    monkeypatch.setattr(type(given.near), "columns", lambda self, start: (self is given.near and whole.append(start)) or real(self, start))
    monkeypatch.setattr(codetable, "COVERS_AT_ONCE", 7)
    found = codetable.mine_pairs(given, 50)
    assert sum(len(items) > 1 for items, _ in found.table.values()) > 4 and whole == [0]
    counts = codetable.HeldPairs(given.near, found.table)
    order, met = [(k, set(found.table[k][0])) for k in codetable.cover_order(found.table)], {}
    for basket in lists:
        left, used = set(basket), []
        for k, items in order:
            if items <= left:
                used.append(k)
                left -= items
        for pair in itertools.combinations(sorted(used), 2):
            met[pair] = met.get(pair, 0) + 1
    got = {tuple(sorted((counts.keys[x], counts.keys[y]))): int(counts.met[x, y]) for x, y in itertools.combinations(range(len(counts.keys)), 2) if counts.met[x, y]}
    assert got == met
    want = {(a, b): gain for (a, b), n in met.items() if (gain := codetable.estimated_gain(found.usage[a], found.usage[b], n, sum(found.usage.values()))) > 1e-6}
    rows = [r for r in counts.falling(found.usage) if r["gain"] > 1e-6]
    assert {(r["a"], r["b"]): pytest.approx(r["gain"]) for r in rows} == want and [r["gain"] for r in rows] == sorted((r["gain"] for r in rows), reverse=True)


def test_many_candidates_share_the_covers_of_held_baskets(spark, monkeypatch):
    """Changes in usage from covers that are known equal those from covering each candidate's baskets, which a large batch does not do again."""
    r = random.Random(47)
    lists = [sorted({*r.sample("abcdefghijkl", r.randint(1, 5)), *(x for g in ("abc", "cde", "fg", "hijk") if r.random() < 0.3 for x in g)}) for _ in range(300)]
    given = miner.ready(db(spark, lists))
    found = codetable.mine_pairs(given, 8)
    sets = codetable.held_order(given.near, found.table)
    covers = codetable.HeldCovers(given.near, sets)
    batch = [("|".join(c), c, n) for size in (2, 3, 4) for c in itertools.combinations("abcdefghijkl", size) if "|".join(c) not in found.table and (n := given.near.supports([c]).get("|".join(c)))]
    want = [codetable.held_delta(given.near, sets, c) for c in batch]
    assert [codetable.held_delta(given.near, sets, c, covers) for c in batch] == want and sum(len(w) > 2 for w in want) > 50
    shared, real = [], codetable.held_delta
    monkeypatch.setattr(codetable, "held_delta", lambda near, sets, c, covers=None: shared.append(covers is not None) or real(near, sets, c, covers))
    codetable.first_shorter(given.near, found.table, found.usage, given.supports, 0.0, batch[:100])
    assert shared and all(shared)


def test_workloads_run(spark, small):
    assert workloads.scaling(spark, (300, 600), 1).count() == 2
    assert {r["kernel"] for r in workloads.cover_ablation(spark, small, max_iter=2).collect()} == {"exact", "greedy", "lazy_heap", "primal_dual"}
    found = workloads.redundancy(spark, small, methods=("cover", "closed_chi2"), max_iter=6).collect()
    iid = {r["method"]: r["iid"] for r in found}
    assert iid["cover"] > iid["closed_chi2"]
    points = workloads.self_recovery(spark, small, 2000, methods=("cover",), max_iter=6).collect()
    assert max(r["precision"] for r in points) == 1.0


def test_candidates_without_a_pass_equal_those_with_one(spark, monkeypatch):
    """Gains from supports alone, against passes over the baskets for every candidate."""
    r = random.Random(11)
    rows = [(n, sorted({*r.sample("abcdefgh", r.randint(1, 3)), *(("p", "q") if r.random() < 0.4 else ()), *(("x", "y", "z") if r.random() < 0.2 else ())})) for n in range(300)]
    baskets = spark.createDataFrame(rows, "tid long, items array<string>")
    fast = miner.mine(baskets, max_iter=6)
    real = structural.deltas
    seen = []

    def checked(compressed, catalog, batch, weight="neglog"):
        seen.append(len(batch))
        return real(compressed, catalog, batch, weight)

    monkeypatch.setattr(structural, "deltas", checked)
    monkeypatch.setattr(structural, "replaced", lambda c: {})
    compressed, m, supports = miner.prepared(baskets)
    catalog, queue = cat.from_support(sorted(supports.items()), m), None
    queue = candidates.build_queue(compressed, catalog, set(), supports)
    change = real(compressed, catalog, queue)
    monkeypatch.undo()
    assert all({k: n for k, n in structural.replaced(c).items() if n} == change[c.key] for c in queue)
    assert [t["accepted"] for t in fast.trace][:2] == ["p|q", "x|y"] or fast.trace[0]["accepted"] in ("p|q", "x|y")


def test_em_keeps_the_state_it_started_from(spark):
    rows = spark.createDataFrame([(["a", "b"], 5), (["c"], 3)], "items array<string>, mult long")
    start = {s.key: s for s in (Itemset.of(("a", "b"), 0.625, 5, 5), Itemset.of(("c",), 0.375, 3, 3))}
    found = em.hard_em(rows, start, 8, max_iter=1, start=0.0)
    assert found.profit == 0.0 and found.catalog == start
    assert em.hard_em(rows, start, 8, max_iter=1).profit < 0


def test_rules_of_large_sets_have_one_item_on_a_side(spark):
    items = [f"i{n:02}" for n in range(14)]
    baskets = spark.createDataFrame([(n, items if n < 3 else items[:2]) for n in range(5)], "tid long, items array<string>")
    sets = spark.createDataFrame([("|".join(items), items, 3)], "key string, items array<string>, support long")
    got = rules.from_catalog(sets, baskets).collect()
    assert len(got) == 28 and {min(r["antecedent"].count("|"), r["consequent"].count("|")) for r in got} == {0}


def test_table_function_mines_pairs(spark):
    from itemlens.functions import expressions as fx

    fx.register(spark)
    spark.createDataFrame([(["a", "b"],)] * 5 + [(["c"],)] * 3, "items array<string>").createOrReplaceTempView("_few")
    got = spark.sql("SELECT * FROM interesting_itemsets(TABLE(SELECT items FROM _few) WITH SINGLE PARTITION, 5)").collect()
    assert [(r["rank"], r["itemset"], r["support"]) for r in got] == [(1, "a|b", 5)]


def test_late_rows_are_counted(spark, tmp_path):
    from datetime import datetime, timedelta

    day = datetime(2024, 1, 10)
    for n, times in enumerate([[day], [day + timedelta(days=9)], [day - timedelta(days=5), day + timedelta(days=9)], [day + timedelta(days=20)]]):
        spark.createDataFrame([(n * 10 + k, t, 1, "view") for k, t in enumerate(times)], "event_id long, ts timestamp, user_id long, event_type string").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    like = spark.read.parquet(str(tmp_path / "in"))
    query = streams.to_memory(streams.form_baskets(streams.source(spark, str(tmp_path / "in"), like)), "late_rows_told")
    assert streams.dropped_late(query) == 1


def test_commonest_sets_are_the_first_of_all(spark):
    r = random.Random(3)
    baskets = spark.createDataFrame([(n, sorted({i for i in "abcdefghij" if r.random() < 0.7})) for n in range(200)], "tid long, items array<string>").where(F.size("items") > 0)
    every = sorted(((-x["support"], x["key"]) for x in frequent.frequent(baskets, 0.05).collect()))
    for most in (30, 200, 10**6):
        assert sorted((-x["support"], x["key"]) for x in frequent.commonest(baskets, 0.05, most).collect()) == every[:most]


def _shuffled(spark):
    listed = spark.sparkContext._jsc.sc().statusStore().executorList(True)
    return sum(listed.apply(i).totalShuffleWrite() for i in range(listed.size()))


def test_counting_sets_shuffles_no_baskets(spark):
    r = random.Random(5)
    rows = [(sorted(f"w{i}" for i in r.sample(range(400), 150)), r.randint(1, 3)) for _ in range(200)]
    compressed = spark.createDataFrame(rows, "items array<string>, mult long").persist()
    supports = {f"w{i}": sum(m for items, m in rows if f"w{i}" in items) for i in range(400)}
    unions = sorted({tuple(sorted(f"w{i}" for i in r.sample(range(401), r.choice((1, 2, 3))))) for _ in range(2000)})
    compressed.count()
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        before = _shuffled(spark)
        got = candidates.counted(compressed, unions, supports)
        after = _shuffled(spark)
        sets = spark.createDataFrame([("|".join(u), list(u), u[0]) for u in unions], "key string, items array<string>, anchor string")
        assert got == {x["key"]: x["support"] for x in cat.count_support(compressed, sets, "mult").collect()}
        assert _shuffled(spark) - after > 5 * (after - before)
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
        compressed.unpersist()


def test_first_step_by_hash_shuffles_no_pairs_by_name(spark, monkeypatch):
    r = random.Random(8)
    rows = [[f"{r.randrange(30):03d}" for _ in range(r.randint(0, 8))] + [f"{'x' * 200}{n}_{i}" for i in range(r.randint(0, 40))] for n in range(120)]
    rows = [sorted(set(x)) for x in rows]
    compressed = encode.compress(db(spark, rows + rows[:20])).persist()
    compressed.count()
    written, found = [], []
    for named in (10**6, 0):
        monkeypatch.setattr(structural, "NAMED_ITEMS", named)
        before = _shuffled(spark)
        found.append(sorted((x["a"], x["b"], x["support"], round(x["gain"], 9)) for x in structural.first_step_gains(compressed, 140).collect()))
        written.append(_shuffled(spark) - before)
    compressed.unpersist()
    assert found[0] == found[1] and len(found[0]) > 10_000
    assert written[1] < written[0] / 3


def test_code_table_decides_many_candidates_a_pass(spark, monkeypatch):
    rng = random.Random(3)
    kinds = [[f"w{i:02}" for i in range(g, g + 4)] for g in range(0, 80, 4)]
    lists = [sorted({x for k in rng.sample(kinds, 4) for x in k if rng.random() < 0.8}) for _ in range(300)]
    rows = spark.createDataFrame(list(enumerate(lists)), "tid long, items array<string>")
    met = {c: sum(set(c) <= set(x) for x in lists) for k in kinds for n in (2, 3) for c in itertools.combinations(k, n)}
    order = sorted(((c, n) for c, n in met.items() if n), key=lambda c: (-c[1], -len(c[0]), "|".join(c[0])))[:60]
    # One at a time, by plain covers.
    table = {i: ((i,), sum(i in x for x in lists)) for i in {i for x in lists for i in x}}

    def used(table):
        sets, out = [(k, set(table[k][0])) for k in codetable.cover_order(table)], {}
        for x in lists:
            left = set(x)
            for k, s in sets:
                if s <= left:
                    out[k], left = out.get(k, 0) + 1, left - s
        return out

    single = used(table)
    bits = codetable.total_bits(table, single, single)
    for c, n in order:
        tried = {**table, "|".join(c): (c, n)}
        if (b := codetable.total_bits(tried, used(tried), single)) < bits - 1e-9:
            table, bits = tried, b
    passes, real = [], codetable.deltas
    monkeypatch.setattr(codetable, "deltas", lambda *a, **k: passes.append(1) or real(*a, **k))
    monkeypatch.setattr(codetable, "PACKED_ROWS", 50)
    assert codetable.mine(rows, order).usage == used(table) and not passes
    monkeypatch.setattr(codetable, "FEW_BASKETS", 0)
    got = codetable.mine(rows, order)
    accepted = len(table) - len(single)
    assert accepted > 20 and set(got.table) == set(table) and got.bits == pytest.approx(bits) and got.usage == used(table)
    assert len(passes) < accepted


def test_rounds_of_em_read_the_baskets_once(spark, monkeypatch):
    r = random.Random(5)
    rows = [(n, sorted({*r.sample("abcdefgh", r.randint(1, 4)), *(("p", "q") if r.random() < 0.4 else ()), *(("q", "x", "y") if r.random() < 0.3 else ())})) for n in range(300)]
    compressed, m, supports = miner.prepared(spark.createDataFrame(rows, "tid long, items array<string>"))
    start = cat.from_support(sorted(supports.items()), m)
    start |= {s.key: s for s in (Itemset.of(("p", "q"), 0.3, 0, 120), Itemset.of(("q", "x", "y"), 0.2, 0, 80), Itemset.of(("a", "b"), 0.1, 0, 30))}
    slow = em.hard_em(compressed, start, m, 0.0, 4, kernel="lazy_heap")
    for most in (20_000, 0):
        monkeypatch.setattr(em, "FRAGMENTS", most)
        fast = em.hard_em(compressed, start, m, 0.0, 4, kernel="lazy_heap", supports=supports)
        assert fast.catalog == slow.catalog and fast.profit == pytest.approx(slow.profit)
    # Where a set is missing, baskets that cannot be covered use nothing, as before.
    short = {k: s for k, s in start.items() if k not in ("x", "c")}
    assert em.hard_em(compressed, short, m, 0.0, 2, kernel="lazy_heap", supports=supports).catalog == em.hard_em(compressed, short, m, 0.0, 2, kernel="lazy_heap").catalog
    # The gains of candidates against covers of whole baskets.
    queue = candidates.build_queue(compressed, slow.catalog, set(), supports)
    got = structural.deltas(compressed, slow.catalog, queue)
    index = cover.Index([*slow.catalog.values(), *(Itemset.of(c.items, 1.0, 0, c.support) for c in queue)])
    want = {c.key: {} for c in queue}
    for _, items in rows:
        basket = frozenset(items)
        known = [k for k in index.applicable(basket) if k in slow.catalog]
        for c in queue:
            if basket.issuperset(c.items):
                for used, sign in ((index.lazy(basket, [*known, c.key], c.key), 1), (index.lazy(basket, known), -1)):
                    for k in used:
                        want[c.key][k] = want[c.key].get(k, 0) + sign
    assert got == {k: {s: n for s, n in x.items() if n} for k, x in want.items()}
    monkeypatch.setattr(em, "FRAGMENTS", 20_000)
    passes, real = [], em.e_step
    monkeypatch.setattr(em, "e_step", lambda *a, **k: passes.append(1) or real(*a, **k))
    miner.mine(compressed.select("items"), max_iter=3)
    assert not passes


def test_counting_many_sets_of_short_baskets(spark):
    """Both ways to look sets up count alike; the level-wise queue equals plain counts."""
    r = random.Random(9)
    lists = [sorted(r.sample("abcdefghijkl", r.randint(0, 7))) for _ in range(200)]
    compressed, m, supports = miner.prepared(spark.createDataFrame(list(enumerate(lists)), "tid long, items array<string>"))
    sets = [c for s in (1, 2, 3, 4) for c in itertools.combinations("abcdefghijkl", s)]
    want = {"|".join(c): n for c in sets if (n := sum(set(c) <= set(x) for x in lists))}
    assert candidates.counted(compressed, sets, supports) == want
    few = sets[100:103]
    assert candidates.counted(compressed, few, supports) == {k: want[k] for c in few if (k := "|".join(c)) in want}
    queue = candidates.apriori_queue(compressed, supports, 2)
    assert {c.key: c.support for c in queue} == {k: n for k, n in want.items() if n >= 2 and "|" in k}


def test_held_baskets_give_the_same_lists(spark, monkeypatch):
    """Baskets of few items that the driver holds, in one word or two, give what jobs give, and need no job for a pass."""
    r = random.Random(23)
    many = [f"i{n}" for n in range(70)]
    bundles = [r.sample(many, 3) for _ in range(4)]
    for lists in ([sorted({*r.sample("abcdefghij", r.randint(0, 5)), *r.choice(["ab", "cde", ""])}) for _ in range(300)], [sorted({*r.sample(many, 2), *r.choice(bundles)}) for _ in range(400)]):
        baskets = spark.createDataFrame(list(enumerate(lists)), "tid long, items array<string>").persist()

        def results():
            given = miner.ready(baskets)
            mined = miner.mine(given, 6)
            common = frequent.commonest(given, 0.01, 60)
            table, pairs = codetable.mine(given, common), codetable.mine_pairs(given, 4)
            return (
                {k: (s.usage, s.support) for k, s in mined.catalog.items()}, [(t["tried"], t["passes"], t["accepted"]) for t in mined.trace], round(mined.profit, 9), sorted(map(tuple, common.select("key", "size", "support").collect())),
                list(table.table), table.usage, round(table.bits, 6), list(pairs.table), pairs.usage, round(pairs.bits, 6), maxent.mine(given, 4, 0.02)[1], [tuple(x) for x in frequent.chi2_list(given, 0.02, 5, 60).select("rank", "itemset", "support").collect()],
            )

        got = results()
        with monkeypatch.context() as m:
            m.setattr(miner, "held", lambda *a: None)
            m.setattr(codetable, "held", lambda *a: None)
            assert got == results()
        with monkeypatch.context() as m:
            for module, name in ((structural, "deltas"), (em, "fragments"), (candidates, "counted"), (maxent, "counted"), (codetable, "row_deltas"), (codetable, "pair_gains"), (frequent, "frequent")):
                m.setattr(module, name, lambda *a, name=name, **k: pytest.fail(name))
            assert got == results()


def prepared_times(monkeypatch):
    times, real = [], miner.prepared
    monkeypatch.setattr(miner, "prepared", lambda baskets: times.append(1) or real(baskets))
    return times


def test_mentions_prepare_baskets_once(spark, small, monkeypatch):
    times = prepared_times(monkeypatch)
    assert workloads.mentions_over_time(spark, small, k=3, max_iter=2, methods=("cover", "maxent", "code_pairs")).count() and len(times) == 1


def test_rank_compare_prepares_baskets_once(spark, small, monkeypatch):
    times = prepared_times(monkeypatch)
    assert workloads.rank_compare(spark, small, methods=("cover", "maxent", "code_pairs"), k=5, max_iter=2).count() and len(times) == 1


def test_self_recovery_prepares_baskets_once(spark, small, monkeypatch):
    times = prepared_times(monkeypatch)
    assert workloads.self_recovery(spark, small, n=300, methods=("cover", "maxent"), max_iter=2, k=5).count() == 22 and len(times) == 2


def test_parts_of_wide_baskets_are_held(spark, monkeypatch):
    """Of more items than the driver holds, those of frequent sets and candidates are few: lists need no job for them."""
    r = random.Random(31)
    lists = [sorted({*r.sample("abcdefgh", r.randint(0, 5)), *(f"w{r.randrange(400)}" for _ in range(3))}) for _ in range(300)]
    baskets = spark.createDataFrame(list(enumerate(lists)), "tid long, items array<string>").persist()

    def results():
        given = miner.ready(baskets)
        assert given.near is None
        common = frequent.commonest(given, 0.05, 80)
        table = codetable.mine(given, frequent.closed(common))
        return sorted(map(tuple, common.select("key", "support").collect())), list(table.table), table.usage, round(table.bits, 6), maxent.mine(given, 4, 0.05)[1]

    got = results()
    with monkeypatch.context() as m:
        m.setattr(miner, "held", lambda *a: None)
        m.setattr(codetable, "held", lambda *a: None)
        assert got == results()
    for module, name in ((candidates, "counted"), (maxent, "counted"), (codetable, "row_deltas"), (codetable, "deltas"), (frequent, "frequent")):
        monkeypatch.setattr(module, name, lambda *a, name=name, **k: pytest.fail(name))
    assert got == results()
