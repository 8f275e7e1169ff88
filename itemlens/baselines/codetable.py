"""Code tables: itemsets with code lengths by usage, covering baskets without overlap.

Cover order is by size, then support, both falling, then key.  Total length = the data under the
codes + the table itself, where a set costs its own code and its items in the singleton-only code.
"""

from __future__ import annotations

import itertools
import math
from bisect import bisect_left, insort
from collections.abc import Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.catalog import to_df, Itemset
from ..operators.held import ROWS, Held, held, words_of
from ..operators.miner import Ready, ready

#: Sets by key: (items, support).
Table = dict[str, tuple[tuple[str, ...], int]]


@dataclass
class CodeTable:
    table: Table
    usage: dict[str, int]
    bits: float
    m: int

    def to_df(self, spark):
        total = sum(self.usage.values())
        rows = [
            (k, list(items), len(items), support, u, -math.log2(u / total) if u else None)
            for k, (items, support) in self.table.items()
            if (u := self.usage.get(k, 0)) or len(items) == 1
        ]
        return spark.createDataFrame(rows, "key string, items array<string>, size int, support long, usage long, bits double")


def cover_order(table: Table) -> list[str]:
    return sorted(table, key=lambda k: (-len(table[k][0]), -table[k][1], k))


def cover(baskets: DataFrame, table: Table, shown: frozenset[str] | None = None) -> DataFrame:
    """baskets with `cover`: sets in table order, each taken if all its items are still uncovered; only those `shown` are written, if given."""
    spark = baskets.sparkSession
    shared = spark.sparkContext.broadcast(([(k, frozenset(table[k][0])) for k in cover_order(table) if len(table[k][0]) > 1], shown))
    names = [f.name for f in baskets.schema]
    at = names.index("items")

    def run(batches):
        sets, only = shared.value
        by_item: dict[str, list[int]] = {}
        for n, (_, items) in enumerate(sets):
            by_item.setdefault(min(items), []).append(n)
        for batch in batches:
            out = []
            for items in batch.column(at).to_pylist():
                left, used = set(items), []
                for n in sorted(n for i in items for n in by_item.get(i, ())):
                    if sets[n][1] <= left:
                        used.append(sets[n][0])
                        left -= sets[n][1]
                whole = used + sorted(left)
                out.append(whole if only is None else [k for k in whole if k in only])
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(out, pa.list_(pa.string()))], [*names, "cover"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in baskets.schema)
    return baskets.mapInArrow(run, f"{fields}, cover array<string>")


def native_cover(baskets: DataFrame, table: Table) -> DataFrame:
    """The same as one fold over the ordered table, for short tables; stays in the JVM."""
    spark = baskets.sparkSession
    ordered = cover_order({k: v for k, v in table.items() if len(v[0]) > 1})
    sets = to_df(spark, {k: Itemset.of(table[k][0], 0.0, support=table[k][1]) for k in ordered}).agg(
        F.array_sort(F.collect_list(F.struct((-F.col("size")).alias("a"), (-F.col("support")).alias("b"), F.col("key").alias("k"), F.col("items").alias("s")))).alias("_t")
    )
    start = F.struct(F.col("items").alias("left"), F.array().cast("array<string>").alias("cover"))
    step = lambda st, s: F.when(
        F.size(F.array_except(s["s"], st["left"])) == 0, F.struct(F.array_except(st["left"], s["s"]).alias("left"), F.array_append(st["cover"], s["k"]).alias("cover"))
    ).otherwise(st)
    done = baskets.crossJoin(F.broadcast(sets)).withColumn("_c", F.aggregate("_t", start, step))
    return done.withColumn("cover", F.concat("_c.cover", F.array_sort("_c.left"))).drop("_t", "_c")


#: Pairs of table sets that the pair search fetches at once, those of highest estimated gain first.
PAIRS_BLOCK = 20_000
#: The pair search looks at the pairs of so many sets of highest usage first, then at those of this many times as many, until all sets.
FIRST_SETS, MORE_SETS = 512, 8
#: Candidates that are scored in one pass: as many to begin with, then twice as many each time, up to the second number.
FIRST_BATCH, LARGEST_BATCH = 32, 1024
#: As many candidates at most are tried in one pass as if all before them had joined.
LONGEST_CHAIN = 32
#: Fewer distinct parts of baskets than this are tried basket by basket.
FEW_BASKETS = 10_000
#: So many parts of baskets travel in one row when packed.
PACKED_ROWS = 1 << 14


def usages(compressed: DataFrame, table: Table) -> dict[str, int]:
    covered = cover(compressed, table).select(F.explode("cover").alias("k"), "mult")
    return {r["k"]: r["n"] for r in covered.groupBy("k").agg(F.sum("mult").alias("n")).toLocalIterator()}


def pair_gains(compressed: DataFrame, table: Table, used: dict[str, int], least: int = 0) -> DataFrame:
    """(a, b, n, gain) of all pairs of table sets with a usage of `least` or more that are used together and whose estimated gain is positive."""
    spark, total = compressed.sparkSession, float(sum(used.values()))
    shown = frozenset(k for k, u in used.items() if u >= least) if least else None
    uses = spark.createDataFrame([(k, float(u)) for k, u in used.items()], "k string, u double")
    covers = cover(compressed, table, shown).select(F.array_sort("cover").alias("c"), "mult")
    flat = covers.select("c", "mult", F.posexplode("c").alias("i", "a")).select("mult", "a", F.explode(F.slice("c", F.col("i") + 2, F.size("c"))).alias("b"))
    met = flat.groupBy("a", "b").agg(F.sum("mult").alias("n"))
    met = met.join(uses.select(F.col("k").alias("a"), F.col("u").alias("x")), "a").join(uses.select(F.col("k").alias("b"), F.col("u").alias("y")), "b")
    part = lambda n: F.when(n > 0, n * F.log2(n)).otherwise(0.0)
    xy, t = F.col("n").cast("double"), F.lit(total)
    gain = (part(t) - part(F.col("x")) - part(F.col("y"))) - (part(t - xy) - part(F.col("x") - xy) - part(F.col("y") - xy) - part(xy))
    return met.select("a", "b", "n", gain.alias("gain")).where("gain > 0")


def descending(gains: DataFrame, block: int | None = None) -> Iterator:
    """All pairs by falling gain, ties by a and b; they come to the driver in blocks, each only when asked for."""
    block, last = block or PAIRS_BLOCK, None
    while True:
        rest = gains
        if last is not None:
            tie = (F.col("gain") == last["gain"]) & ((F.col("a") > last["a"]) | (F.col("a") == last["a"]) & (F.col("b") > last["b"]))
            rest = gains.where((F.col("gain") < last["gain"]) | tie)
        rows = rest.orderBy(F.desc("gain"), "a", "b").limit(block).collect()
        yield from rows
        if len(rows) < block:
            return
        last = rows[-1]


def falling_pairs(compressed: DataFrame, table: Table, used: dict[str, int]) -> Iterator:
    """All pairs of positive estimated gain, falling, as `descending` gives them, without counting the pairs of seldom used sets before they are due.

    The gain of a pair grows with the common usage once it is positive, so a set of usage u is in no
    pair of more than T log T - (T - u) log(T - u) - u log u bits, T being the total.  Pairs above that
    bound are complete as soon as the sets used more often have been counted.
    """
    total, falling = sum(used.values()), sorted(used.values(), reverse=True)
    part = lambda n: n * math.log2(n) if n > 0 else 0.0
    size, above = FIRST_SETS, None
    while True:
        rest = falling[size] if size < len(falling) else 0
        # A little more than the bound, for sums are rounded.
        cut = (part(total) - part(total - rest) - part(rest)) * (1 + 1e-9) + 1e-6 if 0 < rest < total / 2 else 0.0
        if cut or size >= len(falling):
            gains = pair_gains(compressed, table, used, rest + 1 if cut else 0).where(F.col("gain") > cut)
            gains = (gains if above is None else gains.where(F.col("gain") <= above)).persist()
            try:
                yield from descending(gains)
            finally:
                gains.unpersist()
            above = cut
        if size >= len(falling):
            return
        size *= MORE_SETS


#: Covers of so many baskets that the driver holds are counted at once.
COVERS_AT_ONCE = 1 << 12


class HeldPairs:
    """How often the sets of a growing table are used together in baskets that the driver holds.

    A set that joins changes the covers of the baskets that it fits into at its turn, and only those are counted anew.
    """

    def __init__(self, near: Held, table: Table):
        self.near, self.keys = near, list(near.items)
        self.met = np.zeros((len(self.keys), len(self.keys)))
        self.sets: list[Placed] = []
        for start in range(0, len(near.mult), ROWS):
            bits = near.columns(start).astype(float)
            self.met += (bits * near.mult[start : start + ROWS, None]).T @ bits
        for k in cover_order(table):
            if len(table[k][0]) > 1:
                self.join(k, *table[k])

    def join(self, key: str, items: tuple[str, ...], support: int) -> None:
        new = placed(self.near, key, items, support)
        turn = bisect_left(self.sets, new[0], key=lambda s: s[0])
        self.keys.append(key)
        self.met = np.pad(self.met, (0, 1))
        at = {k: n for n, k in enumerate(self.keys)}
        # What comes before the set's turn is the same with and without it.
        first = [(at[k], content) for (_, _, k), content in self.sets[:turn]]
        later = [(at[k], content) for (_, _, k), content in self.sets[turn:]]
        rows = np.flatnonzero(self.near.having(items))
        for start in range(0, len(rows), COVERS_AT_ONCE):
            part = rows[start : start + COVERS_AT_ONCE]
            left = self.near.words[:, part]
            shared = [(n, take(left, content)) for n, content in first]
            fits = np.flatnonzero(self.near.having(items, left))
            left, mult, shared = left[:, fits], self.near.mult[part[fits]], [(n, used[fits]) for n, used in shared]
            if len(fits):
                self._add(left.copy(), mult, shared, later, -1)
                self._add(left, mult, shared, [(at[key], new[1]), *later], 1)
        self.sets.insert(turn, new)

    def _add(self, left: np.ndarray, mult: np.ndarray, shared: list[tuple[int, np.ndarray]], later: list, sign: int) -> None:
        used = [*shared, *((n, take(left, content)) for n, content in later)]
        used = [(n, rows) for n, rows in used if rows.any()]
        bits = Held(self.near.items, left, mult).columns(0)
        single = np.flatnonzero(bits.any(axis=0))
        taken = np.concatenate([bits[:, single], np.array([rows for _, rows in used], np.uint8).reshape(len(used), len(mult)).T], axis=1).astype(float)
        at = np.array([*single.tolist(), *(n for n, _ in used)])
        self.met[np.ix_(at, at)] += sign * ((taken * mult[:, None]).T @ taken)

    def falling(self, used: dict[str, int]) -> Iterator[dict]:
        """All pairs of positive estimated gain, falling, as `descending` gives them."""
        x, y = np.nonzero(np.triu(self.met, 1))
        n, usage, total = self.met[x, y], np.array([used.get(k, 0) for k in self.keys], float), float(sum(used.values()))
        part = lambda n: n * np.log2(np.where(n > 0, n, 1.0))
        order = {k: n for n, k in enumerate(sorted(self.keys))}
        place = np.array([order[k] for k in self.keys])
        a, b = np.where(place[x] < place[y], (x, y), (y, x))
        gain = (part(np.float64(total)) - part(usage[a]) - part(usage[b])) - (part(total - n) - part(usage[a] - n) - part(usage[b] - n) - part(n))
        rows = np.flatnonzero(gain > 0)
        for r in rows[np.lexsort((place[b[rows]], place[a[rows]], -gain[rows]))].tolist():
            yield {"a": self.keys[a[r]], "b": self.keys[b[r]], "n": int(n[r]), "gain": float(gain[r])}


def take(left: np.ndarray, content: list[tuple[int, np.uint64]]) -> np.ndarray:
    """Which columns of bits hold all of the content, which is then taken out of them."""
    fits = None
    for w, x in content:
        here = (left[w] & x) == x
        fits = here if fits is None else fits & here
    if fits.any():
        for w, x in content:
            left[w] ^= fits * x
    return fits


def packed(compressed: DataFrame, items: list[str]) -> DataFrame:
    """(words, mults): the distinct parts of baskets within `items`, PACKED_ROWS or fewer in a row.  Sets of these items alone cover them as they cover the baskets."""
    shared = compressed.sparkSession.sparkContext.broadcast(sorted(items))

    def project(batches):
        place = pa.array(shared.value, pa.string())
        for b in batches:
            words = words_of(b.column(0), place)
            data, size = words.tobytes(), 8 * words.shape[1]
            yield pa.RecordBatch.from_arrays([pa.array([data[n : n + size] for n in range(0, len(data), size)], pa.binary()), b.column(1)], ["bits", "mult"])

    def pack(batches):
        for b in batches:
            for start in range(0, b.num_rows, PACKED_ROWS):
                part = b.slice(start, PACKED_ROWS)
                mults = part.column(1).to_numpy().astype("<i8").tobytes()
                yield pa.RecordBatch.from_arrays([pa.array([b"".join(part.column(0).to_pylist())], pa.binary()), pa.array([mults], pa.binary())], ["words", "mults"])

    merged = compressed.select("items", "mult").mapInArrow(project, "bits binary, mult long").groupBy("bits").agg(F.sum("mult").alias("mult"))
    return merged.mapInArrow(pack, "words binary, mults binary")


def deltas(compressed: DataFrame, table: Table, batch: list[tuple[str, tuple[str, ...], int]], within: list[str] | None = None, chain: int = 0) -> list[dict[str, int]]:
    """For each candidate (key, items, support), how the usage of each set changes if it joins the table; one pass for all.

    compressed: (items, mult), or what `packed` made of it for the items `within`.  The first `chain`
    candidates are also tried in the table that all before them have joined: as many more results.
    """
    spark = compressed.sparkSession
    spot = lambda key, items, support: (-len(items), -support, key)
    sets = sorted((spot(k, items, support), items) for k, (items, support) in table.items() if len(items) > 1)
    new = sorted((spot(key, items, support), items, n) for n, (key, items, support) in enumerate(batch))
    chain = min(chain, len(batch))
    within = sorted({i for s in (*sets, *new) for i in s[1]}) if within is None else sorted(within)
    bit = {i: divmod(n, 64) for n, i in enumerate(within)}

    def mask(items) -> list[tuple[int, int]]:
        of: dict[int, int] = {}
        for i in items:
            of[bit[i][0]] = of.get(bit[i][0], 0) | 1 << bit[i][1]
        return sorted(of.items())

    spots = [s for s, _ in sets]
    tables = [[(n, s[2], bisect_left(spots, s), mask(items)) for s, items, n in new]]
    for n in range(chain):
        # The places at which those before it have joined, and its own.
        before = sorted([*spots, *(spot(*c) for c in batch[:n])])
        joined = [(bisect_left(before, spot(*batch[n - 1])), batch[n - 1][0], mask(batch[n - 1][1]))] if n else []
        tables.append([*joined, (len(batch) + n, batch[n][0], bisect_left(before, spot(*batch[n])), mask(batch[n][1]))])
    shared = spark.sparkContext.broadcast((within, [(s[2], mask(items)) for s, items in sets], tables))
    names = ["words", "mults"] if "words" in compressed.columns else ["items", "mult"]

    def run(batches):
        items, known, tables = shared.value
        wide_mask = lambda m: [(w, np.uint64(x)) for w, x in m]
        known, trials = [(k, wide_mask(m)) for k, m in known], []
        for table in tables:
            for at, k, m in (x for x in table if len(x) == 3):
                known = [*known[:at], (k, wide_mask(m)), *known[at:]]
            trials.append((known, [(n, k, turn, wide_mask(m)) for n, k, turn, m in (x for x in table if len(x) == 4)]))
        place, wide = pa.array(items, pa.string()), -(-max(1, len(items)) // 64)
        sums: dict[tuple[int, str], int] = {}

        def add(n: int, key: str, d: int) -> None:
            if d:
                sums[n, key] = sums.get((n, key), 0) + d

        def fits(left, content):
            out = None
            for w, x in content:
                here = (left[w] & x) == x
                out = here if out is None else out & here
            return out

        def take(left, content, rows) -> None:
            for w, x in content:
                left[w] ^= rows * x

        def score(words, mult, known, tried) -> None:
            start = np.array(words.T, order="C")
            # First which baskets use each set, then once more in the same order: a candidate changes nothing before its turn.
            left, taken = start.copy(), []
            for _, content in known:
                taken.append(fits(left, content))
                take(left, content, taken[-1])
            last, left, turn = left, start, 0
            for n, key, at, content in tried:
                for s in range(turn, at):
                    take(left, known[s][1], taken[s])
                turn = at
                rows = np.flatnonzero(fits(left, content))
                if not len(rows):
                    continue
                after, m = left[:, rows], mult[rows]
                take(after, content, np.True_)
                add(n, key, int(m.sum()))
                for s in range(at, len(known)):
                    now, was = fits(after, known[s][1]), taken[s][rows]
                    take(after, known[s][1], now)
                    if (now != was).any():
                        add(n, known[s][0], int(m[now].sum() - m[was].sum()))
                for w in range(wide):
                    end = last[w][rows]
                    changed = int(np.bitwise_or.reduce(after[w] ^ end))
                    while changed:
                        b = (changed & -changed).bit_length() - 1
                        changed &= changed - 1
                        one = np.uint64(1 << b)
                        add(n, items[64 * w + b], int(m[(after[w] & one) > 0].sum() - m[(end & one) > 0].sum()))

        for b in batches:
            if names[0] == "words":
                for words, mults in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                    for trial in trials:
                        score(np.frombuffer(words, "<u8").reshape(-1, wide), np.frombuffer(mults, "<i8"), *trial)
            else:
                words = words_of(b.column(0), place)
                for trial in trials:
                    score(words, b.column(1).to_numpy(), *trial)
        rows = [(n, k, d) for (n, k), d in sums.items() if d]
        if rows:
            n, k, d = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(n, pa.int32()), pa.array(k), pa.array(d, pa.int64())], ["n", "k", "d"])

    parts = compressed.select(*names).mapInArrow(run, "n int, k string, d long")
    out: list[dict[str, int]] = [{} for _ in range(len(batch) + chain)]
    for r in parts.groupBy("n", "k").agg(F.sum("d").alias("d")).where("d <> 0").collect():
        out[r["n"]][r["k"]] = r["d"]
    shared.unpersist()
    return out


#: A set's place in the order of covers, and its bits.
Placed = tuple[tuple[int, int, str], list[tuple[int, np.uint64]]]


def placed(near: Held, key: str, items: tuple[str, ...], support: int) -> Placed:
    return (-len(items), -support, key), near.mask(items)


def held_order(near: Held, table: Table) -> list[Placed]:
    return sorted((placed(near, k, *s) for k, s in table.items() if len(s[0]) > 1), key=lambda s: s[0])


#: Bytes that the covers of held baskets may take while a batch of candidates is tried on them.
COVERS_BYTES = 64 << 20


class HeldCovers:
    """Which sets of a table, as `held_order` gives it, cover which baskets that the driver holds, and what is left of each basket."""

    def __init__(self, near: Held, sets: list[Placed]):
        self.left, self.taken = near.words.copy(), np.empty((len(sets), len(near.mult)), bool)
        self.masks = np.zeros((len(sets), len(near.words)), np.uint64)
        for n, (_, content) in enumerate(sets):
            self.taken[n] = take(self.left, content)
            for w, x in content:
                self.masks[n, w] = x

    def before(self, turn: int, rows: np.ndarray) -> np.ndarray:
        """What is left of baskets before a set's turn: what is left in the end and what the sets from then on take."""
        out, late = self.left[:, rows], self.taken[turn:, rows]
        for n in np.flatnonzero(late.any(axis=1)):
            for w in np.flatnonzero(self.masks[turn + n]):
                out[w] |= late[n] * self.masks[turn + n, w]
        return out

    def within(self, turn: int, items: np.ndarray) -> np.ndarray:
        """Which sets, from a turn on, hold none but the given items."""
        return ~(self.masks[turn:] & ~items).any(axis=1)


def held_delta(near: Held, sets: list[Placed], candidate: tuple[str, tuple[str, ...], int], covers: HeldCovers | None = None) -> dict[str, int]:
    """The same for one candidate over baskets that the driver holds; only those that hold it are covered.  sets: the table as `held_order` gives it; covers: its covers, if known."""
    key, items, support = candidate
    turn = bisect_left(sets, placed(near, *candidate)[0], key=lambda s: s[0])
    rows = near.having(items)
    if covers:
        rows, out = np.flatnonzero(rows), {}
        left, mult = covers.before(turn, rows), near.mult[rows]
    else:
        left, mult, out = near.words[:, rows], near.mult[rows], {}
        for _, content in sets[:turn]:
            take(left, content)
    fits = near.having(items, left)
    left, mult = left[:, fits], mult[fits]
    if not len(mult):
        return out
    after = left.copy()
    take(after, near.mask(items))
    out[key] = int(mult.sum())
    later = sets[turn:]
    if covers:
        # What is in none of these parts of baskets is not used with the candidate, nor was it without.
        later = [later[n] for n in np.flatnonzero(covers.within(turn, np.bitwise_or.reduce(left, axis=1)))]
    for (_, _, k), content in later:
        was, now = take(left, content), take(after, content)
        if (now ^ was).any() and (d := int(mult[now].sum() - mult[was].sum())):
            out[k] = d
    moved = np.bitwise_or.reduce(left ^ after, axis=1)[:, None]
    for i in near.names(moved)[0]:
        w, b = near.bit[i]
        x = np.uint64(1 << b)
        if d := int(mult[(after[w] & x) > 0].sum() - mult[(left[w] & x) > 0].sum()):
            out[i] = d
    return out


def row_deltas(compressed: DataFrame, table: Table, batch: list[tuple[str, tuple[str, ...], int]]) -> list[dict[str, int]]:
    """For each candidate (key, items, support), how the usage of each set changes if it joins the table; one pass for all, basket by basket: for few baskets and many sets."""
    spark = compressed.sparkSession
    order = {k: n for n, k in enumerate(cover_order(table))}
    place = lambda k: (-len(table[k][0]), -table[k][1], k)
    shared = spark.sparkContext.broadcast(([(place(k), frozenset(table[k][0])) for k in order if len(table[k][0]) > 1], [((-len(items), -support, key), frozenset(items)) for key, items, support in batch]))

    def run(batches):
        sets, new = shared.value
        by_item: dict[str, list[int]] = {}
        for n, (_, items) in enumerate(sets):
            by_item.setdefault(min(items), []).append(n)
        new_by_item: dict[str, list[int]] = {}
        for n, (_, items) in enumerate(new):
            new_by_item.setdefault(min(items), []).append(n)

        sums: dict[tuple[int, str], int] = {}
        for b in batches:
            for items, mult in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                basket = frozenset(items)
                mine = [n for i in basket for n in new_by_item.get(i, ()) if new[n][1] <= basket]
                if not mine:
                    continue
                usable = sorted((sets[n] for i in basket for n in by_item.get(i, ()) if sets[n][1] <= basket), key=lambda s: s[0])
                # What is left before each set's turn: a candidate changes nothing before its own.
                turns, lefts, taken = [s[0] for s in usable], [basket], []
                for n, (spot, content) in enumerate(usable):
                    fits = content <= lefts[-1]
                    lefts.append(lefts[-1] - content if fits else lefts[-1])
                    if fits:
                        taken.append((n, spot[2]))
                for n in mine:
                    spot, content = new[n]
                    turn = bisect_left(turns, spot)
                    if not content <= lefts[turn]:
                        continue
                    left, after = lefts[turn] - content, {spot[2]}
                    for later, other in usable[turn:]:
                        if other <= left:
                            after.add(later[2])
                            left -= other
                    before = {key for at, key in taken if at >= turn}
                    for keys, sign in ((after - before, mult), (before - after, -mult), (left - lefts[-1], mult), (lefts[-1] - left, -mult)):
                        for k in keys:
                            sums[n, k] = sums.get((n, k), 0) + sign
        rows = [(n, k, d) for (n, k), d in sums.items() if d]
        if rows:
            n, k, d = zip(*rows, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(n, pa.int32()), pa.array(k), pa.array(d, pa.int64())], ["n", "k", "d"])

    parts = compressed.select("items", "mult").mapInArrow(run, "n int, k string, d long")
    out: list[dict[str, int]] = [{} for _ in batch]
    for r in parts.groupBy("n", "k").agg(F.sum("d").alias("d")).where("d <> 0").toLocalIterator():
        out[r["n"]][r["k"]] = r["d"]
    shared.unpersist()
    return out


def total_bits(table: Table, used: dict[str, int], single: dict[str, int]) -> float:
    """Data and table together; `single`: usage of items under the singleton-only table."""
    total, plain = sum(used.values()), sum(single.values())
    if not total:
        return 0.0
    bits = 0.0
    for k, u in used.items():
        if u:
            code = -math.log2(u / total)
            bits += u * code + code + sum(-math.log2(single[i] / plain) for i in table[k][0])
    return bits


def gap_of(table: Table, used: dict[str, int], single: dict[str, int], candidate: tuple[str, tuple[str, ...], int], change: dict[str, int], totals: tuple[int, int, int]) -> tuple[float, tuple[int, int, int]]:
    """By how much the total length changes with the candidate, and the totals then; only what changes is summed anew."""
    (key, items, _), (total, plain, kinds) = candidate, totals
    log = lambda n: math.log2(n) if n else 0.0
    # The total is (T + kinds) log T - sum of (u + 1) log u + the items of used sets.
    new_total, new_kinds, gap = total + sum(change.values()), kinds, 0.0
    for k, d in change.items():
        old = used.get(k, 0)
        now = old + d
        gap -= (now + 1) * log(now) - (old + 1) * log(old)
        if (now > 0) != (old > 0):
            sign = 1 if now > 0 else -1
            new_kinds += sign
            gap += sign * sum(-math.log2(single[i] / plain) for i in (items if k == key else table[k][0]))
    return gap + (new_total + new_kinds) * log(new_total) - (total + kinds) * log(total), (new_total, plain, new_kinds)


def joined(table: Table, used: dict[str, int], single: dict[str, int], bits: float, candidate: tuple[str, tuple[str, ...], int], change: dict[str, int], totals: tuple[int, int, int]):
    """(table, usage, bits) with the candidate, if it lowers the total.  totals: the usage of the table and of single items, and how many sets are used."""
    if not change:
        return None
    key, items, support = candidate
    gap, _ = gap_of(table, used, single, candidate, change, totals)
    if gap > 1e-6:
        return None
    tried = {**table, key: (items, support)}
    new_used = {k: u for k in {**used, **change} if (u := used.get(k, 0) + change.get(k, 0))}
    new_bits = total_bits(tried, new_used, single)
    return (tried, new_used, new_bits) if new_bits < bits - 1e-9 else None


def _totals(used: dict[str, int], single: dict[str, int]) -> tuple[int, int, int]:
    return sum(used.values()), sum(single.values()), sum(u > 0 for u in used.values())


def first_shorter(compressed: DataFrame | Held, table: Table, used: dict[str, int], single: dict[str, int], bits: float, batch: list[tuple[str, tuple[str, ...], int]]):
    """Of a batch in its order, the first candidate that lowers the total: (place, table, usage, bits), or None."""
    totals = _totals(used, single)
    if isinstance(compressed, Held):
        sets = held_order(compressed, table)
        # For a few candidates, those that hold them are covered; for many, all baskets once.
        covers = HeldCovers(compressed, sets) if len(batch) > FIRST_BATCH and len(sets) * len(compressed.mult) <= COVERS_BYTES else None
        changes = (held_delta(compressed, sets, c, covers) for c in batch)
    else:
        changes = deltas(compressed, table, batch)
    for n, change in enumerate(changes):
        if (found := joined(table, used, single, bits, batch[n], change, totals)) is not None:
            return n, *found
    return None


def first_run(rows: DataFrame | Held, table: Table, used: dict[str, int], single: dict[str, int], bits: float, batch: list[tuple[str, tuple[str, ...], int]], within: list[str] | None, chain: int):
    """As many decisions, in order, as one pass allows: (decided, accepted, table, usage, bits).

    Either the first candidates, up to `chain`, join one after another until one does not; or, where
    the first does not, all up to the first that does.  rows: packed `within` items, or the baskets
    themselves if that is None.
    """
    if isinstance(rows, Held):
        # Without a job for each pass, all are decided one by one.
        sets, totals, accepted, n = held_order(rows, table), _totals(used, single), 0, 0
        table, used = dict(table), dict(used)
        unsure = max(1e-6, 1e-13 * totals[0] * math.log2(totals[0] + 2))
        for n, candidate in enumerate(batch, 1):
            change = held_delta(rows, sets, candidate)
            gap, after = gap_of(table, used, single, candidate, change, totals) if change else (math.inf, totals)
            # Where rounding could decide, the total is summed anew.
            if gap > 1e-6 or gap > -unsure and joined(table, used, single, total_bits(table, used, single), candidate, change, totals) is None:
                continue
            table[candidate[0]] = candidate[1:]
            for k, d in change.items():
                used[k] = used.get(k, 0) + d
                if not used[k]:
                    del used[k]
            bits, totals, accepted = bits + gap, after, accepted + 1
            insort(sets, placed(rows, *candidate), key=lambda s: s[0])
            if chain == 1:
                break
        return n, accepted, table, used, bits
    chain = 0 if within is None else chain
    changes, state, n = row_deltas(rows, table, batch) if within is None else deltas(rows, table, batch, within, chain), (table, used, bits), 0
    while n < min(chain, len(batch)):
        found = joined(state[0], state[1], single, state[2], batch[n], changes[len(batch) + n], _totals(state[1], single))
        if found is None:
            break
        state, n = found, n + 1
    if n:
        return min(n + (n < chain), len(batch)), n, *state
    totals = _totals(used, single)
    for n, candidate in enumerate(batch):
        if (found := joined(table, used, single, bits, candidate, changes[n], totals)) is not None:
            return n + 1, 1, *found
    return len(batch), 0, *state


def _start(baskets: DataFrame | Ready):
    given = ready(baskets)
    supports = given.supports
    table: Table = {i: ((i,), n) for i, n in supports.items()}
    used = dict(supports)
    return given.compressed, given.m, table, used, supports, total_bits(table, used, supports)


def mine(baskets: DataFrame | Ready, candidates: Iterable[tuple[tuple[str, ...], int]] | DataFrame, prune: bool = False) -> CodeTable:
    """From candidates (items, support): best support first, then size; each is kept if the total falls.

    A table of candidates is sorted by Spark and read part by part.  Candidates are scored in
    batches; results equal one-at-a-time trials.
    """
    given = ready(baskets)
    compressed, m, table, used, single, bits = _start(given)
    if isinstance(candidates, DataFrame):
        keyed = candidates.select("items", "support", F.size("items").alias("size"), F.array_join(F.array_sort("items"), "|").alias("key")).where("size > 1").persist()
        within = [r["i"] for r in keyed.select(F.explode("items").alias("i")).distinct().toLocalIterator()]
        ordered = ((tuple(r["items"]), r["support"]) for r in keyed.orderBy(F.desc("support"), F.desc("size"), "key").toLocalIterator())
    else:
        candidates = list(candidates)
        keyed, within = None, list({i for items, _ in candidates if len(items) > 1 for i in items})
        ordered = iter(sorted((c for c in candidates if len(c[0]) > 1), key=lambda c: (-c[1], -len(c[0]), "|".join(c[0]))))
    waiting: list[tuple[str, tuple[str, ...], int]] = []
    # Of many items, those in candidates may be few.
    near = given.near or held(compressed, within)
    size, chain = (FIRST_BATCH, 1) if prune or not near else (LARGEST_BATCH, LONGEST_CHAIN)
    rows = None if near else packed(compressed, within).persist()
    try:
        few = not near and (rows.agg(F.sum(F.length("mults"))).first()[0] or 0) < 8 * FEW_BASKETS
        tried_on, within = (near.within(within), within) if near else (compressed, None) if few else (rows, within)
        while True:
            for items, support in itertools.islice(ordered, max(0, size - len(waiting))):
                waiting.append(("|".join(sorted(items)), tuple(sorted(items)), support))
            if not waiting:
                break
            batch = waiting[:size]
            n, accepted, tried, new_used, new_bits = first_run(tried_on, table, used, single, bits, batch, within, 1 if prune else chain)
            waiting = waiting[n:]
            if near and not prune:
                table, used, bits = tried, new_used, new_bits
                continue
            if not accepted:
                size, chain = min(LARGEST_BATCH, 2 * size), 1
                continue
            size, chain = FIRST_BATCH, min(LONGEST_CHAIN, 2 * accepted + 2)
            fallen = [k for k in table if len(table[k][0]) > 1 and new_used.get(k, 0) < used.get(k, 0)]
            table, used, bits = tried, new_used, new_bits
            for k in sorted(fallen, key=lambda k: used.get(k, 0)) if prune else ():
                less = {x: v for x, v in table.items() if x != k}
                u = usages(compressed, less)
                if (b := total_bits(less, u, single)) < bits - 1e-9:
                    table, used, bits = less, u, b
    finally:
        for kept in (rows, keyed, None if given is baskets else compressed):
            if kept is not None:
                kept.unpersist()
    return CodeTable(table, used, total_bits(table, used, single) if near else bits, m)


def estimated_gain(x: int, y: int, xy: int, total: int) -> float:
    """Bits of data saved if the pair becomes a set of its own, by usages alone."""
    after = total - xy
    part = lambda n: n * math.log2(n) if n > 0 else 0.0
    return (part(total) - part(x) - part(y)) - (part(after) - part(x - xy) - part(y - xy) - part(xy))


def mine_pairs(baskets: DataFrame | Ready, max_iter: int = 100) -> CodeTable:
    """Without a list of candidates: pairs of table sets by estimated gain; the first that lowers the total joins.

    A round goes through all pairs of positive estimated gain before it ends the search.
    """
    given = ready(baskets)
    compressed, m, table, used, single, bits = _start(given)
    near = given.near
    together = near and HeldPairs(near, table)
    try:
        for _ in range(max_iter):
            pairs, seen, size, found = together.falling(used) if near else falling_pairs(compressed, table, used), set(table), FIRST_BATCH, None
            while found is None:
                batch: list[tuple[str, tuple[str, ...], int]] = []
                for r in pairs:
                    union = tuple(sorted({*table[r["a"]][0], *table[r["b"]][0]}))
                    if (key := "|".join(union)) not in seen:
                        seen.add(key)
                        batch.append((key, union, r["n"]))
                        if len(batch) == size:
                            break
                if not batch:
                    break
                found = first_shorter(near or compressed, table, used, single, bits, batch)
                size = min(LARGEST_BATCH, 2 * size)
            pairs.close()
            if found is None:
                break
            place, table, used, bits = found
            if near:
                together.join(*batch[place])
    finally:
        if given is not baskets:
            compressed.unpersist()
    return CodeTable(table, used, bits, m)


def ranked(found: CodeTable, k: int) -> list[tuple[str, ...]]:
    """Non-singletons by usage."""
    sets = [key for key, (items, _) in found.table.items() if len(items) > 1 and found.usage.get(key, 0)]
    return [found.table[key][0] for key in sorted(sets, key=lambda x: (-found.usage[x], x))[:k]]
