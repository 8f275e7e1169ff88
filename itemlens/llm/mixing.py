"""Mixing sources to target weights by entropy balancing.

A document can be taken at most twice: two copies, each in or out.  Of all rates (expected copies)
that give each source its target of words, those nearest in entropy to a fair choice tilt the odds
of each copy exponentially: rate = 2 / (1 + exp(-(multiplier of the source + slope * length))),
where length is the centred log of the document's size.  The slope belongs to one more constraint,
softened by a ridge: that the mix keeps the corpus's mean log length, word for word, so that a
source's weight does not change how long the texts are.  Multipliers and slope maximise one concave
dual.  Each Newton step sums gradient and curvature over the documents of every source on the
executors; the slope's step follows from the sources' sums (a Schur complement), so only one row
reaches the driver.  Rates then become whole copies, longest documents first, each source carrying
its rounding error on to shorter ones.
"""

from __future__ import annotations

import math

import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import common

WEIGHTS = (3, 1, 2)
SHARE = (3, 2)
MOST_COPIES = 2
#: Documents of one rounding group, about; a source of more is dealt out over several.
GROUP_ROWS = 2_000
#: Newton steps at most, the longest step, and the gap (as a share of a target) at which they end.
NEWTON_STEPS, LONGEST_STEP, SMALLEST_GAP = 60, 2.0, 1e-9
#: The ridge on the slope, for each word of the mix.
RIDGE = 0.05


def word_count(text: Column) -> Column:
    """Number of runs of anything but ASCII white space; null: 0."""
    return F.coalesce(F.size(F.filter(F.split(text, "[\\x20\\x09-\\x0D]+"), lambda w: w != "")), F.lit(0)).cast("long")


def source_targets(sizes: DataFrame) -> DataFrame:
    """(source, source_size, documents, target) from rows (source, size).

    Sources in code-point order, null last, weigh 3, 1, 2 repeatedly and share 150 % of all sizes.
    A target stops at twice its source's size and the excess is shared again: the level that fills
    all sources up is found from running sums over the sources by the level at which each is full.
    """
    per = sizes.groupBy("source").agg(F.sum("size").alias("source_size"), F.count("*").alias("documents"))
    order = Window.orderBy(F.col("source").asc_nulls_last())
    weight = F.element_at(F.array(*map(F.lit, WEIGHTS)), (F.pmod(F.row_number().over(order) - 1, F.lit(len(WEIGHTS))) + 1).cast("int"))
    weighted = per.withColumn("weight", weight).withColumn("full", MOST_COPIES * F.col("source_size"))
    by_level = Window.orderBy(F.col("full") / F.col("weight"), F.col("source").asc_nulls_last())
    everything = by_level.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    before = by_level.rowsBetween(Window.unboundedPreceding, -1)
    onwards = by_level.rowsBetween(0, Window.unboundedFollowing)
    # The level if all sources before this one are full and the rest share what is left.
    level = (F.sum("source_size").over(everything) * SHARE[0] / SHARE[1] - F.coalesce(F.sum("full").over(before), F.lit(0))) / F.sum("weight").over(onwards)
    levels = weighted.withColumn("level", level).withColumn("fits", F.col("level") * F.col("weight") <= F.col("full"))
    # The first source that is not full fixes the level.
    final = F.first(F.when(F.col("fits"), F.col("level")), ignorenulls=True).over(everything)
    target = F.least(F.col("full").cast("double"), F.coalesce(final * F.col("weight"), F.col("full").cast("double")))
    return levels.select("source", "source_size", "documents", target.alias("target"))


def length(size: Column, centre: float) -> Column:
    return F.log(size.cast("double")) - F.lit(centre)


def chance(multiplier: Column, slope: float, z: Column, full: Column) -> Column:
    """Of each of a document's two copies; sources whose target is all they can give take both."""
    return F.when(full, 1.0).otherwise(1 / (1 + F.exp(-(multiplier + F.lit(slope) * z))))


def balanced(sizes: DataFrame, targets: DataFrame) -> tuple[DataFrame, float, float]:
    """(key, source_size, documents, target, full, multiplier) of each source, the slope, and the centre of lengths.

    sizes: (source, size); targets: as source_targets gives them.  Equal sizes of a source are
    counted once with their number, which changes no sum.
    """
    counted = sizes.where("size > 0").groupBy(F.struct("source").alias("key"), "size").agg(F.count("*").alias("n"))
    cells = common.checkpointed(counted)
    total = cells.agg(F.sum(F.col("n") * F.col("size")).alias("words"), F.sum(F.col("n") * F.col("size") * F.log("size")).alias("logs")).first()
    centre = total["logs"] / total["words"] if total["words"] else 0.0
    full = F.col("target") >= MOST_COPIES * F.col("source_size") * (1 - 1e-12)
    state = common.checkpointed(targets.select(F.struct("source").alias("key"), "source_size", "documents", "target", full.alias("full"), F.lit(0.0).alias("multiplier")))
    if not total["words"]:
        return state, 0.0, centre
    ridge = RIDGE * (targets.agg(F.sum("target")).first()[0] or 0.0)
    slope = 0.0
    names = state.columns
    for _ in range(NEWTON_STEPS):
        z, words = length(F.col("size"), centre), F.col("n") * F.col("size")
        p = chance(F.col("multiplier"), slope, z, F.col("full"))
        curve = F.when(F.col("full"), 0.0).otherwise(MOST_COPIES * words * F.col("p") * (1 - F.col("p")))
        met = cells.join(state, "key").select(*names, z.alias("z"), p.alias("p"), words.alias("words"), "n", "size").withColumn("curve", curve)
        sums = met.groupBy("key").agg(
            *(F.first(c).alias(c) for c in names if c != "key"), F.sum(MOST_COPIES * F.col("words") * F.col("p")).alias("mixed"),
            F.sum(MOST_COPIES * F.col("words") * F.col("p") * F.col("z")).alias("lean"), F.sum("curve").alias("h"), F.sum(F.col("curve") * F.col("z")).alias("hz"), F.sum(F.col("curve") * F.col("z") * F.col("z")).alias("hzz"),
        )
        sums = common.checkpointed(sums)
        gap = F.when(F.col("full"), 0.0).otherwise(F.col("mixed") - F.col("target"))
        steep = F.greatest(F.col("h"), F.lit(1e-9))
        row = sums.agg(
            F.max(F.abs(gap) / F.greatest(F.col("target"), F.lit(1.0))).alias("worst"), F.sum("lean").alias("lean"), F.sum("hzz").alias("hzz"),
            F.sum(F.when(F.col("full"), 0.0).otherwise(F.col("hz") * gap / steep)).alias("cross"), F.sum(F.when(F.col("full"), 0.0).otherwise(F.col("hz") * F.col("hz") / steep)).alias("square"),
        ).first()
        pull = row["lean"] + ridge * slope
        if row["worst"] <= SMALLEST_GAP and abs(pull) <= SMALLEST_GAP * max(1.0, ridge):
            break
        turn = -(pull - row["cross"]) / max(row["hzz"] + ridge - row["square"], 1e-9)
        turn = max(-LONGEST_STEP / 2, min(LONGEST_STEP / 2, turn))
        step = -(gap + F.col("hz") * F.lit(turn)) / steep
        step = F.greatest(F.lit(-LONGEST_STEP), F.least(F.lit(LONGEST_STEP), step))
        moved = sums.select(*(c for c in names if c != "multiplier"), (F.col("multiplier") + F.when(F.col("full"), 0.0).otherwise(step)).alias("multiplier"))
        # Sources without words take no part.
        state, slope = moved, slope + turn
    else:
        raise RuntimeError(f"the balance did not settle in {NEWTON_STEPS} steps")
    still = targets.where("source_size = 0").select(F.struct("source").alias("key"), "source_size", "documents", "target", F.lit(False).alias("full"), F.lit(-math.inf).alias("multiplier"))
    return sums.select(*names).unionByName(still), slope, centre


def mixed(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, source, size, source_size, target, copies, taken (copies times size).

    Null sources are one source; null and empty texts have size 0 and copies 0; equal rows are
    treated alike but for rounding; a null doc_id is mixed like any other; the result does not depend
    on how rows are dealt.  No document is taken more than twice.  An empty table gives no rows.
    """
    sizes = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "source", word_count(F.col("text")).alias("size"))
    sizes = common.checkpointed(sizes)
    targets = common.checkpointed(source_targets(sizes))
    state, slope, centre = balanced(sizes, targets)
    parts = F.greatest(F.lit(1), F.ceil(F.col("documents") / GROUP_ROWS))
    info = common.checkpointed(state.select("key", "source_size", "target", "multiplier", "full", parts.alias("parts"), "documents"))
    joined = common.lookup_join(sizes.withColumn("key", F.struct("source")), info, "key", "documents", F.col("doc_id"))
    rate = F.when(F.col("size") > 0, MOST_COPIES * chance(F.col("multiplier"), slope, length(F.greatest(F.col("size"), F.lit(1)), centre), F.col("full"))).otherwise(0.0)
    # Rounded, so that the order in which sums were added cannot tip a copy.
    dealt = joined.withColumn("rate", F.round(rate, 6)).withColumn("part", F.pmod(F.xxhash64("doc_id", "size"), F.col("parts")))
    columns = ["doc_id", "source", "size", "source_size", "target", "rate", "part"]
    grouped = dealt.select(columns).repartition("source", "part").sortWithinPartitions("source", "part", F.col("size").desc(), F.xxhash64("doc_id"), "doc_id")
    return grouped.mapInArrow(_rounded, "doc_id long, source string, size long, source_size long, target double, copies long, taken long")


def _rounded(batches):
    """Copies for rows that come grouped and longest first: each is the whole number that keeps the running error least."""
    group, error = None, 0.0
    for batch in batches:
        rows = batch.to_pydict()
        copies = []
        for source, part, size, rate in zip(rows["source"], rows["part"], rows["size"], rows["rate"], strict=True):
            if group != (source, part):
                group, error = (source, part), 0.0
            n = int(rate)
            error += (rate - n) * size
            if size and n < MOST_COPIES and error >= size / 2:
                n, error = n + 1, error - size
            copies.append(n if size else 0)
        taken = [n * s for n, s in zip(copies, rows["size"], strict=True)]
        columns = [batch.column(batch.schema.get_field_index(c)) for c in ("doc_id", "source", "size", "source_size", "target")]
        yield pa.RecordBatch.from_arrays(
            [*columns, pa.array(copies, pa.int64()), pa.array(taken, pa.int64())], ["doc_id", "source", "size", "source_size", "target", "copies", "taken"]
        )
