"""Streaming counterparts: forming baskets, assigning covers, mentions, drift, refresh and alerts."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions.expressions import contains
from ..operators import em
from ..operators.catalog import Catalog, to_df
from ..operators.cover import cover
from ..operators.encode import compress


def source(spark: SparkSession, folder: str, like: DataFrame, files_per_trigger: int = 1, pattern: str = "*.parquet") -> DataFrame:
    """Rows of Parquet files as they arrive in a folder; event times get a time zone, which watermarks need."""
    rows = spark.readStream.schema(like.schema).option("maxFilesPerTrigger", files_per_trigger).option("pathGlobFilter", pattern).parquet(folder)
    return rows.withColumns({f.name: F.col(f.name).cast("timestamp") for f in like.schema if f.dataType.simpleString() == "timestamp_ntz"})


def assign(baskets: DataFrame, catalog: Catalog, uncovered: str = "flag", floor: float = 1e-6) -> DataFrame:
    """Covers of arriving baskets under a frozen catalog; stateless.  Unknown items leave a null cover, or are covered at a floor."""
    return cover(baskets, catalog, kernel="arrow", floor=None if uncovered == "flag" else floor)


def form_baskets(events: DataFrame, width: str = "1 day", slide: str | None = None, gap: str | None = None, late: str = "1 day") -> DataFrame:
    """(user_id, start, items) by tumbling or sliding window, or by session; later rows than `late` are dropped."""
    window = F.session_window("ts", gap) if gap else F.window("ts", width, slide) if slide else F.window("ts", width)
    rows = events.withWatermark("ts", late) if events.isStreaming else events
    grouped = rows.groupBy(window.alias("w"), "user_id").agg(F.collect_set("event_type").alias("items"))
    return grouped.select("user_id", F.col("w.start").alias("start"), F.array_sort("items").alias("items"))


def mentions(baskets: DataFrame, itemsets: DataFrame, width: str = "1 day", late: str = "1 day") -> DataFrame:
    """(start, itemset, n) of baskets (ts, items) that contain each set."""
    rows = baskets.withWatermark("ts", late) if baskets.isStreaming else baskets
    sets = itemsets.select("itemset", F.col("items").alias("set"), F.element_at("items", 1).alias("anchor"))
    met = rows.select("ts", "items", F.explode("items").alias("anchor")).join(F.broadcast(sets), "anchor").where(contains(F.col("items"), F.col("set")))
    return met.groupBy(F.window("ts", width).alias("w"), "itemset").agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "itemset", "n")


def drift(baskets: DataFrame, catalog: Catalog) -> DataFrame:
    """Running (key, usage, support) under a frozen catalog: interestingness as time passes."""
    sets = to_df(baskets.sparkSession, catalog).select("key", F.col("items").alias("set"), F.element_at("items", 1).alias("anchor"))
    covered = assign(baskets, catalog).select("items", "cover", F.explode("items").alias("anchor"))
    met = covered.join(F.broadcast(sets), "anchor").where(contains(F.col("items"), F.col("set")))
    return met.groupBy("key").agg(F.sum(F.array_contains("cover", F.col("key")).cast("long")).alias("usage"), F.count("*").alias("support"))


def deduplicated(events: DataFrame, key: str = "event_id", late: str = "1 day") -> DataFrame:
    if not events.isStreaming:
        return events.dropDuplicates([key])
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark([key])


def warm_refresh(catalog: Catalog, every: int = 1, on_change: Callable[[Catalog], None] | None = None, keep: int = 8) -> tuple[Callable[[DataFrame, int], None], Callable[[], Catalog]]:
    """A foreachBatch function that re-estimates the catalog on the distinct baskets of the last `keep` batches, and a getter of the catalog."""
    state = {"catalog": catalog, "parts": []}

    def handle(batch: DataFrame, number: int) -> None:
        part = compress(batch).persist()
        part.count()
        state["parts"].append(part)
        for old in state["parts"][:-keep]:
            old.unpersist()
        state["parts"] = state["parts"][-keep:]
        if number % every == every - 1:
            union = state["parts"][0]
            for p in state["parts"][1:]:
                union = union.unionByName(p)
            merged = union.groupBy("items").agg(F.sum("mult").alias("mult"))
            m = merged.agg(F.sum("mult")).first()[0] or 0
            if m:
                state["catalog"] = em.hard_em(merged, state["catalog"], m, max_iter=5, kernel="arrow", keep_singletons=True, floor=0.5 / m).catalog
                if on_change:
                    on_change(state["catalog"])

    return handle, lambda: state["catalog"]


def spike_alerts(daily: DataFrame, z: float = 3.0, least: int = 5) -> DataFrame:
    """(itemset, start, n, z): counts far above the running mean of their set, whose mean and variance are the state."""

    def run(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, mean, square = state.get if state.exists else (0, 0.0, 0.0)
        out = []
        for start, value in pd.concat(list(frames)).sort_values("start")[["start", "n"]].itertuples(index=False):
            sd = (square / n) ** 0.5 if n else 0.0
            if n >= least and sd > 0 and value > mean + z * sd:
                out.append((key[0], start, int(value), float((value - mean) / sd)))
            n += 1
            gap = value - mean
            mean += gap / n
            square += gap * (value - mean)
        state.update((n, float(mean), float(square)))
        yield pd.DataFrame(out, columns=["itemset", "start", "n", "z"])

    return daily.groupBy("itemset").applyInPandasWithState(
        run, "itemset string, start timestamp, n long, z double", "n long, mean double, square double", "append", GroupStateTimeout.NoTimeout
    )


def dropped_late(query: StreamingQuery) -> int:
    """Rows that a query's stateful operators dropped behind the watermark, over its recent progress."""
    return sum(op["numRowsDroppedByWatermark"] for progress in query.recentProgress for op in progress["stateOperators"])


def to_memory(stream: DataFrame, name: str, mode: str = "append") -> StreamingQuery:
    """Run a stream over all that is there, into a table in memory; the finished query tells its progress."""
    query = stream.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).start()
    query.awaitTermination()
    return query
