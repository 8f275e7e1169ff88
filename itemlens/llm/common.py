"""Helpers shared by the corpus operators: tables, checkpoints, skew-safe lookups, components."""

from __future__ import annotations

import re
import sys
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark import cloudpickle
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

# Executors need no copy of this package: its functions travel with the tasks.
cloudpickle.register_pickle_by_value(sys.modules[__package__])

#: A looked-up table sends at most this many of its heaviest keys by broadcast.
HEAVY_KEYS = 1000
#: A key with fewer rows than this is never heavy.
HEAVY_LEAST = 2000
#: Bytes of text that one step of a vectorised kernel takes at once.
CHUNK_BYTES = 1 << 20


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir; only where driver and executors are one process (tests), a temporary folder may stand in for it."""
    top = spark.conf.get("spark.checkpoint.dir", None)
    if top:
        return top.rstrip("/")
    if not re.fullmatch(r"local(\[[^,]*\])?", spark.sparkContext.master):
        raise ValueError("spark.checkpoint.dir is not set: a folder that the driver and all executors share is needed")
    return tempfile.gettempdir()


def checkpointed(df: DataFrame) -> DataFrame:
    """df, written as a Parquet table below spark.checkpoint.dir and read again; later jobs do not depend on executors.

    checkpoint() would store Java-serialised rows, several times as large.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/itemlens-{spark.sparkContext.applicationId}/{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def ranked(df: DataFrame, *keys: str, name: str = "name") -> DataFrame:
    """df, written, with the rank of each row in the order of keys, from 1: the same however many partitions there are.

    Rows are dealt by ranges of their keys and numbered within them; the rows of each range are
    counted, and the counts of the ranges before are added (one row for each range).
    """
    dealt = df.repartitionByRange(*keys).sortWithinPartitions(*keys).withColumn("_at", F.monotonically_increasing_id())
    kept = checkpointed(dealt.withColumn("_range", F.shiftright("_at", 33)).withColumn("_at", F.col("_at").bitwiseAND(F.lit((1 << 33) - 1))))
    counts = sorted((r["_range"], r["n"]) for r in kept.groupBy("_range").agg(F.count("*").alias("n")).collect())
    starts, total = [], 0
    for part, n in counts:
        starts.append((part, total))
        total += n
    before = df.sparkSession.createDataFrame(starts, "_range long, _before long")
    return kept.join(F.broadcast(before), "_range").withColumn(name, F.col("_before") + F.col("_at") + 1).select(*df.columns, name)


def discard(*tables: DataFrame) -> None:
    """Delete tables that checkpointed() wrote and that nothing will read any more."""
    for df in tables:
        spark = df.sparkSession
        for file in df.inputFiles()[:1]:
            folder = spark._jvm.org.apache.hadoop.fs.Path(file.rsplit("/", 1)[0])
            folder.getFileSystem(spark._jsc.hadoopConfiguration()).delete(folder, True)


def utf8_chunks(texts: list, limit: int = CHUNK_BYTES) -> Iterator[tuple[int, list[bytes]]]:
    """(index of the first, encoded texts) in runs of about limit bytes; null counts as empty."""
    first, size, run = 0, 0, []
    for i, text in enumerate(texts):
        data = text.encode("utf-8", "surrogatepass") if text else b""
        if run and size + len(data) > limit:
            yield first, run
            first, size, run = i, 0, []
        run.append(data)
        size += len(data)
    if run:
        yield first, run


def map_arrow(df: DataFrame, f: Callable[[pa.RecordBatch], Iterator[pa.RecordBatch] | pa.RecordBatch | None], schema: str) -> DataFrame:
    """mapInArrow with one call of f for each batch that has rows."""

    def run(batches):
        for batch in batches:
            if batch.num_rows:
                out = f(batch)
                if out is None:
                    continue
                if isinstance(out, pa.RecordBatch):
                    yield out
                else:
                    yield from out

    return df.mapInArrow(run, schema)


def lookup_join(rows: DataFrame, lookup: DataFrame, key: str, weight: str, spread: Column) -> DataFrame:
    """rows with the columns of lookup (unique by key, materialised), as a left join that hot keys do not slow down.

    weight: lookup's column with the number of rows of its key.  At most HEAVY_KEYS keys can hold a
    HEAVY_KEYS-th of all rows or more; those come by broadcast, and their rows are spread over the
    partitions of the join by `spread`, an expression of rows.
    """
    values = [c for c in lookup.columns if c not in (key, weight)]
    total = lookup.agg(F.sum(weight)).first()[0] or 0
    least = max(HEAVY_LEAST, total // HEAVY_KEYS + 1)
    light = lookup.where(F.col(weight) < least).select(F.col(key), F.lit(0).alias("_salt"), *values)
    heavy = lookup.where(F.col(weight) >= least).select(
        F.col(key), F.lit(True).alias("_hot"), *(F.col(v).alias(f"_hot_{v}") for v in values)
    )
    marked = rows.join(F.broadcast(heavy), key, "left").withColumn(
        "_salt", F.when(F.col("_hot"), F.pmod(F.xxhash64(spread), F.lit(1009)) + 1).otherwise(0).cast("int")
    )
    return marked.join(light, [key, "_salt"], "left").select(
        *rows.columns, *(F.coalesce(F.col(f"_hot_{v}"), F.col(v)).alias(v) for v in values)
    )


#: Links that one task joins; beyond that, components are found by rounds over all executors.
ONE_TASK_LINKS = 1_000_000


def forest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of links (a, b), rows (node, root) for every node but the roots: the components within this task, by their smallest ids."""
    parent: dict[int, int] = {}

    def root(x: int) -> int:
        top = x
        while (up := parent.setdefault(top, top)) != top:
            top = up
        while parent[x] != top:
            parent[x], x = top, parent[x]
        return top

    for batch in batches:
        for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            a, b = root(a), root(b)
            if a != b:
                parent[max(a, b)] = min(a, b)
    nodes = [x for x in parent if root(x) != x]
    if nodes:
        yield pa.RecordBatch.from_arrays([pa.array(nodes, pa.int64()), pa.array([parent[x] for x in nodes], pa.int64())], ["a", "b"])


def components(edges: DataFrame, one_task: int = ONE_TASK_LINKS) -> DataFrame:
    """(id, component) of every node of edges (a, b): component is the smallest id it reaches.

    Each partition's links are folded to a forest first.  Up to `one_task` remaining links are
    joined by one task (about 100 bytes each); more go through alternating star rounds.
    """
    folded = checkpointed(edges.select("a", "b").where("a <> b").mapInArrow(forest, "a long, b long"))
    if folded.count() <= one_task:
        links = checkpointed(folded.coalesce(1).mapInArrow(forest, "a long, b long"))
        discard(folded)
    else:
        links = star_rounds(folded)
    roots = links.select(F.col("b").alias("id"), F.col("b").alias("component")).distinct()
    return links.select(F.col("a").alias("id"), F.col("b").alias("component")).unionByName(roots)


def star_rounds(edges: DataFrame, most_rounds: int = 60) -> DataFrame:
    """(node, smallest node of its component) by alternating large-star and small-star steps.

    Each node's neighbours are re-attached to its smallest neighbour until every node hangs on its
    component's smallest node.
    """
    def star(links: DataFrame, large: bool) -> DataFrame:
        if large:
            both = links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
        else:
            both = links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        both = both.where("a <> b").distinct()
        best = checkpointed(both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("m"), F.count("*").alias("n")))
        joined = lookup_join(both, best, "a", "n", F.col("b"))
        if large:
            out = joined.where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b"))
        else:
            out = joined.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(
                best.select("a", F.col("m").alias("b"))
            )
        return out.where("a <> b").distinct()

    def mark(links: DataFrame) -> tuple:
        return tuple(links.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())

    links = checkpointed(edges.select("a", "b").where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct())
    before = mark(links)
    for _ in range(most_rounds if before[0] else 0):
        links, old = checkpointed(star(star(links, True), False)), links
        discard(old)
        now = mark(links)
        if now == before:
            break
        before = now
    else:
        if before[0]:
            raise RuntimeError("components did not settle")
    return links
