"""Exact duplicates by deterministic block naming.

A text is cut into blocks of a fixed number of bytes.  Distinct blocks are sorted, by a digest
of 64 bits and then by content, and named by their rank; then the names of adjacent blocks are
paired, distinct pairs sorted and named in turn, until every text is one name.  Names stand for
contents, never for hashes of them: blocks of one digest with different contents are told apart, so
two texts get one name only if they are equal.  Names do not depend on how rows are dealt.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common

BLOCK_BYTES = 8192
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def normalised(text: Column) -> Column:
    """The text with A-Z lower-cased and nothing else changed; null as empty."""
    return F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER)


def _blocks(text: Column, block_bytes: int) -> Column:
    """The blocks of a binary text as an array; an empty text has one empty block.

    Bytes are cut, not characters: a block is then found without walking over those before it.
    """
    last = F.greatest(F.lit(1), F.ceil(F.octet_length(text) / block_bytes)).cast("int") - 1
    return F.transform(F.sequence(F.lit(0), last), lambda i: F.substring(text, i * block_bytes + 1, F.lit(block_bytes)))


def _once(made: Callable[[Column], Column]) -> Column:
    """made(normalised text in UTF-8), a struct, as columns: a variable holds the text, so that it is normalised once for all blocks."""
    return F.inline(F.transform(F.array(normalised(F.col("text")).cast("binary")), made))


def digest(block: Column) -> Column:
    return F.xxhash64(block)


def block_rows(docs: DataFrame, key: str, block_bytes: int) -> DataFrame:
    """(key, pos, left, block, digest): the `left` blocks of each normalised text."""
    cut = docs.select(key, _once(lambda text: F.struct(_blocks(text, block_bytes).alias("blocks"))))
    rows = cut.select(key, F.size("blocks").alias("left"), F.posexplode("blocks").alias("pos", "block"))
    return rows.select(key, "pos", "left", "block", digest(F.col("block")).alias("digest"))


def block_names(docs: DataFrame, key: str, block_bytes: int = BLOCK_BYTES, digests: DataFrame | None = None) -> DataFrame:
    """(key, level, name) for each row of docs (key unique, text): the text's identity.

    Contents move through one shuffle, folded on the map side; a digest brings each name back to its
    blocks, and only blocks whose digest stands for several contents are compared by content again.
    digests: (key, digests) of all rows, if known.
    """
    if digests is None:
        digests = docs.select(key, _once(lambda text: F.struct(F.transform(_blocks(text, block_bytes), digest).alias("digests"))))
    contents = common.checkpointed(block_rows(docs, key, block_bytes).groupBy("digest", "block").agg(F.count("*").alias("uses")).select("digest", "uses"))
    by_digest = contents.groupBy("digest").agg(F.count("*").alias("contents"), F.sum("uses").alias("uses"))
    clash = common.checkpointed(by_digest.where("contents > 1").select("digest"))
    sure = by_digest.where("contents = 1").select("digest", F.lit(None).cast("binary").alias("block"), "uses")
    unsure = block_rows(docs, key, block_bytes).join(clash, "digest", "left_semi") if not clash.isEmpty() else None
    if unsure is not None:
        sure = sure.unionByName(unsure.groupBy("digest", "block").agg(F.count("*").alias("uses")))
    names = common.ranked(sure, "digest", "block")
    place = [key, "pos", "left"]
    rows = digests.select(key, F.size("digests").alias("left"), F.posexplode("digests").alias("pos", "digest"))
    by_name = common.checkpointed(names.where("block is null").select("digest", "name", "uses"))
    level = common.lookup_join(rows.select(*place, "digest"), by_name, "digest", "uses", F.col(key)).where("name is not null").select(*place, "name")
    if unsure is not None:
        level = level.unionByName(unsure.join(names.where("block is not null").select("digest", "block", "name"), ["digest", "block"]).select(*place, "name"))
    level = common.checkpointed(level)
    common.discard(contents, clash, names, by_name)
    done, step = [], 0
    while True:
        done.append(level.where("left = 1").select(key, F.lit(step).alias("level"), "name"))
        pairs = (
            level.where("left > 1")
            .groupBy(key, F.floor(F.col("pos") / 2).alias("pos"), F.ceil(F.col("left") / 2).alias("left"))
            .agg(F.struct(*(F.coalesce(F.max(F.when(F.col("pos") % 2 == side, F.col("name"))), F.lit(0)).alias(f"side{side}") for side in (0, 1))).alias("pair"))
        )
        pairs = common.checkpointed(pairs)
        if pairs.isEmpty():
            break
        named = common.ranked(pairs.groupBy("pair").agg(F.count("*").alias("uses")), "pair")
        level = common.checkpointed(common.lookup_join(pairs, named, "pair", "uses", F.col(key)).select(*place, "name"))
        common.discard(pairs, named)
        step += 1
    out = done[0]
    for part in done[1:]:
        out = out.unionByName(part)
    return out


def exact_duplicates(docs: DataFrame, block_bytes: int = BLOCK_BYTES) -> DataFrame:
    """One row per row of docs: doc_id, keep_id, group_size, kept, text_sha256.

    Texts are equal when identical after lower-casing A-Z; null counts as empty.  keep_id is the
    largest doc_id among equal texts, and its row is kept.  Of rows that share doc_id and text, all
    are reported and all are marked as their doc_id is.  Extra columns are ignored; an empty table
    gives no rows; a null doc_id is smaller than any other.
    """
    docs = docs.select("doc_id", "text").withColumn("row", F.col("doc_id").cast("long"))
    if not _unique(docs):
        # Repeated ids: number the rows within their text's copies of the id.
        docs = common.checkpointed(docs.withColumn("row", F.monotonically_increasing_id()))
    # One scan for the digests of blocks and of the whole text.
    marked = common.checkpointed(docs.select(
        "row", "doc_id", _once(lambda text: F.struct(F.sha2(text, 256).alias("text_sha256"), F.transform(_blocks(text, block_bytes), digest).alias("digests")))
    ))
    names = block_names(docs, "row", block_bytes, marked.select("row", "digests"))
    identity = common.checkpointed(marked.join(names, "row").select("doc_id", F.struct("level", "name").alias("identity"), "text_sha256"))
    common.discard(marked)
    groups = common.checkpointed(identity.groupBy("identity").agg(F.max("doc_id").alias("keep_id"), F.count("*").alias("group_size"), F.count("*").alias("uses")))
    out = common.lookup_join(identity, groups, "identity", "uses", F.coalesce(F.col("doc_id"), F.lit(0)))
    return out.select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256")


def _unique(docs: DataFrame) -> bool:
    return docs.groupBy("row").agg(F.count("*").alias("n")).where("n > 1 or row is null").isEmpty()


ORACLE_SQL = """
with t as (select doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as text from documents)
select doc_id, max(doc_id) over (partition by text) as keep_id, count(*) over (partition by text) as group_size,
       doc_id = max(doc_id) over (partition by text) as kept, sha256(text) as text_sha256
from t
"""
