"""One-permutation MinHash fingerprints with optimal densification and packed low-order bits."""

from __future__ import annotations

import base64
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common
from .textkernel import mix64, shingle_sets

BINS, BITS = 512, 4
#: Rows of one range of neighbouring ids, about, and how many ranges there are at most; rows of a range are read as a stream, however many.
RANGE_ROWS, MOST_RANGES = 5000, 20_000
#: Texts with so few bins in use choose among those; others ask bin after bin.
FEW_BINS = 24
_EMPTY = np.uint64(0xFFFFFFFFFFFFFFFF)


@cache
def _donors(bins: int) -> tuple[np.ndarray, np.ndarray]:
    """The order in which each bin, if empty, asks all others for a value, and its inverse: the same for all texts."""
    keys = mix64(np.arange(bins * bins, dtype=np.uint64) + np.uint64(65537)).reshape(bins, bins)
    order = np.argsort(keys, axis=1).astype(np.int16)
    rank = np.empty_like(order)
    np.put_along_axis(rank, order, np.arange(bins, dtype=np.int16)[None, :], 1)
    return order, rank


def sketch(sets: list[np.ndarray], bins: int = BINS, bits: int = BITS) -> np.ndarray:
    """One row of `bins` low-order values for each sorted set of hashes; zeros for an empty set.

    An empty bin takes the value of the first bin of its order that is not empty.
    """
    low = np.full((len(sets), bins), _EMPTY)
    rows = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    if len(rows):
        hashes = np.concatenate(sets)
        at = rows * bins + (hashes >> np.uint64(64 - bins.bit_length() + 1)).astype(np.int64)
        # Sets come sorted and bins are the hashes' top bits, so bins rise within each row.
        first = np.append(True, at[1:] != at[:-1])
        low.ravel()[at[first]] = hashes[first] >> np.uint64(1)
    filled = low != _EMPTY
    held = filled.sum(1)
    order, rank = _donors(bins)
    for r in np.flatnonzero((held > 0) & (held <= FEW_BINS)):
        own = np.flatnonzero(filled[r])
        open_ = np.flatnonzero(~filled[r])
        low[r, open_] = low[r, own[rank[np.ix_(open_, own)].argmin(1)]]
    row, bin_ = np.nonzero(~filled & (held > FEW_BINS)[:, None])
    for asked in order.T:
        if not len(row):
            break
        donor = asked[bin_]
        hit = filled[row, donor]
        low[row[hit], bin_[hit]] = low[row[hit], donor[hit]]
        row, bin_ = row[~hit], bin_[~hit]
    # Each bin mixes in its own number, so that bins with one and the same value agree by chance each for itself.
    low = mix64(low ^ (np.arange(bins, dtype=np.uint64) << np.uint64(32)))
    low[held == 0] = 0
    return (low & np.uint64((1 << bits) - 1)).astype(np.uint8)


def pack(values: np.ndarray, bits: int = BITS, empty: bool = False) -> str:
    """The values' low bits as base64 text; an empty set has no text of that kind but "-"."""
    if empty:
        return "-"
    lines = (values[:, None] >> np.arange(bits - 1, -1, -1, dtype=np.uint8)) & 1
    return base64.b64encode(np.packbits(lines.astype(np.uint8).ravel()).tobytes()).decode()


def likeness(x: np.ndarray, y: np.ndarray, bits: int = BITS) -> np.ndarray:
    """Estimated Jaccard similarity, row by row: the share of equal values less what chance gives."""
    chance = 1 / (1 << bits)
    return np.clip(((x == y).mean(-1) - chance) / (1 - chance), 0, 1)


def fingerprints(docs: DataFrame, bins: int = BINS, bits: int = BITS) -> DataFrame:
    """(doc_id, n_shingles, fingerprint) of every whole text of docs; equal texts have equal fingerprints.

    Null, empty and blank texts have no shingle and the fingerprint "-".
    """

    def run(batch):
        n, out = [], []
        for _, chunk in common.utf8_chunks(batch.column(1).to_pylist()):
            sets = shingle_sets(chunk)
            n += map(len, sets)
            out += [pack(v, bits, not len(s)) for v, s in zip(sketch(sets, bins, bits), sets, strict=True)]
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(out)], ["doc_id", "n_shingles", "fingerprint"])

    return common.map_arrow(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), run, "doc_id long, n_shingles long, fingerprint string")


def edited_fingerprints(docs: DataFrame, bins: int = BINS, bits: int = BITS) -> DataFrame:
    """Each text's fingerprint beside that of its edited text and of the next text by doc_id.

    The edit replaces the last floor(n_chars / 4) code points by the first as many (or all) of the
    next document, after the last the first.  Ids are cut into ranges by a sample; the first row
    of each range also serves, as a guest, at the end of the range before, so that no range needs
    another one and texts move once.  Rows that repeat a doc_id follow each other by text; null
    doc_ids come before all others.  An empty table gives no rows; a single row is its own next one.  Likeness with an empty text is 0, of
    two empty texts 1.
    """
    docs = docs.select(F.coalesce(F.col("doc_id").cast("long"), F.lit(-(2**63))).alias("key"), F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    schema = "doc_id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
    rows = docs.count()
    if not rows:
        return docs.sparkSession.createDataFrame([], schema)
    ranges = max(1, min(MOST_RANGES, rows // RANGE_ROWS))
    # One row for each range comes back: its smallest id.
    dealt = docs.select("key").repartitionByRange(ranges, "key")
    starts = dealt.groupBy(F.spark_partition_id().alias("range")).agg(F.min("key").alias("least")).collect()
    bounds = np.unique(np.array([r["least"] for r in starts], np.int64))

    @F.pandas_udf("struct<part: int, first: boolean>")
    def place(ids):
        import pandas as pd

        at = np.searchsorted(bounds, ids.to_numpy(), "right") - 1
        return pd.DataFrame({"part": at.astype(np.int32), "first": bounds[at] == ids.to_numpy()})

    n = len(bounds)
    placed = docs.withColumn("p", place("key"))
    # Only the smallest row of a range's first id is the guest; with repeated ids all come and the first in order is taken.
    homes = F.when(
        F.col("p.first"), F.array(F.struct(F.col("p.part").alias("part"), F.lit(False).alias("guest")), F.struct(F.pmod(F.col("p.part") - 1, F.lit(n)).alias("part"), F.lit(True).alias("guest")))
    ).otherwise(F.array(F.struct(F.col("p.part").alias("part"), F.lit(False).alias("guest"))))
    dealt = placed.select("key", "doc_id", "text", F.inline(homes)).repartition("part").sortWithinPartitions("part", "guest", "key", "text")

    def run(batches):
        import hashlib

        held, out, size = None, [], 0

        def flush(rows):
            texts = [r[1] for r in rows] + [r[3] for r in rows] + [rows[-1][2]]
            sets = [s for _, chunk in common.utf8_chunks(texts) for s in shingle_sets(chunk)]
            values, k = sketch(sets, bins, bits), len(rows)
            # The next text's fingerprint is the next row's, where that is in this run; else it is computed.
            own, edited = values[:k], values[k : 2 * k]
            after = np.concatenate([own[1:], values[2 * k :]])
            sizes = np.array([len(s) for s in sets])
            own_n, edited_n, after_n = sizes[:k], sizes[k : 2 * k], np.append(sizes[1:k], sizes[2 * k])
            for i in range(k - 1):
                if rows[i][2] is not rows[i + 1][1]:
                    s = shingle_sets([rows[i][2].encode()])
                    after[i], after_n[i] = sketch(s, bins, bits)[0], len(s[0])
            near = [np.where((a == 0) | (b == 0), (a == b).astype(float), likeness(x, y, bits)) for a, b, x, y in ((own_n, edited_n, own, edited), (own_n, after_n, own, after))]
            return pa.RecordBatch.from_arrays(
                [
                    pa.array([r[0] for r in rows], pa.int64()), pa.array([len(r[1]) for r in rows], pa.int64()), pa.array([hashlib.sha256(r[3].encode()).hexdigest() for r in rows]),
                    pa.array([pack(v, bits, not c) for v, c in zip(own, own_n, strict=True)]), pa.array([pack(v, bits, not c) for v, c in zip(edited, edited_n, strict=True)]), pa.array(near[0]), pa.array(near[1]),
                ],
                ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"],
            )

        for batch in batches:
            for _, doc_id, text, part, guest in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if held is not None and held[2] == part:
                    quarter = len(held[1]) // 4
                    new = held[1][: len(held[1]) - quarter] + text[:quarter]
                    out.append((held[0], held[1], text, new))
                    size += 4 * len(held[1])
                    if size > common.CHUNK_BYTES:
                        yield flush(out)
                        out, size = [], 0
                held = None if guest else (doc_id, text, part)
        if out:
            yield flush(out)

    return dealt.mapInArrow(run, schema)
