"""Text quality by logistic regression on hashed word n-grams, trained by follow-the-regularised-leader.

Words are runs of letters or digits, or runs of other marks, so that "word***" is two words.
Features are the hashes of single words and of adjacent pairs, weighted by their share of the
text; a score is one sparse dot product.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common
from .textkernel import segments_hash

FEATURE_BITS = 18
#: Labelled rows that training uses, at most: those of the smallest hash of their doc_id.
TRAINING_ROWS = 8000
EPOCHS = 4
#: Follow-the-regularised-leader: step size, its offset, and the two penalties.
ALPHA, BETA, L1, L2 = 0.5, 1.0, 1e-4, 1e-4
THRESHOLD = 0.3
#: Features of one text are scaled by this after they are divided by their number.
SCALE = 16.0

_KIND = np.ones(256, np.uint8)  # 0 white space, 1 letters and all beyond ASCII, 2 digits, 3 marks
_KIND[:128] = 3
_KIND[[9, 10, 11, 12, 13, 32]] = 0
_KIND[48:58] = 2
_KIND[65:91] = _KIND[97:123] = 1
_UPPER = np.zeros(256, bool)
_UPPER[65:91] = True


def features(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(feature of each n-gram of all texts in order, first n-gram of each text and the end)."""
    data = np.frombuffer(b"\n".join(texts), np.uint8)
    kind = _KIND[data]
    begins = kind > 0
    begins[1:] &= kind[1:] != kind[:-1]
    starts = np.flatnonzero(begins)
    one = segments_hash(data, starts)
    ends = np.cumsum([len(t) + 1 for t in texts])
    first = np.append(0, np.searchsorted(starts, ends))
    with np.errstate(over="ignore"):
        two = (one[:-1] * np.uint64(0xA24BAED4963EE407) + one[1:]) * np.uint64(0x9E3779B97F4A7C15)
    mask = np.uint64(64 - FEATURE_BITS)
    # The pair that starts at a text's last word would reach into the next text: it counts as its word again.
    pair = np.append(two, np.uint64(0))
    last = first[1:][first[1:] > first[:-1]] - 1
    pair[last] = one[last]
    both = np.empty(2 * len(one), np.int64)
    both[0::2] = (one >> mask).astype(np.int64)
    both[1::2] = (pair[: len(one)] >> mask).astype(np.int64)
    return both, 2 * first


def sparse(index: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    at, n = np.unique(index, return_counts=True)
    return at, n * (SCALE / max(1, len(index)))


def train(rows: Callable[[], Iterable[tuple[np.ndarray, np.ndarray, int]]], epochs: int = EPOCHS) -> tuple[np.ndarray, float]:
    """Weights and bias from (features, values, label), which rows() yields in one order, epoch by epoch."""
    size = (1 << FEATURE_BITS) + 1
    z, n = np.zeros(size), np.zeros(size)

    def weights(at):
        zi = z[at]
        return np.where(np.abs(zi) <= L1, 0.0, (np.sign(zi) * L1 - zi) / ((BETA + np.sqrt(n[at])) / ALPHA + L2))

    for _ in range(epochs):
        for index, value, label in rows():
            at, x = np.append(index, size - 1), np.append(value, 1.0)
            w = weights(at)
            p = 1 / (1 + np.exp(-np.clip(w @ x, -35, 35)))
            g = (p - label) * x
            step = (np.sqrt(n[at] + g * g) - np.sqrt(n[at])) / ALPHA
            z[at] += g - step * w
            n[at] += g * g
    all_ = weights(np.arange(size))
    return all_[:-1].astype(np.float32), float(all_[-1])


def fit(labelled: DataFrame, rows: int = TRAINING_ROWS) -> tuple[np.ndarray, float]:
    """labelled: doc_id, text, label (0 or 1).  Executors turn the bounded sample into sparse rows; the driver reads them as a stream, once for each epoch."""
    pool = labelled.where("label is not null")
    n = pool.count()
    h = F.xxhash64(F.col("doc_id"), F.lit("quality"))
    share = min(1.0, 2 * rows / max(1, n))
    cut = pool.withColumn("h", h).where(F.pmod("h", F.lit(1 << 20)) < int(share * (1 << 20)))

    def run(batch):
        labels, index, values = batch.column(2).to_pylist(), [], []
        for _, chunk in common.utf8_chunks(batch.column(1).to_pylist()):
            feats, first = features(chunk)
            for a, b in zip(first[:-1], first[1:], strict=True):
                at, v = sparse(feats[a:b])
                index.append(at.astype(np.int32))
                values.append(v.astype(np.float32))
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array([i.tobytes() for i in index]), pa.array([v.tobytes() for v in values]), pa.array(labels, pa.int32())], ["h", "i", "v", "label"])

    made = common.map_arrow(cut.select("h", "text", F.col("label").cast("int").alias("label")), run, "h long, i binary, v binary, label int")
    sample = common.checkpointed(made.orderBy("h", "i", "label").limit(rows))

    def seen():
        for r in sample.orderBy("h", "i", "label").toLocalIterator():
            yield np.frombuffer(r["i"], np.int32), np.frombuffer(r["v"], np.float32).astype(float), r["label"]

    found = train(seen)
    common.discard(sample)
    return found


def score(docs: DataFrame, model: tuple[np.ndarray, float]) -> DataFrame:
    """(doc_id, score) of every whole text; null and empty texts have the bias alone."""
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batch):
        w, bias = shared.value
        out = []
        for _, chunk in common.utf8_chunks(batch.column(1).to_pylist()):
            feats, first = features(chunk)
            sums = np.append(0.0, np.cumsum(w[feats], dtype=np.float64))
            n = np.diff(first)
            out.append(bias + SCALE * (sums[first[1:]] - sums[first[:-1]]) / np.maximum(n, 1))
        p = 1 / (1 + np.exp(-np.clip(np.concatenate(out), -35, 35)))
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(p.round(9))], ["doc_id", "score"])

    return common.map_arrow(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), run, "doc_id long, score double")


def held_out():
    """Rows whose labels training never sees: crc32 of the doc_id as text divisible by 5."""
    return F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(5)) == 0, F.lit(False))


def scored(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """One row per row of docs: doc_id, held_out, score (0 to 1), predicted (1 from THRESHOLD on).

    Labels of null doc_ids or null quality are left out; without any label all scores are 0.5.
    Repeated rows are scored alike.  An empty table gives no rows.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    known = labels.where("doc_id is not null").groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max("quality").alias("label"))
    model = fit(rows.join(known.where(~held_out()), "doc_id"))
    return score(rows, model).select("doc_id", held_out().alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
