"""Packing documents into sequences: shortest pack first over the histogram of piece lengths.

Documents are tokenised and cut into pieces of at most `size` tokens.  Only the histogram of piece
lengths goes to the driver (`size` numbers, whatever the input).  Lengths are placed from the
longest down, always into the shortest packs with room, and whole groups of equal packs at a
time; what results is a list of patterns with counts.  Pieces then find their place by rank:
the r-th piece of a length takes the r-th slot of that length over all patterns.
"""

from __future__ import annotations

import re
import zlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common

SEQUENCE_TOKENS = 1024
END_ID = 0
TOKENIZER = "byte_bpe_50k.json"
#: Pieces of one length and rank bucket, about.
BUCKET_ROWS = 2_000
#: Patterns that are broadcast; each length adds four at most, so 1024 tokens stay below.
MOST_PATTERNS = 8_192
#: Rows that a worker turns into Python objects at once.
SLICE_ROWS = 500

#: Beyond these characters the two tokenizer libraries' character classes could differ.
_PLAIN = re.compile(r"[^\x09\x0a\x0d\x20-\x7e\xa1-ɏ‐-‧‰-⁞]")


class Encoder:
    """Token ids of texts, those of the reference encoder as it is loaded: added tokens in a text are read as such.

    The fast library encodes plain Latin text that holds no added token, with the same ids; the
    reference encoder all else.
    """

    def __init__(self, tokenizer: str = TOKENIZER):
        import base64
        import json
        import os

        import public_tokenizers
        import tiktoken
        from tokenizers import Tokenizer

        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        self._load = lambda: Tokenizer.from_file(public_tokenizers.path(tokenizer))
        self._exact = None
        self.fast = None
        ranks = tokenizer.replace(".json", ".tiktoken")
        if ranks in ("byte_bpe_50k.tiktoken",):
            with open(public_tokenizers.path(tokenizer), encoding="utf-8") as file:
                added = [t["content"] for t in json.load(file).get("added_tokens", [])]
            self._added = re.compile("|".join(map(re.escape, added)) or r"(?!)")
            with open(public_tokenizers.path(ranks), "rb") as lines:
                table = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
            self.fast = tiktoken.Encoding("plain", pat_str=public_tokenizers.PATTERN, mergeable_ranks=table, special_tokens={})

    @property
    def exact(self):
        """The reference encoder, a hundred megabytes that only a worker with such text loads."""
        if self._exact is None:
            self._exact = self._load()
        return self._exact

    def __call__(self, text: str) -> list[int]:
        if self.fast is not None and not _PLAIN.search(text) and not self._added.search(text):
            return self.fast.encode_ordinary(text)
        return self.exact.encode(text, add_special_tokens=False).ids


def pieces(docs: DataFrame, size: int = SEQUENCE_TOKENS, tokenizer: str = TOKENIZER) -> DataFrame:
    """(doc_id, start, length, ids_crc32, doc_tokens): each text's tokens and END_ID, cut every `size` tokens."""
    schema = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"

    def run(batches):
        encode = Encoder(tokenizer)
        for batch in (b.slice(at, SLICE_ROWS) for b in batches for at in range(0, b.num_rows, SLICE_ROWS)):
            rows = []
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                ids = np.array([*(encode(text) if text else ()), END_ID], "<u4")
                rows += [(doc_id, at, min(size, len(ids) - at), zlib.crc32(ids[at : at + size].tobytes()), len(ids)) for at in range(0, len(ids), size)]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], ["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(run, schema)


def pack_histogram(counts: dict[int, int], size: int) -> list[tuple[tuple[int, ...], int]]:
    """Patterns (lengths in order, how many packs have them) that hold every length as often as counts says."""
    open_by_used: dict[int, list[list]] = defaultdict(list)
    closed = []

    def put(pattern: tuple[int, ...], n: int, used: int) -> None:
        if used == size:
            closed.append((pattern, n))
        else:
            open_by_used[used].append([pattern, n])

    for length in sorted(counts, reverse=True):
        todo = counts[length]
        for used in sorted(u for u in open_by_used if u + length <= size and open_by_used[u]):
            groups = open_by_used[used]
            while todo and groups:
                pattern, n = groups.pop()
                take = min(n, todo)
                if take < n:
                    groups.append([pattern, n - take])
                put((*pattern, length), take, used + length)
                todo -= take
            if not todo:
                break
        if todo:
            # New packs of this length take as many of it as fit.
            fit = size // length
            full, rest = divmod(todo, fit)
            if full:
                put((length,) * fit, full, fit * length)
            if rest:
                put((length,) * rest, 1, rest * length)
    return closed + [(p, n) for groups in open_by_used.values() for p, n in groups]


def slots(spark: SparkSession, patterns: list[tuple[tuple[int, ...], int]]) -> DataFrame:
    """(length, first, last, sequence, offset): ranks first..last of a length go to sequences from `sequence` on."""
    rows, taken, base = [], defaultdict(int), 0
    for pattern, n in patterns:
        at = 0
        for length in pattern:
            rows.append((length, taken[length], taken[length] + n, base, at))
            taken[length] += n
            at += length
        base += n
    return spark.createDataFrame(rows, "length long, first long, last long, sequence long, offset long")


def ranked(parts: DataFrame, counts: dict[int, int], order: list[str]) -> DataFrame:
    """parts with `rank`, from 0 within each length.

    A length is dealt over as many buckets as its count asks for; buckets are counted first, then
    rows within a bucket.
    """
    by = "length"
    buckets = F.array(*(F.lit(max(1, -(-counts.get(n, 0) // BUCKET_ROWS))) for n in range(1, max(counts) + 1)))
    dealt = parts.withColumn("bucket", F.pmod(F.xxhash64(*order), F.element_at(buckets, F.col(by).cast("int"))))
    before = Window.partitionBy(by).orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    starts = dealt.groupBy(by, "bucket").agg(F.count("*").alias("n")).select(by, "bucket", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("begin"))
    within = Window.partitionBy(by, "bucket").orderBy(*order)
    numbered = dealt.withColumn("rank", F.row_number().over(within) - 1)
    return numbered.join(starts, [by, "bucket"]).withColumn("rank", F.col("rank") + F.col("begin")).drop("bucket", "begin")


def packed(docs: DataFrame, size: int = SEQUENCE_TOKENS, tokenizer: str = TOKENIZER) -> DataFrame:
    """One row per piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    Null and empty texts are one piece of END_ID alone; repeated rows are packed each; pieces tie
    by doc_id, start and checksum, and equal pieces are interchangeable.  A null doc_id is packed like
    any other and stays null.  An empty table gives no rows.
    """
    parts = common.checkpointed(pieces(docs, size, tokenizer))
    counts = {r["length"]: r["n"] for r in parts.groupBy("length").agg(F.count("*").alias("n")).collect()}
    if not counts:
        return parts.withColumns({"sequence_id": F.lit(0).cast("long"), "offset": F.lit(0).cast("long")})
    patterns = pack_histogram(counts, size)
    places = slots(parts.sparkSession, patterns)
    with_rank = ranked(parts, counts, ["doc_id", "start", "ids_crc32"])
    # Slots grow with the number of distinct lengths (at most `size`) and patterns, not with the documents.
    at = F.broadcast(places) if len(patterns) <= MOST_PATTERNS else places
    out = with_rank.join(at, (with_rank["length"] == at["length"]) & (F.col("rank") >= F.col("first")) & (F.col("rank") < F.col("last")))
    return out.select(
        "doc_id", "start", with_rank["length"], "ids_crc32", "doc_tokens", (F.col("sequence") + F.col("rank") - F.col("first")).alias("sequence_id"), "offset"
    )
