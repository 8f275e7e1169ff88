"""Exact near-duplicate join by Jaccard similarity of word shingles, over token-combination prefixes.

Every text is the set of its distinct 5-word shingles, here called tokens: 64-bit hashes.  Copies
with equal sets are folded into one representative first.  Tokens are put in one global order, rare
ones first, with the frequencies of a count sketch taken over all texts.  Two sets of similarity t
or more miss at most |x| - ceil(t |x|) tokens of x, so they meet within a prefix of that order:

* rare tokens are indexed alone,
* frequent tokens fall into classes and are indexed by pairs of one class; each class may then lose
  one more token, so the prefix is extended by one token for each class it uses,
* a set has as many classes, up to CLASSES, as its size affords (a power of two), and is also
  indexed by the numbers of classes of its smallest possible partner, so that every pair of sizes
  has one number in common.  Only the smallest sets have no class,
* each prefix goes SHARED - 1 tokens beyond what one common signature needs, so similar sets share
  SHARED signatures (sets of so few tokens that they cannot: all that they must have in common).

In random texts, pairs that share one rare token by chance grow with the square of the corpus and in
the end tie all of it together, so sets that meet in small groups only are candidates if they
share as many signatures as similar sets must.  Sets of a larger group whose sizes may be similar
are chained, not paired, and joined by that signature alone, so it costs the size of its group and
not its square; each task folds its own rows of such a signature to a few for each size first, so no
signature is large after the shuffle.  The components of both are families; all similar pairs lie
within one.  A family beyond a block's size is
indexed again by its own frequencies, which sets aside what all its texts share.  Each family's
texts come together once and are compared exactly, by bit rows or postings, only as far as they are
not yet linked.  What is still large is compared in blocks that share a few pivots; what the pivots
do not tie to the rest is then compared with every block.  No candidate is dropped.
"""

from __future__ import annotations

import hashlib
import zlib

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark import Broadcast
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common
from .textkernel import mix64, shingle_sets

#: Bits of a cell's number in the count sketch: enough for about 16 tokens a cell, between these.  Counts have no upper end.
LEAST_CELL_BITS, MOST_CELL_BITS = 22, 25
#: Steps for each doubling in which counts are told apart when tokens are ordered.
STEPS = 1000
#: A token is frequent if its cell holds this many more sets than the mean cell has, in standard deviations, and FREQUENT_LEAST.
FREQUENT_SIGMAS, FREQUENT_LEAST = 8.0, 64
#: Classes of frequent tokens, each indexed by pairs; small sets have fewer.
CLASSES = 64
#: Signatures that similar sets share at least; sets that share fewer, in groups of up to WHOLE_GROUP sets, are no candidates.
SHARED, WHOLE_GROUP = 3, 16
#: Signatures that a task folds at once.
FOLD_ROWS = 1 << 20
#: How often a family that exceeds a block is indexed by its own frequencies.
REFINEMENTS = 3
#: A family's block has about this many sets and bytes of text at most.
BLOCK_SETS, BLOCK_BYTES = 1024, 8 << 20
PIVOTS = 8
#: Bit rows of a block up to this size; postings beyond.
DENSE_BYTES = 64 << 20
#: Up to this many ids (16 bytes each, and as many again in the table) are sent to all executors; more are shuffled.
BROADCAST_IDS = 300_000
#: Bits of the maps that keep rows from being shuffled (4 MB).
BITMAP_BITS = 1 << 25


def _row(batch: pa.RecordBatch, name: str) -> list:
    return batch.column(batch.schema.get_field_index(name)).to_pylist()


def set_keys(docs: DataFrame) -> DataFrame:
    """(doc_id, n_shingles, set_key): set_key is null for a text without words."""

    def run(batch):
        ids, texts = batch.column(0), _row(batch, "text")
        n, keys = [], []
        for _, chunk in common.utf8_chunks(texts):
            for s in shingle_sets(chunk):
                n.append(len(s))
                keys.append(hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None)
        return pa.RecordBatch.from_arrays([ids, pa.array(n, pa.int64()), pa.array(keys, pa.binary())], ["doc_id", "n_shingles", "set_key"])

    return common.map_arrow(docs.select("doc_id", "text"), run, "doc_id long, n_shingles long, set_key binary")


def _cells(tokens: np.ndarray, cells: int) -> np.ndarray:
    return (mix64(tokens) >> np.uint64(32)).astype(np.int64) % cells


def _packed_counts(low: np.ndarray, at: np.ndarray, carry: np.ndarray) -> bytes:
    """Counts low + 256 carry (at: the cells with a carry): one bit for each cell in use, then the few counts above one, then the carries."""
    above = np.flatnonzero(low > 1).astype(np.uint32)
    gaps = np.diff(above, prepend=np.uint32(0)).astype(np.uint32)
    head = np.array([len(above), len(at)], np.uint32)
    parts = (head, np.packbits(low > 0), gaps, low[above], at.astype(np.uint32), carry.astype(np.uint64))
    return zlib.compress(b"".join(p.tobytes() for p in parts), 1)


def _unpacked_counts(data: bytes, width: int) -> np.ndarray:
    raw = zlib.decompress(data)
    n, carries = map(int, np.frombuffer(raw, np.uint32, 2))
    out = np.unpackbits(np.frombuffer(raw, np.uint8, width // 8, 8)).astype(np.uint64)
    end = 8 + width // 8
    above = np.cumsum(np.frombuffer(raw, np.uint32, n, end))
    out[above] = np.frombuffer(raw, np.uint8, n, end + 4 * n)
    end += 5 * n
    at = np.frombuffer(raw, np.uint8, 4 * carries, end).view(np.uint32)
    out[at] += np.frombuffer(raw, np.uint8, 8 * carries, end + 4 * carries).view(np.uint64) << np.uint64(8)
    return out


def step_of(count):
    """A count as a step on a logarithmic scale; counts below STEPS have steps of their own."""
    return np.floor(np.log2(1.0 + count) * STEPS).astype(np.uint16)


def _sets(batch: pa.RecordBatch, limit: int = common.CHUNK_BYTES):
    """(first row, sets) of a batch's texts in runs; with a column `family`, each family's tokens are apart from all others."""
    family = batch.schema.get_field_index("family")
    own = None if family < 0 else mix64(batch.column(family).to_numpy(zero_copy_only=False).view(np.uint64))
    for first, chunk in common.utf8_chunks(_row(batch, "text"), limit):
        sets = shingle_sets(chunk)
        yield first, sets if own is None else [mix64(s ^ own[first + i]) for i, s in enumerate(sets)]


def cell_count(tokens: int) -> int:
    """Cells for an input whose sets have so many members altogether."""
    return 1 << min(MOST_CELL_BITS, max(LEAST_CELL_BITS, (tokens // 16).bit_length()))


def count_sketch(texts: DataFrame, cells: int) -> np.ndarray:
    """How many sets hold a token of each cell, over all texts, as steps (step_of)."""
    blocks, width = 64, cells // 64

    def run(batches):
        low, carries = np.zeros(cells, np.uint8), []
        for batch in batches:
            for _, sets in _sets(batch):
                at, n = np.unique(_cells(np.concatenate(sets), cells), return_counts=True)
                n += low[at]
                low[at] = n & 255
                if (over := n >> 8).any():
                    carries.append((at[over > 0], over[over > 0]))
        at, carry = np.zeros(0, np.int64), np.zeros(0, np.int64)
        if carries:
            at, place = np.unique(np.concatenate([a for a, _ in carries]), return_inverse=True)
            carry = np.zeros(len(at), np.int64)
            np.add.at(carry, place, np.concatenate([c for _, c in carries]))
        if low.any() or len(at):
            ends = np.searchsorted(at, np.arange(blocks + 1) * width)
            rows = [_packed_counts(p, at[a:b] - k * width, carry[a:b]) for k, (p, a, b) in enumerate(zip(low.reshape(blocks, width), ends[:-1], ends[1:], strict=True))]
            yield pa.RecordBatch.from_arrays([pa.array(range(blocks), pa.int32()), pa.array(rows, pa.binary())], ["block", "counts"])

    def add(batches):
        block, total = None, None
        one = lambda: pa.RecordBatch.from_arrays([pa.array([block], pa.int32()), pa.array([step_of(total).tobytes()], pa.binary())], ["block", "counts"])
        for batch in batches:
            for b, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                if b != block:
                    if block is not None:
                        yield one()
                    block, total = b, np.zeros(width, np.uint64)
                total += _unpacked_counts(v, width)
        if block is not None:
            yield one()

    parts = texts.mapInArrow(run, "block int, counts binary")
    merged = parts.repartition("block").sortWithinPartitions("block").mapInArrow(add, "block int, counts binary")
    out = np.zeros((blocks, width), np.uint16)
    for row in merged.toLocalIterator():
        out[row["block"]] = np.frombuffer(row["counts"], np.uint16)
    return out.ravel()


def class_counts(n: int, num: int, den: int, shared: int = 1) -> list[int]:
    """The numbers of classes by which a set of n tokens is indexed so that similar sets share `shared` signatures: what it affords, down to what its smallest partner affords."""

    def most(size: int) -> int:
        able = min(CLASSES, size * num // den - shared)
        return 1 << able.bit_length() - 1 if able > 0 else 0

    c, least, out = most(n), most(-(-n * num // den)), []
    while c > least:
        out.append(c)
        c //= 2
    return [*out, least]


def prefix_signatures(tokens: np.ndarray, weight: np.ndarray, frequent: np.ndarray, num: int, den: int) -> np.ndarray:
    """Signatures of one set.  tokens: its distinct hashes; weight: their sketch counts; frequent: a mask; t = num/den.

    Two sets of similarity t or more share SHARED signatures at least, or as many as the smaller set's share t of tokens.
    """
    n = len(tokens)
    order = np.lexsort((tokens, weight))
    tokens, frequent = tokens[order], frequent[order]
    common_least = -(-n * num // den)
    needed = n - common_least + min(SHARED, common_least)
    if not frequent.any():
        return mix64(tokens[:needed])
    out = []
    for classes in class_counts(n, num, den, SHARED):
        if not classes:
            out.append(mix64(tokens[:needed]))
            continue
        kind = np.where(frequent, (tokens % np.uint64(classes)).astype(np.int64), -1)
        first_of_class = np.zeros(n, bool)
        _, at = np.unique(kind, return_index=True)
        first_of_class[at] = True
        gain = np.cumsum(~(first_of_class & frequent))
        end = int(np.searchsorted(gain, needed)) + 1
        head, kind = tokens[:end], kind[:end]
        out.append(mix64(head[kind < 0]))
        for k in np.unique(kind[kind >= 0]):
            own = np.sort(head[kind == k])
            i, j = np.triu_indices(len(own), 1)
            with np.errstate(over="ignore"):
                out.append(mix64(own[i] * np.uint64(0xA24BAED4963EE407) + own[j]))
    return np.unique(np.concatenate(out))


def folded(sig: np.ndarray, ids: np.ndarray, n: np.ndarray, num: int, den: int) -> tuple:
    """(rows that stand for all rows of their signature, links (a, b) among the rest of them).

    Rows of one signature are chained by size; of each size class, narrower than the similarity
    asks for, the first and the last row stay.  A row of another task that could be linked with one
    that went meets the ends of its class.
    """
    order = np.lexsort((ids, n, sig))
    sig, ids, n = sig[order], ids[order], n[order]
    same = sig[1:] == sig[:-1]
    near = same & (ids[1:] != ids[:-1]) & (den * n[:-1].astype(np.int64) >= num * n[1:].astype(np.int64))
    size = np.floor(np.log(n) / np.log(den / num) * 2).astype(np.int32)
    first = np.append(True, ~(same & (size[1:] == size[:-1])))
    stays = first | np.append(first[1:], True)
    return (sig[stays], ids[stays], n[stays]), _distinct_pairs(ids[:-1][near], ids[1:][near])


def _distinct_pairs(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    pairs = np.stack([np.minimum(a, b), np.maximum(a, b)], 1)
    pairs = pairs[np.lexsort((pairs[:, 1], pairs[:, 0]))]
    return pairs[np.append(True, (pairs[1:] != pairs[:-1]).any(1))] if len(pairs) else pairs


def signatures(texts: DataFrame, shared: Broadcast, mean: float, num: int, den: int) -> DataFrame:
    """(sig, id, n, other) of texts (doc_id, text, [family]): signatures, and with n = -1 links of id and other.

    A signature with more than WHOLE_GROUP rows in a task is folded; `other` is 0 in its rows, else null.
    shared: the count sketch; mean: of its cells, as a count.
    """
    limit = int(step_of(max(FREQUENT_LEAST, mean + FREQUENT_SIGMAS * np.sqrt(mean))))
    schema = pa.schema([("sig", pa.int64()), ("id", pa.int64()), ("n", pa.int32()), ("other", pa.int64())])

    def run(batches):
        held, rows = [], 0

        def flush():
            rows = [np.concatenate(c) for c in zip(*held, strict=True)]
            _, place, size = np.unique(rows[0], return_inverse=True, return_counts=True)
            large = size[place] > WHOLE_GROUP
            sig, ids, n = (c[~large] for c in rows)
            yield pa.RecordBatch.from_arrays([pa.array(sig.view(np.int64)), pa.array(ids), pa.array(n), pa.nulls(len(n), pa.int64())], schema=schema)
            if not large.any():
                return
            (sig, ids, n), links = folded(*(c[large] for c in rows), num, den)
            yield pa.RecordBatch.from_arrays([pa.array(sig.view(np.int64)), pa.array(ids), pa.array(n), pa.array(np.zeros(len(n), np.int64))], schema=schema)
            if len(links):
                a, b = links[:, 0].copy(), links[:, 1].copy()
                yield pa.RecordBatch.from_arrays([pa.array(mix64(a.view(np.uint64)).view(np.int64)), pa.array(a), pa.array(np.full(len(a), -1, np.int32)), pa.array(b)], schema=schema)

        for batch in batches:
            if not batch.num_rows:
                continue
            ids = batch.column(batch.schema.get_field_index("doc_id")).to_numpy(zero_copy_only=False)
            for first, sets in _sets(batch, common.CHUNK_BYTES // 2):
                for i, s in enumerate(sets):
                    if len(s):
                        weight = shared.value[_cells(s, len(shared.value))]
                        sig = prefix_signatures(s, weight, weight >= limit, num, den)
                        held.append((sig, np.full(len(sig), ids[first + i], np.int64), np.full(len(sig), len(s), np.int32)))
                        rows += len(sig)
                if rows >= FOLD_ROWS:
                    yield from flush()
                    held, rows = [], 0
        if held:
            yield from flush()

    return texts.mapInArrow(run, "sig long, id long, n int, other long")


def in_bitmap(ids: DataFrame, column: str, bits: int = BITMAP_BITS):
    """A predicate: whether column may be among ids (id).

    A bitmap of a fixed number of bits, one hash for each id; beyond it more and more rows pass, up
    to all, and what relies on it then shuffles as much as it would without.
    """
    line = 4096
    marked = ids.select(F.pmod(F.xxhash64("id"), F.lit(bits)).alias("bit")).groupBy((F.col("bit") / line).cast("int").alias("line")).agg(F.collect_set("bit").alias("set"))

    def pack(batch):
        out = []
        for one in batch.column(1).to_pylist():
            row = np.zeros(line, np.uint8)
            row[np.array(one, np.int64) % line] = 1
            out.append(np.packbits(row).tobytes())
        return pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], ["line", "bits"])

    table = np.zeros((bits // line, line // 8), np.uint8)
    for row in common.map_arrow(marked, pack, "line int, bits binary").toLocalIterator():
        table[row["line"]] = np.frombuffer(row["bits"], np.uint8)
    shared = ids.sparkSession.sparkContext.broadcast(table.ravel())

    @F.pandas_udf("boolean")
    def test(bit: pd.Series) -> pd.Series:
        at = bit.to_numpy()
        return pd.Series((shared.value[at >> 3] >> (7 - (at & 7)).astype(np.uint8)) & 1 == 1)

    return test(F.pmod(F.xxhash64(column), F.lit(bits)))


def _met(a: np.ndarray, b: np.ndarray, least: np.ndarray) -> pa.RecordBatch:
    """(a, b, met, least) of pairs, equal ones added up."""
    low, high = np.minimum(a, b), np.maximum(a, b)
    order = np.lexsort((least, high, low))
    low, high, least = low[order], high[order], least[order]
    first = np.flatnonzero(np.append(True, (low[1:] != low[:-1]) | (high[1:] != high[:-1])))
    met = np.diff(np.append(first, len(low)))
    return pa.RecordBatch.from_arrays([pa.array(low[first]), pa.array(high[first]), pa.array(met, pa.int32()), pa.array(least[first], pa.int32())], ["a", "b", "met", "least"])


def chains(sigs: DataFrame, num: int, den: int) -> DataFrame:
    """(a, b): candidates whose sizes allow the similarity, and neighbours by size within each large signature's group.

    The sets of a group of up to WHOLE_GROUP are paired, and pairs count that share as many
    signatures as they must.  In a larger group, two sets whose sizes allow it are joined by the
    neighbours between them, whatever else they share.  So the components over these rows hold all
    similar pairs.  A large group is read as a stream, whatever its size.
    """
    parts = sigs.repartition("sig").sortWithinPartitions("sig", "n", "id")

    def pairs_of(sig, ids, n, folded):
        """Pairs (a, b, least) of whole groups, and neighbours of large or folded ones, for which least is 0."""
        start = np.flatnonzero(np.append(True, sig[1:] != sig[:-1]))
        size = np.diff(np.append(start, len(sig)))
        large = (size > WHOLE_GROUP) | (np.add.reduceat(folded.astype(np.int64), start) > 0)
        inside = np.repeat(large, size)
        i = [np.flatnonzero(inside[1:] & (sig[1:] == sig[:-1]))]
        j, joined = [i[0] + 1], len(i[0])
        for k in np.unique(size[~large & (size > 1)]):
            x, y = np.triu_indices(k, 1)
            at = start[~large & (size == k)][:, None]
            i.append((at + x).ravel())
            j.append((at + y).ravel())
        i, j = np.concatenate(i), np.concatenate(j)
        least = np.minimum(SHARED, -(-n[i].astype(np.int64) * num // den))
        least[:joined] = 0
        near = (ids[i] != ids[j]) & (den * n[i].astype(np.int64) >= num * n[j].astype(np.int64))
        return ids[i[near]], ids[j[near]], least[near]

    def run(batches):
        held = None
        for batch in batches:
            sig, ids, n = (batch.column(i).to_numpy(zero_copy_only=False) for i in range(3))
            folded = batch.column(3).is_valid().to_numpy(zero_copy_only=False)
            if (known := n < 0).any():
                other = batch.column(3).filter(pa.array(known)).to_numpy(zero_copy_only=False)
                yield _met(ids[known], other, np.zeros(len(other), np.int64))
                sig, ids, n, folded = (c[~known] for c in (sig, ids, n, folded))
            if held is not None:
                sig, ids, n, folded = (np.append(x, y) for x, y in zip(held, (sig, ids, n, folded), strict=True))
            if not len(sig):
                continue
            # The last signature's group may go on in the next batch: whole if it is small, else its last row.
            cut = int(np.searchsorted(sig, sig[-1]))
            rows = [c[:cut] for c in (sig, ids, n, folded)]
            held = [c[cut:] for c in (sig, ids, n, folded)]
            if len(held[0]) > WHOLE_GROUP or held[3].any():
                rows = [sig, ids, n, np.append(folded[:cut], np.ones(len(sig) - cut, bool))]
                held = [sig[-1:], ids[-1:], n[-1:], np.ones(1, bool)]
            if len(rows[0]):
                a, b, least = pairs_of(*rows)
                if len(a):
                    yield _met(a, b, least)
        if held is not None and len(held[0]) > 1:
            a, b, least = pairs_of(*held)
            if len(a):
                yield _met(a, b, least)

    met = parts.mapInArrow(run, "a long, b long, met int, least int")
    return met.groupBy("a", "b").agg(F.sum("met").alias("met"), F.min("least").alias("least")).where("met >= least").select("a", "b")


def family_links(ids: np.ndarray, sets: list[np.ndarray], num: int, den: int) -> list[tuple[int, int]]:
    """Links of similarity num/den or more that span the components of these sets, by exact overlaps."""
    f = len(sets)
    sizes = np.array([len(s) for s in sets], np.int64)
    token, df = np.unique(np.concatenate(sets), return_counts=True)
    token = token[df > 1]
    cols = []
    for s in sets:
        at = np.minimum(np.searchsorted(token, s), max(0, len(token) - 1))
        cols.append(at[token[at] == s] if len(token) else at[:0])
    shared = np.array([len(c) for c in cols], np.int64)
    # A set with too many tokens of its own is linked with nothing.
    able = np.flatnonzero(den * shared >= num * sizes)
    able = able[np.argsort(sizes[able], kind="stable")]
    if len(able) < 2:
        return []
    dense = len(able) * (len(token) // 8 + 1) <= DENSE_BYTES
    if dense:
        bits = np.zeros((len(able), -(-len(token) // 64) * 8), np.uint8)
        for r, i in enumerate(able):
            line = np.zeros(bits.shape[1] * 8, np.uint8)
            line[cols[i]] = 1
            bits[r] = np.packbits(line)
        bits = bits.view(np.uint64)
    else:
        order = np.concatenate([cols[i] for i in able])
        owner = np.repeat(np.arange(len(able)), shared[able])
        by_token = np.argsort(order, kind="stable")
        posting, begin = owner[by_token], np.searchsorted(order[by_token], np.arange(len(token) + 1))
    n = sizes[able]
    group = np.arange(len(able))
    out = []
    for r in range(len(able) - 1):
        # Sizes rise, so only sets up to den/num of this size can be near enough.
        end = int(np.searchsorted(n, n[r] * den // num, "right"))
        other = np.flatnonzero(group[r + 1 : end] != group[r]) + r + 1
        if not len(other):
            continue
        if dense:
            both = np.bitwise_count(bits[other] & bits[r]).sum(1, dtype=np.int64)
        else:
            met = np.concatenate([posting[begin[t] : begin[t + 1]] for t in cols[able[r]]])
            both = np.bincount(met, minlength=len(able))[other]
        for k in other[den * both >= num * (n[r] + n[other] - both)]:
            if group[k] != group[r]:
                out.append((int(ids[able[r]]), int(ids[able[k]])))
                group[group == group[k]] = group[r]
    return out


def _compare(groups: DataFrame, keys: list[str], num: int, den: int) -> DataFrame:
    """Links (a, b) within each group of rows (keys, id, text); groups are of bounded size."""
    dealt = groups.select(*keys, "id", "text").repartition(*keys).sortWithinPartitions(*keys)
    width = len(keys)

    def run(batches):
        key, ids, sets = None, [], []

        def close():
            links = family_links(np.array(ids, np.int64), sets, num, den) if len(sets) > 1 else []
            if links:
                a, b = zip(*((min(x), max(x)) for x in links), strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

        for batch in batches:
            columns = [batch.column(i).to_pylist() for i in range(width + 1)]
            for first, chunk in common.utf8_chunks(_row(batch, "text")):
                for i, s in enumerate(shingle_sets(chunk), first):
                    now = tuple(c[i] for c in columns[:width])
                    if now != key:
                        yield from close()
                        key, ids, sets = now, [], []
                    ids.append(columns[width][i])
                    sets.append(s)
        yield from close()

    return dealt.mapInArrow(run, "a long, b long")


def candidates(texts: DataFrame, tokens: int, num: int, den: int) -> DataFrame:
    """(id, component): the families of texts (doc_id, text, [family]) that share signatures; texts that share none are absent.

    tokens: about how many members the sets have altogether, for the size of the sketch.
    """
    cells = cell_count(tokens)
    sketch = count_sketch(texts, cells)
    shared = texts.sparkSession.sparkContext.broadcast(sketch)
    del sketch
    near = common.checkpointed(chains(signatures(texts, shared, tokens / cells, num, den), num, den))
    shared.destroy()
    found = common.checkpointed(common.components(near))
    common.discard(near)
    return found


def _large(rows: DataFrame) -> DataFrame:
    """(family, sets, blocks) of the families that exceed a block; at most one for each block of the input."""
    sized = rows.groupBy("family").agg(F.count("*").alias("sets"), F.sum(F.octet_length("text")).alias("bytes"))
    blocks = F.greatest(F.ceil(F.col("sets") / BLOCK_SETS), F.ceil(F.col("bytes") / BLOCK_BYTES))
    return common.checkpointed(sized.withColumn("blocks", blocks).where("blocks > 1").select("family", "sets", "blocks"))


def jaccard_links(texts: DataFrame, num: int, den: int, tokens: int) -> DataFrame:
    """Links (a, b) that span every component of the graph of pairs with similarity num/den or more.

    texts: (doc_id, text), no two with the same set; tokens: how many members the sets have altogether.
    """
    family = candidates(texts, tokens, num, den)
    keyed = texts.select(F.col("doc_id").alias("id"), "text")
    if family.count() <= BROADCAST_IDS:
        member = keyed.join(F.broadcast(family), "id")
    else:
        # Only texts of some family are shuffled.
        member = keyed.where(in_bitmap(family, "id")).join(family, "id")
    rows = common.checkpointed(member.select("id", "text", F.col("component").alias("family")))
    large = _large(rows)
    for _ in range(REFINEMENTS):
        if large.isEmpty():
            break
        before = large.agg(F.sum("sets")).first()[0]
        apart = rows.join(large, "family", "left_semi")
        finer = candidates(apart.withColumnRenamed("id", "doc_id"), before * 256, num, den)
        again = common.checkpointed(apart.drop("family").join(finer, "id").select("id", "text", F.col("component").alias("family")))
        rows = rows.join(large, "family", "left_anti").select("id", "text", "family").unionByName(again)
        large = _large(again)
        if (large.agg(F.sum("sets")).first()[0] or 0) > 0.9 * before:
            break
    if large.isEmpty():
        return common.checkpointed(_compare(rows, ["family"], num, den))
    large = large.select("family", "blocks")
    small = _compare(rows.join(large, "family", "left_anti"), ["family"], num, den)
    cut = rows.join(large, "family").withColumn("block", F.pmod(F.xxhash64("id"), F.col("blocks")))
    pivots = _pivots(rows.join(large, "family"))
    shared = pivots.select("family", "id", "text", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("block"))
    first = common.checkpointed(small.unionByName(_compare(cut.select("family", "block", "id", "text").unionByName(shared), ["family", "block"], num, den)))
    # What is not tied to its family's largest component is compared with every block.
    found = cut.join(common.components(first), "id", "left").withColumn("component", F.coalesce("component", "id"))
    found = common.checkpointed(found.select("family", "block", "blocks", "id", "component", "text"))
    main = found.groupBy("family", "component").agg(F.count("*").alias("n")).groupBy("family").agg(F.max_by("component", F.struct("n", "component")).alias("main"))
    loose = found.join(main, "family").where("component <> main")
    counted = loose.groupBy("family").agg(F.greatest(F.ceil(F.count("*") / BLOCK_SETS), F.ceil(F.sum(F.octet_length("text")) / BLOCK_BYTES)).alias("parts"))
    dealt = loose.join(counted, "family").withColumn("part", F.pmod(F.xxhash64("id", F.lit(2)), F.col("parts")))
    parts = dealt.select("family", "part").distinct()
    guests = dealt.select("family", "part", "id", "text", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)).alias("block"))
    hosts = found.select("family", "block", "id", "text").join(parts, "family").select("family", "part", "id", "text", "block")
    second = _compare(guests.unionByName(hosts).dropDuplicates(["family", "part", "block", "id"]), ["family", "part", "block"], num, den)
    return common.checkpointed(first.unionByName(second))


def _pivots(rows: DataFrame) -> DataFrame:
    """PIVOTS rows of each family, those of the smallest hash; partial results are as short."""
    from pyspark.sql import Window

    order = Window.partitionBy("family").orderBy("h", "id")
    # A first cut by hash leaves few rows to rank, however large the family.
    cut = rows.withColumn("h", F.xxhash64("id", F.lit(1))).where(F.pmod("h", F.col("blocks")) == 0)
    return cut.withColumn("r", F.row_number().over(order)).where(F.col("r") <= PIVOTS).select("family", "blocks", "id", "text")


def similarity_classes(docs: DataFrame, num: int = 3, den: int = 4) -> DataFrame:
    """(doc_id, n_shingles, component_id) for every row of docs (doc_id, text).

    Words are runs of anything but ASCII white space, A-Z lower-cased; a set holds the distinct
    5-word shingles, or the whole text where it has fewer words.  Null, empty and blank texts have
    n_shingles 0 and link with nothing.  component_id is the smallest doc_id reachable over links of
    similarity num/den or more.  Rows that repeat a doc_id are one node of the graph.  An empty
    table gives no rows.  A null doc_id keeps its row, with itself as component.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    keys = common.checkpointed(set_keys(docs))
    copies = common.checkpointed(
        keys.where("set_key is not null and doc_id is not null").groupBy("set_key").agg(F.min("doc_id").alias("rep"), F.count("*").alias("copies"))
    )
    reps = copies.select(F.col("rep").alias("doc_id")).distinct()
    others = common.checkpointed(keys.where("doc_id is not null").select("doc_id").distinct().join(reps, "doc_id", "left_anti"))
    whole = docs.where("text is not null and doc_id is not null")
    if others.count() <= BROADCAST_IDS:
        texts = whole.join(F.broadcast(others), "doc_id", "left_anti")
    else:
        # Of the whole texts, only those that may be copies are shuffled to find out.
        whole = whole.withColumn("doubt", in_bitmap(others.withColumnRenamed("doc_id", "id"), "doc_id"))
        texts = whole.where("not doubt").drop("doubt").unionByName(whole.where("doubt").drop("doubt").join(others, "doc_id", "left_anti"))
    tokens = keys.agg(F.sum("n_shingles")).first()[0] or 0
    links = jaccard_links(texts, num, den, tokens)
    member = common.checkpointed(common.lookup_join(keys, copies, "set_key", "copies", F.col("doc_id")))
    same = member.where("rep <> doc_id").select(F.col("doc_id").alias("a"), F.col("rep").alias("b"))
    twice = keys.where("doc_id is not null").groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1").select("doc_id")
    # Only where an id is repeated can a copy tie two representatives together.
    links = links.unionByName(same.join(twice.withColumnRenamed("doc_id", "a"), "a", "left_semi"))
    found = common.checkpointed(common.components(links))
    weighted = copies.groupBy(F.col("rep")).agg(F.sum("copies").alias("copies"))
    classes = common.checkpointed(weighted.join(found.withColumnRenamed("id", "rep"), "rep", "left").withColumn("component", F.coalesce("component", "rep")))
    out = common.lookup_join(member, classes, "rep", "copies", F.col("doc_id"))
    return out.select("doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component_id"))
