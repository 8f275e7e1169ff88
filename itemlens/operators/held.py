"""Distinct baskets over few items, held by the driver as rows of bits.

Where the items are few (nations and regions, event types), so are the distinct baskets, however
many baskets there are.  Up to `BYTES` of them travel to the driver once, and each pass of a method
is an array operation there instead of a job.  Beyond either limit the passes stay distributed, with
the same results.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Items that held baskets may have, and bytes that they may take.
ITEMS, BYTES = 256, 32 << 20
#: Rows that an array operation takes at once.
ROWS = 1 << 15


def words_of(lists: pa.Array, place: pa.Array) -> np.ndarray:
    """Baskets as rows of 64-bit words: a bit for each item of `place` that a basket holds."""
    wide = -(-max(1, len(place)) // 64)
    out = np.empty((len(lists), wide), np.uint64)
    at_once = max(1, (1 << 25) // (64 * wide))
    for start in range(0, len(lists), at_once):
        part = lists.slice(start, at_once)
        found = pc.index_in(part.flatten(), value_set=place)
        held = np.zeros((len(part), 64 * wide), np.uint8)
        known = found.is_valid().to_numpy(zero_copy_only=False)
        held[np.repeat(np.arange(len(part)), pc.list_value_length(part).to_numpy(zero_copy_only=False))[known], found.drop_null().to_numpy()] = 1
        out[start : start + len(part)] = np.packbits(held, axis=1, bitorder="little").view("<u8")
    return out


class Held:
    """words: a column for each distinct basket, a row for each 64 items; mult: how often each occurs."""

    def __init__(self, items: list[str], words: np.ndarray, mult: np.ndarray):
        self.items, self.words, self.mult = items, np.ascontiguousarray(words), mult
        self.bit = {i: divmod(n, 64) for n, i in enumerate(items)}

    def mask(self, items) -> list[tuple[int, np.uint64]]:
        of: dict[int, int] = {}
        for i in items:
            w, b = self.bit[i]
            of[w] = of.get(w, 0) | 1 << b
        return [(w, np.uint64(x)) for w, x in sorted(of.items())]

    def having(self, items, among: np.ndarray | None = None) -> np.ndarray:
        """Which baskets hold all the items."""
        words, out = self.words if among is None else among, None
        for w, x in self.mask(items):
            here = (words[w] & x) == x
            out = here if out is None else out & here
        return np.ones(words.shape[1], bool) if out is None else out

    def supports(self, unions) -> dict[str, int]:
        """Supports of sets by key, as `candidates.counted`; those without any are absent."""
        sums = dict.fromkeys(range(len(unions)), 0)
        known = [n for n, u in enumerate(unions) if all(i in self.bit for i in u)]
        for start in range(0, len(self.mult), ROWS):
            words, mult = self.words[:, start : start + ROWS], self.mult[start : start + ROWS]
            for n in known:
                sums[n] += int(mult[self.having(unions[n], words)].sum())
        return {"|".join(unions[n]): s for n, s in sums.items() if s}

    def columns(self, start: int) -> np.ndarray:
        """ROWS baskets from `start` as rows of zeros and ones, a column for each item."""
        part = np.ascontiguousarray(self.words[:, start : start + ROWS].T)
        return np.unpackbits(part.view(np.uint8), axis=1, bitorder="little")[:, : len(self.items)]

    def pairs(self, at_least: int = 1) -> list[tuple[str, str, int]]:
        """(a, b, support) of all pairs of items that meet, a before b."""
        met = np.zeros((len(self.items), len(self.items)))
        for start in range(0, len(self.mult), ROWS):
            bits = self.columns(start).astype(float)
            met += (bits * self.mult[start : start + ROWS, None]).T @ bits
        return [(self.items[a], self.items[b], int(met[a, b])) for a, b in zip(*np.nonzero(np.triu(met, 1) >= at_least), strict=True)]

    def parts(self, items, rows: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """The distinct parts within `items` of all baskets, or of some rows: (words, mult)."""
        words, mult = (self.words, self.mult) if rows is None else (self.words[:, rows], self.mult[rows])
        kept = np.zeros(len(self.words), np.uint64)
        for w, x in self.mask(items):
            kept[w] = x
        used = np.flatnonzero(kept)
        cut = words[used] & kept[used, None]
        if len(used) == 1:
            found, of = np.unique(cut[0], return_inverse=True)
            found = found[None, :]
        else:
            found, of = np.unique(cut, axis=1, return_inverse=True)
        out = np.zeros((len(self.words), found.shape[1]), np.uint64)
        out[used] = found
        sums = np.zeros(found.shape[1], np.int64)
        np.add.at(sums, of.ravel(), mult)
        return out, sums

    def within(self, items) -> Held:
        """The distinct parts of the baskets within `items`, and no other items."""
        items = sorted(i for i in items if i in self.bit)
        words, mult = self.parts(items)
        old, wide = Held(self.items, words, mult), -(-max(1, len(items)) // 64)
        out, columns = np.zeros((wide, len(mult)), np.uint64), [self.items.index(i) for i in items]
        for start in range(0, len(mult), ROWS):
            bits = old.columns(start)
            packed = np.zeros((len(bits), 64 * wide), np.uint8)
            packed[:, : len(items)] = bits[:, columns]
            out[:, start : start + len(bits)] = np.packbits(packed, axis=1, bitorder="little").view("<u8").T
        return Held(items, out, mult)

    def names(self, words: np.ndarray) -> list[tuple[str, ...]]:
        """The items of each column, in order."""
        out = []
        for column in words.T:
            found = []
            for w, x in enumerate(column.tolist()):
                while x:
                    found.append(self.items[64 * w + (x & -x).bit_length() - 1])
                    x &= x - 1
            out.append(tuple(found))
        return out


def held(compressed: DataFrame, items) -> Held | None:
    """Weighted distinct baskets of few items; None if there are too many."""
    items = sorted(items)
    wide = -(-max(1, len(items)) // 64)
    if not 0 < len(items) <= ITEMS or 8 * (wide + 1) * compressed.count() > BYTES:
        return None
    shared = compressed.sparkSession.sparkContext.broadcast(items)

    def pack(batches):
        place = pa.array(shared.value, pa.string())
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([words_of(b.column(0), place).tobytes()], pa.binary()), pa.array([b.column(1).to_numpy().astype("<i8").tobytes()], pa.binary())], ["words", "mults"])

    rows = compressed.select("items", "mult").mapInArrow(pack, "words binary, mults binary").collect()
    shared.unpersist()
    words = [np.frombuffer(r["words"], "<u8").reshape(-1, wide) for r in rows] or [np.zeros((0, wide), np.uint64)]
    mult = [np.frombuffer(r["mults"], "<i8") for r in rows] or [np.zeros(0, np.int64)]
    return Held(items, np.concatenate(words).T, np.concatenate(mult))
