"""Vectorised hashing of words and word shingles, for Arrow batches of texts."""

from __future__ import annotations

import numpy as np

SHINGLE_WORDS = 5
_ODD = np.uint64(0x9E3779B97F4A7C15)
_JOIN = np.uint64(0xA24BAED4963EE407)
#: Bytes of a word that have a table row each; longer words are hashed in runs of as many bytes.
PLACES = 64


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser of 64 bits (the published splitmix64 constants)."""
    with np.errstate(over="ignore"):
        x = x + _ODD
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True
#: A number for each byte at each place, unrelated to all others; white space counts nothing.
_TABLE = mix64(mix64(np.arange(PLACES * 256, dtype=np.uint64) + np.uint64(1)))
_TABLE.reshape(PLACES, 256)[:, _SPACE] = 0


def segments_hash(data: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """A hash of each run of bytes from one start to the next; white space at a run's end does not count.

    A run's hash is the sum of the table's numbers of its bytes at their places, so no algebra ties
    the places to each other; of longer runs, the hashes of their parts are mixed with the part's
    number before they are added.
    """
    if not len(starts):
        return np.zeros(0, np.uint64)
    lengths = np.diff(np.append(starts, len(data)))
    begin, body = starts - starts[0], data[starts[0] :]
    place = np.arange(len(body)) - np.repeat(begin, lengths)
    if int(lengths.max()) <= PLACES:
        return mix64(np.add.reduceat(_TABLE[(place << 8) | body], begin))
    part = np.flatnonzero(place % PLACES == 0)
    sums = np.add.reduceat(_TABLE[((place % PLACES) << 8) | body], part)
    number = (place[part] // PLACES).astype(np.uint64)
    with np.errstate(over="ignore"):
        later = mix64(sums ^ mix64(number * _JOIN))
        sums = np.where(number == 0, sums, np.where(sums == 0, np.uint64(0), later))
        return mix64(np.add.reduceat(sums, np.searchsorted(part, begin)))


def words(texts: list[bytes], lower: bool = True) -> tuple[np.ndarray, np.ndarray]:
    """(hash of each word of all texts in order, first word of each text and the end)."""
    joined = b"\n".join(texts)
    data = np.frombuffer(joined.lower() if lower else joined, np.uint8)
    space = _SPACE[data]
    begins = ~space
    begins[1:] &= space[:-1]
    starts = np.flatnonzero(begins)
    ends = np.cumsum([len(t) + 1 for t in texts])
    return segments_hash(data, starts), np.append(0, np.searchsorted(starts, ends))


def shingle_sets(texts: list[bytes], k: int = SHINGLE_WORDS) -> list[np.ndarray]:
    """Each text's distinct k-word shingles as sorted 64-bit hashes; a shorter text is one shingle, no word none."""
    hashes, first = words(texts)
    n = len(hashes)
    with np.errstate(over="ignore"):
        joined = hashes[: max(0, n - k + 1)].copy()
        for j in range(1, k):
            joined = joined * _JOIN + hashes[j : n - k + 1 + j]
        joined = mix64(joined)
        out = []
        for a, b in zip(first[:-1], first[1:], strict=True):
            if b - a >= k:
                out.append(np.unique(joined[a : b - k + 1]))
            elif b > a:
                whole = np.uint64(b - a)
                for h in hashes[a:b]:
                    whole = whole * _JOIN + h
                out.append(mix64(np.array([whole])))
            else:
                out.append(np.zeros(0, np.uint64))
    return out
