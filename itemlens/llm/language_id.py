"""Language identification by unigram pieces, summed over all segmentations of each word.

Each language has a probability for every piece of a fixed public vocabulary.  A forward pass adds
up all ways to cut a word into pieces; a text's score for a language is the sum over its words.
Piece probabilities are fitted by expectation maximisation on labelled rows, so training too
weighs every segmentation instead of choosing one.  A word is a run of letters (Unicode category
L) of the lower-cased text, of any length.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from itertools import groupby

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

VOCABULARY = "piece_bpe_32k.model"
#: Labelled rows that the model is fitted on, at most for each language: those of the smallest hash.  All their words count.
TRAINING_ROWS = 400
EM_STEPS = 3
SMOOTHING = 0.5
#: Expected uses are added as whole numbers of this share, so that sums do not depend on their order.
USES_SHARE = 1 << 20
#: Sums are kept in range by this factor (as a log) for each character.
CHARACTER_SCALE = 7.0
#: Words of up to so many letters are scored many at a time; longer ones, and those whose sums come near the end of the range, one by one with rescaling.
BATCHED_LETTERS, LEAST_SUM = 48, 1e-200
#: Words whose scores a task keeps for later texts; then it starts anew.
KEPT_WORDS = 200_000
UNKNOWN = "und"
_RUN = re.compile(r"[^\W\d_]+")
_BASE = np.uint64(0xD1342543DE82EF95)


def words(text: str | None) -> list[str]:
    out = []
    for run in _RUN.findall(text.lower()) if text else ():
        if run.isalpha():
            out.append(run)
        else:
            # Numerals that are not decimal digits, as in "x²", are no letters.
            out += ["".join(part) for letters, part in groupby(run, str.isalpha) if letters]
    return out


def vocabulary(name: str = VOCABULARY) -> dict[str, int]:
    """Pieces of letters, lower-cased, with "▁" for a word's start, and every single letter they hold."""
    import public_tokenizers
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path(name))
    pieces = {p.lower() for p in map(model.id_to_piece, range(model.get_piece_size()))}
    kept = sorted({p for p in pieces if p.replace("▁", "").isalpha() and "▁" not in p[1:]} | {"▁"})
    return {p: i for i, p in enumerate(kept)}


def unknown_log(logp: np.ndarray) -> float:
    """The log probability of a letter that is no piece."""
    return float(logp.min()) - 2


class Pieces:
    """Forward sums over the segmentations of words, for all languages at once."""

    def __init__(self, pieces: dict[str, int], logp: np.ndarray):
        logp = logp.astype(np.float64)
        each = np.exp(logp.T)
        self.rows = {p: each[i] for p, i in pieces.items()}
        self.langs = len(logp)
        self.unknown = math.exp(unknown_log(logp))
        self.longest = max(map(len, pieces))
        # Pieces by the hash of their characters, for whole arrays of substrings at once.
        names = sorted(pieces, key=pieces.get)
        by_hash = np.zeros(len(names), np.uint64)
        sizes = np.array([len(p) for p in names])
        for n in np.unique(sizes):
            at = np.flatnonzero(sizes == n)
            by_hash[at] = self._hash(self._codes([names[i] for i in at], int(n)))[:, -1]
        order = np.argsort(by_hash)
        self.hashes = by_hash[order]
        if (self.hashes[1:] == self.hashes[:-1]).any():
            raise ValueError("two pieces share a hash")
        self.table = (np.exp(logp) * np.exp(CHARACTER_SCALE * sizes)).T[order]
        self.filter = np.zeros(1 << 22, bool)
        self.filter[self._slot(self.hashes)] = True
        self._forget()

    def _forget(self) -> None:
        self.place: dict[str, int] = {}
        self.known = np.zeros((0, self.langs))

    @staticmethod
    def _codes(texts: list[str], length: int) -> np.ndarray:
        return np.frombuffer("".join(texts).encode("utf-32-le", "surrogatepass"), "<u4").reshape(len(texts), length).astype(np.uint64)

    @staticmethod
    def _slot(h: np.ndarray) -> np.ndarray:
        return ((h * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(42)).astype(np.int64)

    @staticmethod
    def _hash(chars: np.ndarray) -> np.ndarray:
        """Hashes of all prefixes of the rows, the empty one first."""
        out = np.zeros((len(chars), chars.shape[1] + 1), np.uint64)
        with np.errstate(over="ignore"):
            for j in range(chars.shape[1]):
                out[:, j + 1] = out[:, j] * _BASE + chars[:, j] + np.uint64(1)
        return out

    def scores(self, words: list[str]) -> np.ndarray:
        """Log probability of each word in each language."""
        out = np.zeros((len(words), self.langs))
        by_length: dict[int, list[int]] = {}
        for n, w in enumerate(words):
            by_length.setdefault(len(w) if len(w) <= BATCHED_LETTERS else 0, []).append(n)
        alone = by_length.pop(0, [])
        for length, rows in by_length.items():
            for at in range(0, len(rows), 20_000):
                some = np.array(rows[at : at + 20_000])
                sums = self._forward([words[k] for k in some], length)
                small = (sums < LEAST_SUM).any(1)
                out[some[~small]] = np.log(sums[~small]) - CHARACTER_SCALE * (length + 1)
                alone += some[small].tolist()
        for n in alone:
            out[n] = self._rescaled(words[n])
        return out

    def _forward(self, words: list[str], length: int) -> np.ndarray:
        """Sums of words of one length, times the scale of each of their characters."""
        chars = np.empty((len(words), length + 1), np.uint64)
        chars[:, 0] = ord("▁")
        chars[:, 1:] = self._codes(words, length)
        prefix = self._hash(chars)
        power = [np.uint64(1)]
        with np.errstate(over="ignore"):
            for _ in range(self.longest):
                power.append(power[-1] * _BASE)
        alpha = np.zeros((length + 2, len(words), self.langs))
        alpha[0] = 1
        single = self.unknown * math.exp(CHARACTER_SCALE)
        for j in range(1, length + 2):
            for i in range(max(0, j - self.longest), j):
                with np.errstate(over="ignore"):
                    h = prefix[:, j] - prefix[:, i] * power[j - i]
                hit = np.flatnonzero(self.filter[self._slot(h)])
                if len(hit):
                    at = np.minimum(np.searchsorted(self.hashes, h[hit]), len(self.hashes) - 1)
                    true = self.hashes[at] == h[hit]
                    hit, at = hit[true], at[true]
                    alpha[j, hit] += alpha[i, hit] * self.table[at]
                if j == i + 1 and len(hit) < len(words):
                    rest = np.ones(len(words), bool)
                    rest[hit] = False
                    alpha[j, rest] += alpha[i, rest] * single
        return alpha[-1]

    def _rescaled(self, word: str) -> np.ndarray:
        """The log of the same sum for one word of any length: the sums that are still needed are rescaled as they get small."""
        text, sums, shift = "▁" + word, [np.ones(self.langs)], np.zeros(self.langs)
        for j in range(1, len(text) + 1):
            total = np.zeros(self.langs)
            for back in range(1, min(j, self.longest) + 1):
                p = self.rows.get(text[j - back : j], self.unknown if back == 1 else None)
                if p is not None:
                    total += sums[-back] * p
            sums = [*sums[1 - self.longest :], total] if self.longest > 1 else [total]
            if total.min() < 1e-100:
                sums = [s / total for s in sums]
                shift += np.log(total)
        return shift + np.log(sums[-1])

    def totals(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """(log probability of each text's words in each language, number of words)."""
        found = [words(t) for t in texts]
        distinct = dict.fromkeys(w for ws in found for w in ws)
        new = [w for w in distinct if w not in self.place]
        if len(self.place) + len(new) > KEPT_WORDS:
            self._forget()
            new = list(distinct)
        if new:
            self.known = np.concatenate([self.known, self.scores(new)])
            self.place.update(zip(new, range(len(self.place), len(self.place) + len(new)), strict=True))
        counts = np.array([len(ws) for ws in found], np.int64)
        out = np.zeros((len(texts), self.langs))
        if distinct:
            each = self.known[np.fromiter((self.place[w] for ws in found for w in ws), np.int64, int(counts.sum()))]
            owner = np.repeat(np.arange(len(texts)), counts)
            for k in range(self.langs):
                out[:, k] = np.bincount(owner, each[:, k], minlength=len(texts))
        return out, counts


def segment_uses(word: str, p: dict[str, float], unknown: float, longest: int) -> dict[str, float]:
    """Expected uses of each piece over all segmentations of a word; p: probabilities of pieces, unknown: of other letters."""
    text = "▁" + word
    size = len(text)
    edges = []
    for j in range(1, size + 1):
        for i in range(max(0, j - longest), j):
            q = p.get(text[i:j], unknown if j == i + 1 else None)
            if q is not None:
                edges.append((i, j, q))
    alpha, beta = [0.0] * (size + 1), [0.0] * (size + 1)
    alpha[0] = beta[size] = 1.0
    for i, j, q in edges:
        alpha[j] += alpha[i] * q
    if alpha[size] > LEAST_SUM:
        for i, j, q in reversed(edges):
            beta[i] += beta[j] * q
        shares = [alpha[i] * q * beta[j] / alpha[size] for i, j, q in edges]
    else:
        # Beyond the range of numbers: the same in logs.
        alpha, beta = [-math.inf] * (size + 1), [-math.inf] * (size + 1)
        alpha[0] = beta[size] = 0.0
        for i, j, q in edges:
            alpha[j] = float(np.logaddexp(alpha[j], alpha[i] + math.log(q)))
        for i, j, q in reversed(edges):
            beta[i] = float(np.logaddexp(beta[i], beta[j] + math.log(q)))
        shares = [math.exp(alpha[i] + math.log(q) + beta[j] - alpha[size]) for i, j, q in edges]
    out: dict[str, float] = {}
    for (i, j, _), share in zip(edges, shares, strict=True):
        out[text[i:j]] = out.get(text[i:j], 0.0) + share
    return out


def word_counts(texts: DataFrame) -> DataFrame:
    """(lang, word, n) of rows (lang, text), folded in each task's batches first."""

    def run(batches):
        for batch in batches:
            counts: Counter = Counter()
            for lang, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                counts.update((lang, w) for w in words(text))
            if counts:
                langs, found = zip(*counts, strict=True)
                yield pa.RecordBatch.from_arrays([pa.array(langs), pa.array(found), pa.array(counts.values(), pa.int64())], ["lang", "word", "n"])

    return texts.select("lang", "text").mapInArrow(run, "lang string, word string, n long").groupBy("lang", "word").agg(F.sum("n").alias("n"))


def expected_uses(counts: DataFrame, langs: list[str], pieces: dict[str, int], logp: np.ndarray) -> np.ndarray:
    """Expected uses of each piece in each language over all words; executors add them up, a number for each language and piece comes back."""
    shared = counts.sparkSession.sparkContext.broadcast((langs, pieces, logp))

    def run(batches):
        langs, pieces, logp = shared.value
        unknown, longest = math.exp(unknown_log(logp)), max(map(len, pieces))
        place = {lang: k for k, lang in enumerate(langs)}
        p: dict[int, dict[str, float]] = {}
        sums = np.zeros(logp.shape, np.int64)
        for batch in batches:
            for lang, word, n in zip(*(batch.column(c).to_pylist() for c in range(3)), strict=True):
                k = place[lang]
                if k not in p:
                    p[k] = dict(zip(pieces, np.exp(logp[k][list(pieces.values())]).tolist(), strict=True))
                for piece, share in segment_uses(word, p[k], unknown, longest).items():
                    if piece in pieces:
                        sums[k, pieces[piece]] += round(n * share * USES_SHARE)
        lang, piece = np.nonzero(sums)
        if len(lang):
            yield pa.RecordBatch.from_arrays([pa.array(lang.astype(np.int32)), pa.array(piece.astype(np.int32)), pa.array(sums[lang, piece])], ["lang", "piece", "uses"])

    tasks = max(8, counts.sparkSession.sparkContext.defaultParallelism)
    parts = counts.select("lang", "word", "n").repartition(tasks).mapInArrow(run, "lang int, piece int, uses long")
    got = parts.groupBy("lang", "piece").agg(F.sum("uses").alias("uses")).toArrow()
    out = np.zeros(logp.shape)
    out[got.column("lang").to_numpy(), got.column("piece").to_numpy()] = got.column("uses").to_numpy() / USES_SHARE
    shared.unpersist()
    return out


def fit(labelled: DataFrame, vocabulary_name: str = VOCABULARY, rows: int = TRAINING_ROWS) -> dict:
    """Languages and their piece log probabilities, from labelled rows (doc_id, text, lang).

    The sample is bounded: `rows` whole texts of each language, those of the smallest hash of their
    doc_id; all their words are counted.
    """
    from pyspark.sql import Window

    order = Window.partitionBy("lang").orderBy("h", "doc_id")
    chosen = labelled.where("lang is not null and text is not null and doc_id is not null").select("doc_id", "lang", F.xxhash64("doc_id").alias("h"))
    # A first cut by hash keeps the ranking small; it leaves four times the rows on average.
    sizes = {r["lang"]: r["n"] for r in chosen.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    if not sizes:
        return {"langs": [], "pieces": {}, "logp": np.zeros((0, 0))}
    share = F.create_map(*[F.lit(x) for lang, n in sizes.items() for x in (lang, float(min(1.0, 4 * rows / n + 1e-9)))])
    cut = chosen.where(F.pmod("h", F.lit(1 << 20)) < share[F.col("lang")] * (1 << 20))
    picked = cut.withColumn("r", F.row_number().over(order)).where(F.col("r") <= rows).select("doc_id", "lang").distinct()
    texts = labelled.select("doc_id", "lang", "text").join(F.broadcast(picked), ["doc_id", "lang"])
    counts = common.checkpointed(word_counts(texts))
    langs, pieces = sorted(sizes), vocabulary(vocabulary_name)
    logp = np.full((len(langs), len(pieces)), -math.log(len(pieces)))
    for _ in range(EM_STEPS):
        uses = expected_uses(counts, langs, pieces, logp)
        # Smoothing goes by what all languages use, so a rare piece does not favour the smallest language.
        prior = (uses.sum(0) + 1) / (uses.sum() + len(pieces))
        smooth = uses + SMOOTHING * len(pieces) * prior * 0.1 + 1e-6
        logp = np.log(smooth / smooth.sum(1, keepdims=True))
    common.discard(counts)
    return {"langs": langs, "pieces": pieces, "logp": logp.astype(np.float32)}


def predict(docs: DataFrame, model: dict, carry: list[str] | None = None) -> DataFrame:
    """(doc_id, lang_pred, score, [carry]) of each whole text: the likeliest language and its posterior at equal priors.

    Without a letter, or with a null text, lang_pred is "und" and score 0.  Ties go to the first
    language in order.
    """
    langs, carry = model["langs"], carry or []
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        m = shared.value
        scorer = Pieces(m["pieces"], m["logp"]) if langs else None
        for batch in batches:
            preds, scores = [], []
            texts = batch.column(1).to_pylist()
            for chunk in _chunks(texts):
                if scorer is None:
                    preds += [UNKNOWN] * len(chunk)
                    scores += [0.0] * len(chunk)
                    continue
                total, counts = scorer.totals(chunk)
                best = total.argmax(1)
                post = 1 / np.exp(np.maximum(total - total.max(1, keepdims=True), -700)).sum(1)
                preds += [langs[k] if n else UNKNOWN for k, n in zip(best, counts, strict=True)]
                scores += np.where(counts > 0, post, 0.0).tolist()
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(preds, pa.string()), pa.array(scores, pa.float64()), *batch.columns[2:]], ["doc_id", "lang_pred", "score", *carry])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").alias("_text"), *carry)
    kept = "".join(f", `{c}` {docs.schema[c].dataType.simpleString()}" for c in carry)
    return rows.mapInArrow(run, f"doc_id long, lang_pred string, score double{kept}")


def _chunks(texts: list) -> list[list]:
    """Runs of about a megabyte."""
    out, size = [[]], 0
    for text in texts:
        if size > common.CHUNK_BYTES:
            out.append([])
            size = 0
        out[-1].append(text)
        size += len(text) if text else 0
    return out


def held_out():
    """Rows that training never sees: crc32 of the doc_id as text leaves 2 modulo 4."""
    return F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(4)) == 2


def identified(docs: DataFrame, carry: list[str] | None = None) -> DataFrame:
    """One row per row of docs (doc_id, text, lang): doc_id, held_out, lang_pred, score, and the columns named in carry.

    lang is read for training alone, from rows that are not held out.  An empty table gives no rows;
    a null doc_id is scored, not trained on, and counts as not held out; repeated rows are scored alike.
    """
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), *dict.fromkeys(["text", "lang", *(carry or [])]))
    model = fit(rows.where(~F.coalesce(held_out(), F.lit(True))))
    return predict(rows, model, carry).select("doc_id", F.coalesce(held_out(), F.lit(False)).alias("held_out"), "lang_pred", "score", *(carry or []))
