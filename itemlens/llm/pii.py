"""Personal data by weak supervision: labelers vote, their reliabilities are estimated, a classifier decides.

Four base kinds are found by fixed patterns and always stay.  Further candidates come from loose
patterns that also match much that is harmless: long mixed strings, plain numbers, capitalised
words.  Labelers of three sorts vote on each candidate and often disagree: patterns and check
digits, word lists, and the words and marks around it.  Expectation maximisation over the vote
patterns of all documents estimates how reliable each labeler is, and so how likely each candidate
is personal data.  Those posteriors train the span classifier, which sees none of the votes but the
span's own text, shape and surroundings; candidates that it accepts are added.
"""

from __future__ import annotations

import math
import re
import zlib
from bisect import bisect_right
from collections import Counter

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

BASE_KINDS = ("email", "ip", "card", "phone")
KINDS = (*BASE_KINDS, "iban", "mac", "name", "number", "secret", "ssn")
ACCEPT = 0.5
EM_STEPS = 50
#: Candidate spans that the classifier is trained on, at most: those of the smallest hash of document and place.
TRAINING_SPANS = 20_000
#: Features of a span are hashed to so many bits; the penalty on their weights, and the steps of training.
FEATURE_BITS, PENALTY, TRAINING_STEPS = 12, 0.02, 200

_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_LOCAL = frozenset("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789._%+-")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])++")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_DIGIT = re.compile(r"[0-9]")

# Loose candidates; each kind with its pattern.
_MORE = (
    ("iban", re.compile(r"(?<![A-Za-z0-9])[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){3,7}(?: ?[A-Z0-9]{1,3})?(?![A-Za-z0-9])")),
    ("mac", re.compile(r"(?<![0-9A-Fa-f:-])[0-9A-Fa-f]{2}(?:[:-][0-9A-Fa-f]{2}){5}(?![0-9A-Fa-f:-])")),
    ("ssn", re.compile(r"(?<![\w-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![\w-])")),
    ("number", re.compile(r"(?<![\w.+-])\(?[0-9]{2,5}\)?(?:[ .-]?[0-9]{2,5}){1,4}(?![\w-])(?!\.[0-9])")),
    ("secret", re.compile(r"(?<![A-Za-z0-9_+/=-])(?=[A-Za-z_+/=-]*+[0-9])(?=[0-9_+/=-]*+[A-Za-z])[A-Za-z0-9_+/-]{16,}+=*+")),
)
_NAME = re.compile(r"\b(?:(?:Mr|Mrs|Ms|Dr|Prof|Herr|Frau|Mme|Sr|Sra)\.? |(?:[Nn]ame|[Cc]ontact|[Aa]uthor)[:=] ?)[A-Z][a-z]+(?: [A-Z][a-z]+)?")
_NAME_MARKS = ("Mr", "Ms", "Dr", "Prof", "Herr", "Frau", "Mme", "Sr", "ame:", "ame=", "ontact:", "ontact=", "uthor:", "uthor=")

# Word lists.
CUES = {
    "phone number": "phone tel telephone mobile call fax cell whatsapp telefon movil teléfono téléphone",
    "secret": "password passwd pwd secret token key apikey api auth bearer credential credentials pass passwort clave",
    "bank": "card credit visa mastercard iban account bank konto compte cuenta",
    "person": "name contact author mail email address social security ssn passport",
    "host": "mac ip host server hwaddr ether",
}
_CUES = frozenset(w for line in CUES.values() for w in line.split())
_AGAINST = frozenset("version v ver license licence release chapter section figure fig table page pages pp isbn issn doi rfc level copyright since year commit revision rev build order item no nr id sha md5 checksum lot step".split())
_UNITS = frozenset("kg km cm mm m g mb gb kb tb ms s percent usd eur dollars euros years pages times people".split())
_GIVEN = frozenset("james mary robert patricia john jennifer michael linda david elizabeth william barbara anna maria peter thomas hans pierre marie jean juan carlos carmen sofia lucas emma".split())
_DOMAINS = frozenset("com org net edu gov io de fr es uk eu info".split())
_KEY_STARTS = ("AKIA", "ASIA", "ghp_", "gho_", "github_pat_", "sk-", "sk_live_", "pk_live_", "xoxb-", "xoxp-", "AIza", "glpat-", "eyJ")
_WORDS = re.compile(r"[^\W\d_]+")
_TOKEN = re.compile(r"[^\W_]+|[^\w\s]")
_NEAR = 40


def _luhn(digits: str) -> bool:
    total = 0
    for i, d in enumerate(reversed(digits)):
        n = int(d) * (1 + i % 2)
        total += n - 9 * (n > 9)
    return total % 10 == 0


def base_spans(text: str) -> list[tuple[int, int, str]]:
    """(start, end, kind) of the four base kinds: leftmost, without overlaps within a kind."""
    out = []
    at, done = text.find("@"), 0
    while at >= 0:
        start = at
        while start > done and text[start - 1] in _LOCAL:
            start -= 1
        if start < at and (m := _DOMAIN.match(text, at + 1)):
            out.append((start, m.end(), "email"))
            done = m.end()
            at = text.find("@", done)
        else:
            at = text.find("@", at + 1)
    if _DIGIT.search(text):
        for m in _IP.finditer(text):
            if all(len(p.lstrip("0")) <= 3 and int(p.lstrip("0") or 0) <= 255 for p in m.group().split(".")):
                out.append((m.start(), m.end(), "ip"))
        for m in _CARD.finditer(text):
            if m.end() - m.start() >= 12 and 12 <= len(d := m.group().replace(" ", "").replace("-", "")) <= 19 and _luhn(d):
                out.append((m.start(), m.end(), "card"))
        if "+" in text:
            for m in _PHONE.finditer(text):
                if 9 <= sum(c.isdigit() for c in m.group()) <= 15:
                    out.append((m.start(), m.end(), "phone"))
    return sorted(out, key=lambda s: (s[0], KINDS.index(s[2])))


def more_spans(text: str, base: list[tuple[int, int, str]]) -> list[tuple[int, int, str]]:
    """Candidates of the other kinds that overlap neither a base span nor an earlier candidate."""
    found = []
    if _DIGIT.search(text):
        for kind, pattern in _MORE:
            found += [(m.start(), m.end(), kind) for m in pattern.finditer(text)]
    if any(t in text for t in _NAME_MARKS):
        found += [(m.start(), m.end(), "name") for m in _NAME.finditer(text)]
    if not found:
        return []
    # Base spans as intervals apart from each other.
    starts, ends = [], []
    for a, b, _ in sorted(base):
        if ends and a < ends[-1]:
            ends[-1] = max(ends[-1], b)
        else:
            starts.append(a)
            ends.append(b)
    out, end = [], 0
    order = {kind: n for n, (kind, _) in enumerate(_MORE)}
    for s in sorted(found, key=lambda s: (s[0], -s[1], order.get(s[2], -1))):
        i = bisect_right(starts, s[1] - 1) - 1
        if s[0] >= end and (i < 0 or ends[i] <= s[0]) and (s[2] != "number" or sum(c.isdigit() for c in text[s[0] : s[1]]) >= 7):
            out.append(s)
            end = s[1]
    return out


def _bits(body: str) -> float:
    """Entropy of the characters, in bits for each."""
    n = len(body)
    return -sum(c / n * math.log2(c / n) for c in Counter(body).values())


def _iban(body: str) -> bool:
    code = body.replace(" ", "")
    return int("".join(str(int(c, 36)) for c in code[4:] + code[:4])) % 97 == 1


def _valid(kind: str, body: str, digits: str) -> str:
    """Check digits and value ranges."""
    if kind == "iban":
        return "+" if _iban(body) else "-"
    if kind == "ssn":
        return "-" if digits[:3] in ("000", "666") or digits[0] == "9" or digits[3:5] == "00" or digits[5:] == "0000" else "+"
    if kind == "secret":
        return "+" if _bits(body) > 3.0 else "-" if _bits(body) < 2.3 else "0"
    if kind == "mac":
        return "-" if len(set(body.lower()) - set(":-")) < 3 else "+"
    if kind == "number":
        return "-" if len(set(digits)) < 4 or len(digits) > 15 else "0"
    return "+" if kind in ("card", "ip") else "0"


def _shape_vote(kind: str, body: str, digits: str) -> str:
    if kind == "secret":
        if body.startswith(_KEY_STARTS) or re.fullmatch(r"[0-9a-f]{32,128}|[0-9A-F]{32,128}", body):
            return "+"
        # Words joined by marks are names of things, not keys.
        return "-" if len(digits) * 8 < len(body) else "0"
    if kind == "number":
        return "+" if re.fullmatch(r"\(?[0-9]{3}\)?[ .-][0-9]{3}[ .-][0-9]{4}", body) else "-"
    return "+"


def _listed(kind: str, body: str) -> str:
    if kind == "email":
        return "+" if body.rsplit(".", 1)[-1].lower() in _DOMAINS else "0"
    if kind == "name":
        return "+" if any(w.lower() in _GIVEN for w in _WORDS.findall(body)[1:]) else "-"
    if kind == "secret":
        runs = _WORDS.findall(body.lower())
        return "-" if runs and max(map(len, runs)) >= 8 and sum(c in "aeiou" for c in "".join(runs)) * 3 > sum(map(len, runs)) else "0"
    return "0"


def votes(text: str, span: tuple[int, int, str]) -> str:
    """One character for each labeler: + personal data, - not, 0 no opinion."""
    start, end, kind = span
    body = text[start:end]
    digits = "".join(c for c in body if c.isdigit())
    left, right = text[max(0, start - _NEAR) : start], text[end : end + _NEAR]
    before, after = [w.lower() for w in _WORDS.findall(left)][-3:], [w.lower() for w in _WORDS.findall(right)][:1]
    cue = "+" if any(w in _CUES for w in before) else "-" if kind in ("number", "secret") else "0"
    against = "-" if any(w in _AGAINST for w in before) or any(w in _UNITS for w in after) else "0"
    given = "+" if re.search(r"[:=] ?[\"']?$", left) else "0"
    inside = "-" if left[-1:] in ("/", ".", "_", "#") or right[:1] in ("/", "_") or right[:2] in (".h", ".p", ".j") else "0"
    return _shape_vote(kind, body, digits) + _valid(kind, body, digits) + _listed(kind, body) + cue + against + given + inside


def features(text: str, span: tuple[int, int, str]) -> list[int]:
    """Hashed features of a span's text, shape and surroundings; the votes are not among them."""
    start, end, kind = span
    body = text[start:end]
    shape = re.sub(r"(.)\1+", r"\1+", re.sub(r"[0-9]", "9", re.sub(r"[A-Z]", "A", re.sub(r"[a-z]", "a", body))))[:24]
    left = [w.lower() for w in _TOKEN.findall(text[max(0, start - _NEAR) : start])][-3:]
    right = [w.lower() for w in _TOKEN.findall(text[end : end + _NEAR])][:2]
    n = len(body)
    names = [
        "bias", f"kind {kind}", f"shape {kind} {shape}", f"length {kind} {min(n, 64) // 4}", f"digits {kind} {10 * sum(c.isdigit() for c in body) // n}", f"distinct {kind} {10 * len(set(body)) // n}",
        f"bits {kind} {int(2 * _bits(body))}", f"head {kind} {body[:3]}", f"mark before {text[start - 1 : start]}", f"mark after {text[end : end + 1]}",
        *(f"left {w}" for w in left if not w.isdigit()), f"last {left[-1] if left else ''}", *(f"right {w}" for w in right if not w.isdigit()),
    ]
    return sorted({zlib.crc32(name.encode("utf-8", "surrogatepass")) >> (32 - FEATURE_BITS) for name in names})


_SPAN = pa.struct([("start", pa.int64()), ("end", pa.int64()), ("kind", pa.string()), ("base", pa.bool_()), ("votes", pa.string()), ("features", pa.list_(pa.int32()))])
_SPAN_SQL = "struct<start: long, end: long, kind: string, base: boolean, votes: string, features: array<int>>"


def candidates(docs: DataFrame) -> DataFrame:
    """(doc_id, spans) with spans of (start, end, kind, base, votes, features) in order, for each whole text."""

    def run(batches):
        for batch in batches:
            out = []
            for text in batch.column(1).to_pylist():
                base = base_spans(text) if text else []
                spans = [(*s, True) for s in base] + [(*s, False) for s in (more_spans(text, base) if text else [])]
                spans.sort(key=lambda s: (s[0], KINDS.index(s[2])))
                out.append([{"start": a, "end": b, "kind": k, "base": f, "votes": votes(text, (a, b, k)), "features": features(text, (a, b, k))} for a, b, k, f in spans])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.list_(_SPAN))], ["doc_id", "spans"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return rows.mapInArrow(run, f"doc_id long, spans array<{_SPAN_SQL}>")


def reliabilities(patterns: dict[str, float], steps: int = EM_STEPS) -> tuple[dict[str, float], float, np.ndarray]:
    """Expectation maximisation over vote patterns (votes -> how often).

    Returns each pattern's posterior, the share of personal data, and for each labeler the chances
    of +, - and 0 in either class.  It starts from the majority of the votes; a few votes on either
    side stand for what labelers are made for, and keep the classes from changing places.
    """
    keys = sorted(patterns)
    n = np.array([patterns[k] for k in keys], float)
    one_hot = np.array([[["+-0".index(c) == v for v in range(3)] for c in k] for k in keys], float)
    score = one_hot[:, :, 0].sum(1) - one_hot[:, :, 1].sum(1) - 0.5
    post = 1 / (1 + np.exp(-2 * score))
    # As if each labeler had been seen right more often than wrong.
    seen = np.array([[3.0, 1.0, 2.0], [1.0, 3.0, 2.0]])[:, None, :]
    prior, chance = 0.5, None
    for _ in range(steps):
        prior = float((n @ post + 1) / (n.sum() + 2))
        chance = np.stack([((n * q)[:, None, None] * one_hot).sum(0) for q in (post, 1 - post)]) + seen
        chance /= chance.sum(2, keepdims=True)
        odds = np.log(prior) - np.log(1 - prior) + (one_hot * (np.log(chance[0]) - np.log(chance[1]))).sum((1, 2))
        post = 1 / (1 + np.exp(-np.clip(odds, -50, 50)))
    return dict(zip(keys, post.tolist(), strict=True)), prior, chance


def train(rows: list[tuple[list[int], float]], steps: int = TRAINING_STEPS) -> np.ndarray:
    """Weights of a logistic regression on (features, probability), by accelerated gradient steps."""
    size = 1 << FEATURE_BITS
    merged: dict[tuple[int, ...], list[float]] = {}
    for f, y in rows:
        cell = merged.setdefault(tuple(f), [0.0, 0.0])
        cell[0] += 1
        cell[1] += y
    if not merged:
        return np.zeros(size)
    index = np.concatenate([np.array(f, np.int64) for f in merged])
    owner = np.repeat(np.arange(len(merged)), [len(f) for f in merged])
    n, y = (np.array([c[k] for c in merged.values()]) for k in (0, 1))
    total, most = n.sum(), max(len(f) for f in merged)
    w, ahead, last = np.zeros(size), np.zeros(size), np.zeros(size)
    rate = 1 / (most / 4 + PENALTY / total)
    for k in range(steps):
        p = 1 / (1 + np.exp(-np.clip(np.bincount(owner, ahead[index], len(n)), -30, 30)))
        slope = np.bincount(index, ((n * p - y) / total)[owner], size) + PENALTY / total * ahead
        w = ahead - rate * slope
        ahead, last = w + k / (k + 3) * (w - last), w
    return w


def detected(docs: DataFrame, accept: float = ACCEPT) -> DataFrame:
    """One row per row of docs: doc_id, spans (start, end, kind, base, probability) that stay or are accepted.

    Null and empty texts have none; repeated rows are treated alike; a null doc_id stays null; an
    empty table gives no rows.  To the driver come vote patterns with their counts (a bounded number)
    and the features of TRAINING_SPANS spans at most.
    """
    found = common.checkpointed(candidates(docs))
    flat = found.select("doc_id", F.explode("spans").alias("s"))
    counts = flat.groupBy("s.votes").agg(F.count("*").alias("n")).collect()
    spans = sum(r["n"] for r in counts)
    weights = np.zeros(1 << FEATURE_BITS)
    if spans:
        posterior, _, _ = reliabilities({r["votes"]: r["n"] for r in counts})
        place = F.xxhash64("doc_id", "s.start", "s.kind")
        share = 2 * TRAINING_SPANS / spans
        near = flat.where(F.pmod(place, F.lit(1 << 30)) < int(min(1.0, share) * (1 << 30)))
        sample = near.select("s.votes", "s.features", place.alias("h")).orderBy("h", "votes", "features").limit(TRAINING_SPANS).collect()
        weights = train([(r["features"], posterior[r["votes"]]) for r in sample])
    shared = docs.sparkSession.sparkContext.broadcast(weights)

    def rate(batches):
        for batch in batches:
            spans = batch.column(1)
            flat = spans.flatten()
            lists = flat.field("features")
            n = np.diff(lists.offsets.to_numpy())
            owner = np.repeat(np.arange(len(flat)), n)
            scores = np.bincount(owner, shared.value[lists.flatten().to_numpy(zero_copy_only=False)], len(flat)) if len(flat) else np.zeros(0)
            chance = pa.array(1 / (1 + np.exp(-np.clip(scores, -30, 30))))
            rated = pa.StructArray.from_arrays([flat.field(c) for c in ("start", "end", "kind", "base")] + [chance], ["start", "end", "kind", "base", "probability"])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(np.append(0, np.cumsum(spans.value_lengths().to_numpy())), pa.int32()), rated)], ["doc_id", "spans"])

    rated = found.mapInArrow(rate, "doc_id long, spans array<struct<start: long, end: long, kind: string, base: boolean, probability: double>>")
    return rated.select("doc_id", F.filter("spans", lambda s: s["base"] | (s["probability"] >= accept)).alias("spans"))


def _equals(kind: str):
    return lambda k: k == kind


def digest(found: DataFrame) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone (base spans), base_sha256, spans (all) as text, and n_spans, their number."""
    line = lambda s: F.concat_ws(":", s["kind"], s["start"], s["end"])
    base = F.filter("spans", lambda s: s["base"])
    counts = [F.size(F.filter(base["kind"], _equals(k))).cast("long").alias(f"n_{k}") for k in BASE_KINDS]
    return found.select(
        "doc_id", *counts, F.sha2(F.array_join(F.transform(base, line), ","), 256).alias("base_sha256"), F.array_join(F.transform("spans", line), ",").alias("spans"), F.size("spans").cast("long").alias("n_spans")
    )
