"""Personal data: base patterns, and a semi-Markov conditional random field that adds what they miss.

Base patterns give e-mail addresses, IP addresses, payment cards and phone numbers by fixed rules; a
match that fails its check is dropped without a retry.  The random field works on islands: stretches
of text with an at sign or enough digits.  An island is a sequence of atoms (runs of letters, runs of
digits, single other characters); a candidate segment is up to ``MAX_ATOMS`` atoms and ``MAX_CHARS``
characters, and features of the whole segment (its shape, digits, check sum, separators, what stands beside
and before it) score it for each type.  A dynamic program over ends and segment lengths finds the best
boundaries and types of an island together.  Weights are fitted by the likelihood of base matches, through
the same dynamic program with sums, on all islands of ``TRAIN_DOCS`` documents, chosen by hash; without any
they keep their priors.  A span of the field is added unless it overlaps a base span or one added before it.

Null and empty texts have no spans.  Rows without a doc_id count like others; repeated rows give repeated
results.  Columns other than doc_id and text are not looked at, but redact() keeps them.  An empty table
gives an empty result.  Whole texts are read; work is linear in a text's length, as scans start anew only
at new runs and islands of more than ``ISLAND_ATOMS`` atoms are decoded in windows that overlap by
``MAX_ATOMS``.
"""

from __future__ import annotations

import hashlib
import math
import re
from bisect import bisect_left
from collections.abc import Iterator
from functools import lru_cache
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import documents, table

KINDS = ("email", "ip", "card", "phone")
MAX_ATOMS = 24
MAX_CHARS = 320  # of a candidate segment
ISLAND_ATOMS = 240
TRAIN_DOCS = 1000
Span = tuple[int, int, int]  # kind, start, end
Example = tuple[str, str, str, tuple[Span, ...]]  # island, text before, character after, base spans in it

_DOMAIN = re.compile(r"[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)+")
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")  # no match begins inside a run of digits: the one before took it whole
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_TRIGGER = re.compile(r"[0-9@]")
_DIGITS = re.compile(r"[+(]?[0-9][0-9\x20().\-/]*+")
_AFTER_AT = re.compile(r"\x20?[^\s@]++")
_ATOM = re.compile(r"[0-9]+|[^\W\d_]+|.", re.S)
_CONTEXT = {
    "email": re.compile(r"(e-?mail|contact|write)\W*$", re.I),
    "ip": re.compile(r"(\bip|addr(ess)?|host|server)\W*$", re.I),
    "card": re.compile(r"(card|visa|master|amex|credit|debit)\W*(no|number|nr)?\W*$", re.I),
    "phone": re.compile(r"(phone|tel|call|mobile|cell|fax)\W*(no|number|nr)?\W*$", re.I),
}


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = d * 2 - 9 * (d > 4)
        total += d
    return total % 10 == 0


def _digits(s: str) -> str:
    return "".join(c for c in s if "0" <= c <= "9")


def base_spans(text: str) -> list[Span]:
    """Matches of the base patterns, by kind and then start; each scan is linear in the text."""
    if not _TRIGGER.search(text):
        return []
    out: list[Span] = []
    done, at = 0, text.find("@")
    while at >= 0:
        begin = at
        while begin > done and text[begin - 1] in _LOCAL:
            begin -= 1
        match = _DOMAIN.match(text, at + 1) if begin < at else None
        done = match.end() if match else at + 1
        if match:
            out.append((0, begin, done))
        at = text.find("@", done)
    out += [(1, m.start(), m.end()) for m in _IP.finditer(text) if all(len(p.lstrip("0")) <= 3 and int(p[-4:]) <= 255 for p in m[0].split("."))]
    for m in _CARD.finditer(text):
        digits = _digits(m[0])
        if 13 <= len(digits) <= 19 and luhn(digits):
            out.append((2, m.start(), m.end()))
    out += [(3, m.start(), m.end()) for m in _PHONE.finditer(text) if 9 <= len(_digits(m[0])) <= 15]
    return out


#: Whole-span features; every kind has a weight for each.
FEATURES = (
    "bias", "atoms", "clean_start", "clean_end", "told_email", "told_ip", "told_card", "told_phone",
    "one_at", "dotted_domain", "ip_groups", "ip_range", "card_digits", "check_sum", "card_issuer", "even_groups",
    "plus", "phone_digits", "parentheses", "inner_space", "trimmed",
)
_N = len(FEATURES)
_PRIOR = {
    "email": {"bias": -6, "one_at": 3, "dotted_domain": 5, "clean_start": 1, "clean_end": 1, "inner_space": -3, "told_email": 1},
    "ip": {"bias": -6, "ip_groups": 3, "ip_range": 4, "clean_start": 1, "clean_end": 1, "inner_space": -4, "told_ip": 1},
    "card": {"bias": -9, "card_digits": 3, "check_sum": 4, "card_issuer": 1, "even_groups": 1, "clean_start": 1, "clean_end": 1, "told_card": 1},
    "phone": {"bias": -8, "plus": 4, "phone_digits": 3, "parentheses": 1, "clean_start": 1, "clean_end": 1, "trimmed": 1, "told_phone": 2},
}


def prior_weights() -> np.ndarray:
    return np.array([[float(_PRIOR[k].get(f, 0)) for f in FEATURES] for k in KINDS])


def islands(text: str) -> list[tuple[int, int]]:
    """Bounds of the stretches that may hold personal data; each character is looked at a bounded number of times."""
    found: list[tuple[int, int]] = []
    done, at = 0, text.find("@")
    while at >= 0:
        begin = at - 1 if at > done and text[at - 1] == " " else at
        while begin > done and text[begin - 1] != "@" and not text[begin - 1].isspace():
            begin -= 1
        after = _AFTER_AT.match(text, at + 1)
        done = after.end() if after else at + 1
        if after:
            found.append((begin, done))
        at = text.find("@", done)
    for m in _DIGITS.finditer(text):
        if len(_digits(m[0])) >= 7 or m[0].count(".") >= 3:
            found.append((m.start(), m.end()))
    out: list[tuple[int, int]] = []
    for a, z in sorted(found):  # those that overlap are one
        if out and a < out[-1][1]:
            out[-1] = (out[-1][0], max(z, out[-1][1]))
        else:
            out.append((a, z))
    return out


def units(text: str) -> Iterator[tuple[int, int, str, str]]:
    """(start, end, text before, character after) of the islands, long ones in overlapping windows."""
    for a, z in islands(text):
        atoms = [m.start() for m in _ATOM.finditer(text, a, z)] + [z]
        for first in range(0, max(1, len(atoms) - 1 - MAX_ATOMS), ISLAND_ATOMS - MAX_ATOMS):
            lo, hi = atoms[first], atoms[min(first + ISLAND_ATOMS, len(atoms) - 1)]
            yield lo, hi, text[max(0, lo - 24) : lo], text[hi : hi + 1]


@lru_cache(maxsize=1 << 14)
def segments(island: str, before: str, after: str) -> tuple[tuple[int, ...], tuple[tuple[int, int, tuple[float, ...]], ...], int]:
    """(bounds of the atoms, candidate segments (first atom, atom after the last, features), atoms)."""
    bounds = [m.start() for m in _ATOM.finditer(island)] + [len(island)]
    n = len(bounds) - 1
    left = before[-1:] or " "
    told = tuple(float(bool(before and _CONTEXT[k].search(before))) for k in KINDS)
    untold = (0.0,) * len(KINDS)
    out = []
    for i in range(n):
        if island[bounds[i]] in " )-/":
            continue
        p = island[bounds[i] - 1] if i else left
        for j in range(i + 1, min(n, i + MAX_ATOMS) + 1):
            if bounds[j] - bounds[i] > MAX_CHARS:
                break
            s = island[bounds[i] : bounds[j]]
            if s[-1] in " (-/.@+":
                continue
            digits = _digits(s)
            at = s.count("@")
            if not at and len(digits) < 4:
                continue
            q = island[bounds[j]] if j < n else (after or " ")[0]
            groups = s.split(".")
            four = len(groups) == 4 and all(g.isdigit() and g.isascii() for g in groups)
            domain = s.rpartition("@")[2].strip() if at == 1 else ""
            pure = not at and not re.search(r"[^\W\d_]", s)
            parts = re.split(r"[\x20-]", s) if pure else []
            card = pure and 13 <= len(digits) <= 19 and not re.search(r"[^0-9\x20-]", s)
            phone = pure and 9 <= len(digits) <= 15
            out.append((i, j, (
                1.0, (j - i) / MAX_ATOMS, float(not (p.isalnum() or p in "@.+-")), float(not (q.isalnum() or q in "@-")), *(told if i == 0 else untold),
                float(at == 1), float(at == 1 and bool(re.fullmatch(r"[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)*\.[A-Za-z]{2,24}", domain))),
                float(four), float(four and all(len(g) <= 3 and int(g) <= 255 for g in groups)),
                float(card), float(card and luhn(digits)), float(card and digits[0] in "3456"), float(card and len(set(map(len, parts))) == 1),
                float(s[0] == "+" and pure), float(phone), float("(" in s and ")" in s and pure), float(" " in s), float(pure and len(parts) >= 2),
            )))
    return tuple(bounds), tuple(out), n


def _scored(island: str, before: str, after: str, weights: np.ndarray) -> tuple[tuple[int, ...], list[tuple[int, int]], np.ndarray, np.ndarray, int]:
    bounds, cut, n = segments(island, before, after)
    if not cut:
        return bounds, [], np.zeros((0, _N)), np.zeros((0, 4)), n
    x = np.array([c[2] for c in cut])
    return bounds, [(c[0], c[1]) for c in cut], x, x @ weights.T, n


def best_spans(island: str, before: str, after: str, weights: np.ndarray) -> list[Span]:
    """The highest-scoring segmentation; an atom outside any span scores 0."""
    bounds, cut, _, scores, n = _scored(island, before, after, weights)
    if not len(scores) or scores.max() <= 0:
        return []
    kind = scores.argmax(axis=1)
    ends: list[list[int]] = [[] for _ in range(n + 1)]
    for k, (_, j) in enumerate(cut):
        if scores[k, kind[k]] > 0:
            ends[j].append(k)
    best, back = [0.0] * (n + 1), [-1] * (n + 1)
    for j in range(1, n + 1):
        best[j] = best[j - 1]
        for k in ends[j]:
            s = best[cut[k][0]] + scores[k, kind[k]]
            if s > best[j] + 1e-12:
                best[j], back[j] = s, k
    out, j = [], n
    while j > 0:
        if back[j] < 0:
            j -= 1
        else:
            i, z = cut[back[j]]
            out.append((int(kind[back[j]]), bounds[i], bounds[z]))
            j = i
    return out[::-1]


def field_spans(text: str, weights: np.ndarray) -> list[Span]:
    """The field's spans, by start; windows of one island may give one span twice, or two that overlap."""
    found = {(k, lo + i, lo + j) for lo, hi, before, after in units(text) for k, i, j in best_spans(text[lo:hi], before, after, weights)}
    return sorted(found, key=lambda s: (s[1], s[2], s[0]))


def all_spans(text: str, weights: np.ndarray) -> tuple[list[Span], list[Span]]:
    """(base spans, all spans), each by kind and then start."""
    base = base_spans(text)
    if not _TRIGGER.search(text):
        return base, base
    taken = sorted((a, z) for _, a, z in base)
    begins, ends = [a for a, _ in taken], list(accumulate((z for _, z in taken), max))
    more: list[Span] = []
    done = 0
    for k, a, z in field_spans(text, weights):
        n = bisect_left(begins, z)  # base spans that begin before the span's end
        if a >= done and (not n or ends[n - 1] <= a):
            more.append((k, a, z))
            done = z
    return base, sorted(base + more)


def examples(text: str) -> Iterator[Example]:
    """The islands of a text with the base spans that lie in them."""
    base = base_spans(text)
    for lo, hi, before, after in units(text):
        yield text[lo:hi], before, after, tuple((k, i - lo, j - lo) for k, i, j in base if lo <= i and j <= hi)


def _log_sum(values: list[float]) -> float:
    most = max(values)
    return most + math.log(sum(math.exp(v - most) for v in values))


def fit_weights(seen: list[Example], rounds: int = 12, rate: float = 0.5) -> np.ndarray:
    """Weights that raise the likelihood of the base spans of the given islands, from the priors."""
    weights = prior_weights()
    prior = weights.copy()
    for _ in range(rounds if seen else 0):
        gradient = np.zeros_like(weights)
        for island, before, after, gold in seen:
            bounds, cut, x, scores, n = _scored(island, before, after, weights)
            if not len(scores):
                continue
            # sums over segmentations of what stands before and behind each atom
            starts: list[list[int]] = [[] for _ in range(n + 1)]
            ends: list[list[int]] = [[] for _ in range(n + 1)]
            mass = np.logaddexp.reduce(scores, axis=1).tolist()
            for k, (i, j) in enumerate(cut):
                starts[i].append(k)
                ends[j].append(k)
            ahead, behind = [0.0] * (n + 1), [0.0] * (n + 1)
            for j in range(1, n + 1):
                ahead[j] = _log_sum([ahead[j - 1], *(ahead[cut[k][0]] + mass[k] for k in ends[j])]) if ends[j] else ahead[j - 1]
            for i in range(n - 1, -1, -1):
                behind[i] = _log_sum([behind[i + 1], *(behind[cut[k][1]] + mass[k] for k in starts[i])]) if starts[i] else behind[i + 1]
            edge = np.array([ahead[i] + behind[j] for i, j in cut]) - ahead[n]
            expected = np.exp(np.minimum(scores + edge[:, None], 0))
            wanted = np.zeros_like(expected)
            place = {(bounds[i], bounds[j]): k for k, (i, j) in enumerate(cut)}
            for kind, i, j in gold:
                if (i, j) in place:
                    wanted[place[i, j], kind] = 1.0
            gradient += (wanted - expected).T @ x
        weights += rate * (gradient / max(1, len(seen)) - 0.01 * (weights - prior))
    return np.round(weights, 6)


def train(docs: DataFrame) -> np.ndarray:
    """Weights from all islands of the TRAIN_DOCS texts with digits or at signs that come first by hashes of id and text.

    The driver gets the distinct islands of these documents, not their texts.
    """
    texts = documents(docs).where(F.expr("text rlike '[0-9@]'")).select(F.xxhash64("doc_id").alias("h"), F.xxhash64("text").alias("t"), "text")
    chosen = texts.select("h", "t").distinct().orderBy("h", "t").limit(TRAIN_DOCS)

    def found(batches):
        for batch in batches:
            rows = [e for text in batch.column(0).to_pylist() for e in examples(text)]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.string()) for i in range(3)] + [pa.array([as_text(list(r[3])) for r in rows], pa.string())], ["island", "before", "after", "gold"])

    rows = texts.join(F.broadcast(chosen), ["h", "t"]).select("text").mapInArrow(found, "island string, before string, after string, gold string").distinct().collect()

    def spans(text: str) -> tuple[Span, ...]:
        return tuple((KINDS.index(k), int(a), int(z)) for k, a, z in (s.split(":") for s in text.split(",") if s))

    return fit_weights([(r.island, r.before, r.after, spans(r.gold)) for r in sorted(rows)])


def as_text(spans: list[Span]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{z}" for k, a, z in spans)


def find_personal_data(docs: DataFrame, weights: np.ndarray | None = None) -> DataFrame:
    """doc_id, n_email, n_ip, n_card, n_phone (of base spans), base_sha256, spans (all of them), n_added."""
    weights = train(docs) if weights is None else weights
    kept = documents(docs)
    counts = [f"n_{k}" for k in KINDS]

    def found(batches):
        for batch in batches:
            rows = []
            for text in batch.column(1).to_pylist():
                base, every = all_spans(text, weights)
                rows.append(([sum(s[0] == k for s in base) for k in range(4)], hashlib.sha256(as_text(base).encode()).hexdigest(), as_text(every), len(every) - len(base)))
            columns = [pa.array([r[0][k] for r in rows], pa.int64()) for k in range(4)]
            yield pa.RecordBatch.from_arrays([batch.column(0), *columns, *(pa.array([r[i] for r in rows], t) for i, t in ((1, pa.string()), (2, pa.string()), (3, pa.int64())))], ["doc_id", *counts, "base_sha256", "spans", "n_added"])

    key = kept.schema["doc_id"].dataType.simpleString()
    return kept.mapInArrow(found, f"doc_id {key}, {', '.join(f'{c} bigint' for c in counts)}, base_sha256 string, spans string, n_added bigint")


def redact_text(text: str, weights: np.ndarray) -> str:
    """The text with every span replaced by its kind in angle brackets; of overlapping spans the first stays."""
    out, done = [], 0
    for k, a, z in sorted(all_spans(text, weights)[1], key=lambda s: (s[1], -s[2], s[0])):
        if a >= done:
            out += [text[done:a], f"<{KINDS[k]}>"]
        done = max(done, z)
    return "".join([*out, text[done:]]) if out else text


def redact(docs: DataFrame, weights: np.ndarray | None = None) -> DataFrame:
    """docs with personal data replaced in text and n_chars to match, all other columns as they were; null texts stay null."""
    weights = train(docs) if weights is None else weights

    @F.pandas_udf("string")
    def clean(texts):
        return texts.map(lambda t: None if t is None else redact_text(t, weights))

    out = docs.withColumn("text", clean("text"))
    return out.withColumn("n_chars", F.length("text").cast("bigint")) if "n_chars" in docs.columns else out


def op6_personal_data(spark, sf_dir: str) -> DataFrame:
    return find_personal_data(table(spark, sf_dir, "documents"))


QUERIES = {"op6_personal_data": op6_personal_data}
ORACLES: dict[str, str] = {}
