"""Toxicity by class-conditional Kneser-Ney language models over characters.

Two models, one of toxic and one of ordinary training texts, predict each UTF-8 byte (A-Z lowered,
white space as one byte) from the five before it.  Each takes DISCOUNT off its counts of runs of six bytes
and gives what that frees to a lower order: its own counts of the distinct runs of six that end with a run
of four, discounted alike.  What these free goes to one backoff distribution that both models share, of
continuation counts of runs of three and of two bytes over both classes, discounted by BACKOFF, and from
there to all bytes alike.  Counts are taken at the smaller class's size.  So the probabilities of each model
add up to one after every history, and an expression too rare to tell the classes apart gets the shared
probability in both.  A text's evidence is the difference of its log-likelihoods divided by its length, and
the largest such mean of its windows of ``WINDOW`` bytes, so that one expression in a long text shows.  A
logistic curve, fitted on training rows that the models have not seen, turns both into a score.

Runs of six bytes are counted exactly, as rows of a table that grows with the distinct runs of the
training rows; continuation counts and all probabilities come from that table by shuffled aggregates and
joins.  What scoring needs is, of each order, the log ratio of the runs that a class has more than DISCOUNT
times, and for other bytes, whose lower probabilities are looked up next or cancel, the ratio of what both
classes free after their history, if it differs: these tables' size follows the training rows too.  Only the
curve's numbers are fitted on at most ``CURVE_ROWS`` rows.  Training rows: labelled, with crc32(doc_id as
text) mod 5 other than 0; 1 to 3 train the models, 4 the curve.

Null and empty texts have evidence 0.  Without toxic or without ordinary training rows every score is 0.
Rows that repeat a doc_id are scored one by one, rows without one too, as held_out by the empty id; labels
that repeat an id count as toxic if any does, those without an id or label do not count.  Columns other than
doc_id and text are not looked at.  An empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import words as kernel
from .common import documents, only, saved, table

WINDOW = 8
#: Taken off every count, at the smaller class's size; what is left to share goes to the lower order.
DISCOUNT = 2.0
BACKOFF = 0.75  # taken off the shared continuation counts
CURVE_ROWS = 20_000
MERGE_RUNS = 1 << 20  # runs that a task holds before equal ones are added up
U64 = np.uint64
_NONE = U64(2**64 - 1)  # no run has this code
_FOLD = np.arange(256, dtype=np.uint8)
_FOLD[65:91] += 32
_FOLD[[*range(0x09, 0x0E)]] = 0x20


@dataclass
class Ratios:
    """Log ratios by run, in a table of twice the places at least; the run itself is kept, so none stands for another."""

    codes: np.ndarray
    logs: np.ndarray

    @staticmethod
    def of(codes: np.ndarray, logs: np.ndarray) -> Ratios:
        places = 1 << max(4, (2 * len(codes)).bit_length())
        out = Ratios(np.full(places, _NONE), np.zeros(places, dtype=np.float32))
        rest, at = np.arange(len(codes)), out.first(codes)
        while len(rest):
            free = out.codes[at] == _NONE
            out.codes[at[free]] = codes[rest[free]]
            done = out.codes[at] == codes[rest]
            out.logs[at[done]] = logs[rest[done]]
            rest, at = rest[~done], (at[~done] + 1) & (places - 1)
        return out

    def first(self, codes: np.ndarray) -> np.ndarray:
        with np.errstate(over="ignore"):
            h = (codes ^ codes >> U64(23)) * U64(0x9E3779B97F4A7C15)
        return (h >> U64(65 - len(self.codes).bit_length())).astype(np.int64)

    def find(self, codes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(log ratio of each run, 0 if it is not there; the runs that are not there)."""
        at = self.first(codes)
        found = self.codes[at]
        rest = np.flatnonzero((found != codes) & (found != _NONE))
        while len(rest):
            at[rest] = (at[rest] + 1) & (len(self.codes) - 1)
            found = self.codes[at[rest]]
            rest = rest[(found != codes[rest]) & (found != _NONE)]
        return self.logs[at], np.flatnonzero(self.codes[at] == _NONE)


@dataclass
class Runs:
    """Codes of the six bytes up to and with each byte of some rows, each row led by five blanks."""

    codes: np.ndarray
    at: np.ndarray  # len rows + 1: bounds of the rows

    @staticmethod
    def of(w: kernel.Words) -> Runs:
        lengths = np.diff(w.row_bytes)
        begin = w.row_bytes[:-1] + 5 * np.arange(1, w.rows + 1)
        padded = np.full(len(w.data) + 5 * w.rows, 0x20, dtype=np.uint8)
        if not len(w.data):
            return Runs(np.zeros(0, dtype=U64), w.row_bytes)
        real = np.repeat(begin - w.row_bytes[:-1], lengths) + np.arange(len(w.data))
        padded[real] = _FOLD[w.data]
        wide = padded.astype(U64)
        codes = np.zeros(len(padded), dtype=U64)
        for j in range(6):
            codes[j:] |= wide[: len(padded) - j] << U64(8 * j)
        return Runs(codes[real], w.row_bytes)


@dataclass
class Model:
    """Of runs of six and of four bytes: their log ratios, and those of any other byte after a history of five or three."""

    six: Ratios
    after_five: Ratios
    four: Ratios
    after_three: Ratios

    def ratios(self, runs: Runs) -> np.ndarray:
        """Log of toxic over ordinary probability of each byte given those before it."""
        out, rest = self.six.find(runs.codes)
        ends = runs.codes[rest] & U64(0xFFFFFFFF)
        lower, other = self.four.find(ends)
        lower[other] = self.after_three.find(ends[other] >> U64(8))[0]
        out[rest] = self.after_five.find(runs.codes[rest] >> U64(8))[0] + lower
        return out

    def evidence(self, w: kernel.Words) -> np.ndarray:
        """(mean over the text, largest mean of a window) of each row; 0 for an empty row."""
        out = np.zeros((w.rows, 2))
        runs = Runs.of(w)
        n = len(runs.codes)
        if not n:
            return out
        sums = np.zeros(n + 1)
        np.cumsum(self.ratios(runs), out=sums[1:])
        length = np.diff(runs.at)
        has = length > 0
        out[has, 0] = (sums[runs.at[1:]] - sums[runs.at[:-1]])[has] / length[has]
        end = np.minimum(np.arange(n) + WINDOW, np.repeat(runs.at[1:], length))
        size = end - np.arange(n)
        mean = (sums[end] - sums[:-1]) / size
        mean[(size < WINDOW) & (np.arange(n) != np.repeat(runs.at[:-1], length))] = -np.inf
        out[has, 1] = np.maximum.reduceat(mean, runs.at[:-1][has])
        return out


def _merged(parts: list[np.ndarray]) -> list[np.ndarray]:
    """Rows of (run, ordinary count, toxic count) with equal runs added up, by run."""
    code, n0, n1 = (np.concatenate(x) for x in zip(*parts, strict=True))
    order = np.argsort(code)
    code = code[order]
    first = np.flatnonzero(np.append(True, code[1:] != code[:-1])) if len(code) else np.zeros(0, dtype=np.int64)
    return [code[first], *(np.add.reduceat(n[order], first) if len(code) else n for n in (n0, n1))]


def gather(train: DataFrame) -> DataFrame:
    """code, n0, n1: how often each run of six bytes is in ordinary and in toxic texts of train (text, toxic)."""

    def rows(found: list[np.ndarray]):
        for at in range(0, len(found[0]), 1 << 16):
            code, n0, n1 = (x[at : at + (1 << 16)] for x in found)
            yield pa.RecordBatch.from_arrays([pa.array(code.view(np.int64)), pa.array(n0), pa.array(n1)], ["code", "n0", "n1"])

    def counted(batches):
        parts: list[list[np.ndarray]] = []
        for batch in batches:
            toxic = np.asarray(batch.column(1).to_numpy(zero_copy_only=False), dtype=np.int64)
            for a, z, w in kernel.steps(batch):
                label = np.repeat(toxic[a:z], np.diff(w.row_bytes)).astype(U64)
                both, n = np.unique(Runs.of(w).codes << U64(1) | label, return_counts=True)
                one = (both & U64(1)).astype(np.int64)
                parts.append([both >> U64(1), n * (1 - one), n * one])
                if sum(len(p[0]) for p in parts) > MERGE_RUNS:
                    parts = [_merged(parts)]
                    if len(parts[0][0]) > MERGE_RUNS // 2:
                        yield from rows(parts.pop())
        if parts:
            yield from rows(_merged(parts))

    found = train.select("text", "toxic").mapInArrow(counted, "code bigint, n0 bigint, n1 bigint")
    return found.groupBy("code").agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1"))


def _ends(runs: DataFrame, mask: int) -> DataFrame:
    """(code, n, history, all, kinds, end) of the runs that the given ones end with, n of them; all and kinds: of their history; end: the next shorter run."""
    ends = runs.groupBy(F.col("code").bitwiseAND(mask).alias("code")).agg(F.count("*").alias("n")).withColumn("history", F.shiftright("code", 8))
    whole = ends.groupBy("history").agg(F.sum("n").alias("all"), F.count("*").alias("kinds"))
    return ends.join(whole, "history").withColumn("end", F.col("code").bitwiseAND(mask >> 8))


def backoff(four: DataFrame) -> DataFrame:
    """(code, shared): the shared probability of a byte after two, for every run of three bytes that one of four ends with."""
    share = lambda lower: (F.greatest(F.col("n") - BACKOFF, F.lit(0.0)) + BACKOFF * F.col("kinds") * lower) / F.col("all")
    three = saved(_ends(four, 0xFFFFFF))
    two = _ends(three, 0xFFFF).select(F.col("code").alias("end"), share(F.lit(1 / 256)).alias("lower"))  # 65,536 rows at most
    return three.join(F.broadcast(two), "end").select("code", share(F.col("lower")).alias("shared"))


@dataclass
class Order:
    """Counts of an order (code, n0, n1): runs with their history, and what each class frees after a history."""

    runs: DataFrame
    histories: DataFrame
    scale: list[float]

    @staticmethod
    def of(counts: DataFrame) -> Order | None:
        size = counts.agg(F.sum("n0"), F.sum("n1")).first()
        if not size[0] or not size[1]:
            return None
        scale = [min(size) / x for x in size]
        more = [F.col(f"n{c}") * F.lit(scale[c]) > DISCOUNT for c in (0, 1)]
        runs = counts.withColumns({"history": F.shiftright("code", 8), "more": more[0] | more[1]})
        # sums of whole numbers, so that they do not depend on their order
        sums = [a for c in (0, 1) for a in (F.sum(f"n{c}").alias(f"s{c}"), F.sum(F.when(more[c], F.col(f"n{c}")).otherwise(0)).alias(f"k{c}"), F.count_if(more[c]).alias(f"r{c}"))]
        freed = [F.when(F.col(f"s{c}") == 0, 1.0).otherwise(1 - (F.col(f"k{c}") * scale[c] - DISCOUNT * F.col(f"r{c}")) / (F.col(f"s{c}") * scale[c])).alias(f"left{c}") for c in (0, 1)]
        return Order(runs, saved(runs.groupBy("history").agg(*sums).select("history", "s0", "s1", *freed)), scale)

    def probabilities(self, runs: DataFrame, lower: tuple[str, str]) -> DataFrame:
        """runs, some of this order's with columns of lower probabilities, with p0 and p1."""
        p = {f"p{c}": F.greatest(F.col(f"n{c}") * self.scale[c] - DISCOUNT, F.lit(0.0)) / F.greatest(F.col(f"s{c}") * self.scale[c], F.lit(1e-300)) + F.col(f"left{c}") * F.col(lower[c]) for c in (0, 1)}
        return runs.join(self.histories, "history").withColumns(p)

    def others(self) -> DataFrame:
        """(code, log) by history: the log ratio of what the classes free, where it differs."""
        return self.histories.where("left0 != left1").select(F.col("history").alias("code"), F.log(F.col("left1") / F.col("left0")).cast("float").alias("log"))


def probabilities(train: DataFrame) -> tuple[Order, DataFrame, Order, DataFrame] | None:
    """(order of six, its runs seen more than DISCOUNT times with p0 and p1, order of four, all its runs with p0 and p1); None if a class has no text."""
    six = Order.of(saved(gather(train)))
    if six is None:
        return None
    ends = six.runs.groupBy(F.col("code").bitwiseAND(0xFFFFFFFF).alias("code"))
    four = Order.of(saved(ends.agg(F.count_if(F.col("n0") > 0).alias("n0"), F.count_if(F.col("n1") > 0).alias("n1"))))
    shared = backoff(four.runs).withColumnRenamed("code", "last")
    of_four = saved(four.probabilities(four.runs.withColumn("last", F.col("code").bitwiseAND(0xFFFFFF)).join(shared, "last"), ("shared", "shared")).select("code", "more", "p0", "p1"))
    lower = of_four.select(F.col("code").alias("last"), F.col("p0").alias("q0"), F.col("p1").alias("q1"))
    of_six = six.probabilities(six.runs.where("more").withColumn("last", F.col("code").bitwiseAND(0xFFFFFFFF)).join(lower, "last"), ("q0", "q1"))
    return six, of_six, four, of_four


def fit(train: DataFrame) -> Model | None:
    """The model of train (text, toxic); None if a class has no text.  What is collected grows with the runs seen more than DISCOUNT times."""
    found = probabilities(train)
    if found is None:
        return None
    six, of_six, four, of_four = found
    log = F.log(F.col("p1") / F.col("p0")).cast("float").alias("log")
    # a history that frees all of both classes has no row, so these are no more than the runs
    got = [t.toArrow() for t in (of_six.select("code", log), six.others(), of_four.where("more").select("code", log), four.others())]
    return Model(*(Ratios.of(g["code"].to_numpy().view(U64), g["log"].to_numpy()) for g in got))


def with_evidence(docs: DataFrame, model: Model | None, *more: str) -> DataFrame:
    """doc_id, the named columns, evidence and peak (the largest window mean) for every row of docs (doc_id, text, the named columns)."""
    kept = docs.select("doc_id", *more, "text")
    if model is None:
        return kept.drop("text").withColumns({"evidence": F.lit(0.0), "peak": F.lit(0.0)})
    shared = docs.sparkSession.sparkContext.broadcast(model)  # grows with the runs seen more than DISCOUNT times
    names = ["doc_id", *more]

    def scored(batches):
        for batch in batches:
            found = np.concatenate([np.zeros((0, 2)), *(shared.value.evidence(w) for _, _, w in kernel.steps(batch))])
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(len(names))), *(pa.array(np.ascontiguousarray(found[:, i])) for i in (0, 1))], [*names, "evidence", "peak"])

    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in kept.schema if f.name != "text")
    return kept.mapInArrow(scored, f"{schema}, evidence double, peak double")


def fit_curve(evidence: np.ndarray, label: np.ndarray) -> tuple[list[float], float]:
    """Slopes and offset of a logistic curve over the columns of evidence by Newton's method, with a light ridge."""
    if not len(label) or label.min() == label.max():
        return [0.0, 4.0], -2.0
    mid, scale = evidence.mean(axis=0), evidence.std(axis=0)
    scale[scale == 0] = 1.0
    x = np.concatenate([(evidence - mid) / scale, np.ones((len(evidence), 1))], axis=1)
    w = np.zeros(x.shape[1])
    for _ in range(50):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (p * (1 - p))[:, None]).T @ x + 1e-2 * np.eye(len(w)), x.T @ (p - label) + 1e-2 * w)
        w -= np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-8:
            break
    return (w[:-1] / scale).tolist(), float(w[-1] - (w[:-1] * mid / scale).sum())


def fold(column: str = "doc_id") -> F.Column:
    return F.crc32(F.coalesce(F.col(column).cast("string"), F.lit("")).cast("binary")) % 5


def score_toxicity(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted for every row of docs."""
    texts = documents(docs)
    labelled = labels.where("doc_id is not null and toxic is not null").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    labelled = labelled.withColumn("fold", fold()).where("fold != 0")
    model = fit(only(texts, labelled.where("fold <= 3"), how="inner"))
    curve = labelled.where("fold = 4").orderBy(F.xxhash64("doc_id"), "doc_id").limit(CURVE_ROWS)
    slopes, offset = [0.0, 0.0], -1e3
    if model is not None:
        seen = with_evidence(texts.join(F.broadcast(curve), "doc_id"), model, "toxic").select("evidence", "peak", "toxic").orderBy("evidence", "peak", "toxic").toArrow()  # CURVE_ROWS rows
        slopes, offset = fit_curve(np.stack([seen["evidence"].to_numpy(), seen["peak"].to_numpy()], axis=1), seen["toxic"].to_numpy().astype(float))
    found = with_evidence(texts, model)
    score = 1 / (1 + F.exp(-(F.col("evidence") * slopes[0] + F.col("peak") * slopes[1] + offset)))
    out = found.select("doc_id", (fold() == 0).alias("held_out"), score.alias("score"), "evidence", "peak")
    return out.select("doc_id", "held_out", "score", F.when(F.col("score") >= 0.5, 1).otherwise(0).alias("predicted"), "evidence", "peak")


def op3_toxicity(spark, sf_dir: str) -> DataFrame:
    return score_toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


QUERIES = {"op3_toxicity": op3_toxicity}
ORACLES: dict[str, str] = {}
