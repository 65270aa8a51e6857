"""Quality classifier by importance resampling with hashed n-gram models.

Two bags of hashed words and word pairs are counted: over the target documents (labels with quality
1) and over every document given.  A document's log importance is the sum, over its n-grams, of the
log ratio of the two smoothed multinomials.  Adding a Gumbel variate drawn from a hash of the row's id and
text, and taking the k largest samples k documents without replacement in proportion to importance.  k is
the rows times the labelled rows' share of quality 1, so it follows the data, not a fixed number.

The k-th largest key is found exactly by four passes over 65,536-bin histograms of the keys' bits, so
nothing is sorted globally and the driver sees bin counts only.  The models are ``BUCKETS`` numbers.

Null and empty texts have importance 0 (log).  Without target documents all documents have, and the
sample is uniform.  Equal keys (rows that repeat id and text, and empty ones without an id) are taken or left
together; other rows without an id have keys of their own.  Labels that repeat an id count as target if any
does.  Columns other than doc_id and text are not looked at.  An empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import words as kernel
from .common import documents, only, row_key, saved, table

BUCKETS = 1 << 16
SEED = 977
U64 = np.uint64


def _features(w: kernel.Words) -> tuple[np.ndarray, np.ndarray]:
    """(row, bucket) of every n-gram: words, word pairs, and the edges of words, by which unseen words tell."""
    h, row = w.hashes(), w.row_of_word()
    pairs, at = w.grams(2, h)
    n = w.ends - w.starts
    head = np.zeros(len(h), dtype=U64)
    tail = np.zeros(len(h), dtype=U64)
    for j in range(4):
        inside = n > j
        with np.errstate(over="ignore"):
            head[inside] = head[inside] * U64(257) + w.data[w.starts[inside] + j] + U64(1)
            tail[inside] = tail[inside] * U64(257) + w.data[w.ends[inside] - 1 - j] + U64(1)
    values = [h, pairs, kernel.mix(head, 101), kernel.mix(tail, 202)]
    return np.concatenate([row, row[at], row, row]), (np.concatenate(values) & U64(BUCKETS - 1)).astype(np.int64)


def bag(docs: DataFrame) -> np.ndarray:
    """Counts of the BUCKETS hashed n-grams over all rows of docs (text)."""

    def counted(batches):
        n = np.zeros(BUCKETS, dtype=np.int64)
        for batch in batches:
            for _, _, w in kernel.steps(batch):
                n += np.bincount(_features(w)[1], minlength=BUCKETS)
        used = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(used), pa.array(n[used])], ["bucket", "n"])

    rows = docs.select("text").mapInArrow(counted, "bucket bigint, n bigint").groupBy("bucket").agg(F.sum("n").alias("n")).toArrow()
    out = np.zeros(BUCKETS)
    out[rows["bucket"].to_numpy()] = rows["n"].to_numpy()
    return out


def log_importance(docs: DataFrame, target: DataFrame) -> np.ndarray:
    good = bag(only(documents(docs), target))
    if not good.any():
        return np.zeros(BUCKETS)
    raw = bag(documents(docs))
    return np.log((good + 1) / (good.sum() + BUCKETS)) - np.log((raw + 1) / (raw.sum() + BUCKETS))


def with_importance(docs: DataFrame, ratios: np.ndarray, seed: int = SEED) -> DataFrame:
    """doc_id, n_grams, log_importance, key for every row of docs."""

    def scored(batches):
        for batch in batches:
            grams, sums = [], []
            for _, _, w in kernel.steps(batch):
                row, bucket = _features(w)
                grams.append(np.bincount(row, minlength=w.rows))
                sums.append(np.bincount(row, weights=ratios[bucket], minlength=w.rows))
            join = lambda x, t: pa.array(np.concatenate(x).astype(t) if x else np.zeros(0, dtype=t))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), join(grams, np.int64), join(sums, np.float64)], ["doc_id", "rid", "n_grams", "log_importance"])

    kept = documents(docs).select("doc_id", row_key().alias("rid"), "text")
    out = kept.mapInArrow(scored, f"doc_id {kept.schema['doc_id'].dataType.simpleString()}, rid bigint, n_grams bigint, log_importance double")
    uniform = (F.shiftrightunsigned(F.xxhash64("rid", F.lit(seed)), 11).cast("double") + 0.5) / F.lit(2.0**53)
    return out.withColumn("key", F.col("log_importance") - F.log(-F.log(uniform))).drop("rid")


def kth_largest(keys: DataFrame, k: int) -> int | None:
    """The k-th largest of the bigint column key, by 16 bits a pass; None if there are fewer."""
    high, left = 0, k
    for shift in (48, 32, 16, 0):
        known = keys if shift == 48 else keys.where(F.shiftright("key", shift + 16) == high)
        bins = known.groupBy(F.shiftright("key", shift).alias("bin")).count().collect()  # 65,536 rows at most
        for r in sorted(bins, key=lambda r: -r["bin"]):
            if left <= r["count"]:
                high = r["bin"]
                break
            left -= r["count"]
        else:
            return None
    return high


def resample(docs: DataFrame, labels: DataFrame, fraction: float | None = None) -> DataFrame:
    """One row per row of docs: n_grams, log_importance, key and whether it is in the sample."""
    target = labels.where("quality = 1 and doc_id is not null").select("doc_id").distinct()
    scored = with_importance(docs, log_importance(docs, target))
    # the key as an integer in steps of 2**-20, so that the bins of kth_largest order it
    scored = saved(scored.withColumn("key", F.round(F.col("key") * F.lit(2.0**20)).cast("bigint")))
    if fraction is None:
        fraction = labels.agg(F.avg(F.when(F.col("quality") == 1, 1.0).when(F.col("quality") == 0, 0.0))).first()[0] or 0.5
    k = round(fraction * scored.count())
    least = kth_largest(scored.select("key"), k) if k else None
    taken = F.lit(k > 0) if least is None else F.col("key") >= least
    return scored.select("doc_id", "n_grams", "log_importance", (F.col("key") / F.lit(2.0**20)).alias("key"), taken.alias("kept"))


def op10_importance(spark, sf_dir: str) -> DataFrame:
    return resample(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


QUERIES = {"op10_importance": op10_importance}
ORACLES: dict[str, str] = {}
