"""Dense positions of rows in their strata, and the layout that minibatches are fetched from."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.rng import hash52

#: Buckets that order a stratum's rows, and the rows of one beyond which it is ranked in ranges.
BUCKETS, ROWS_PER_BUCKET = 64, 500_000
#: Ranges of all buckets whose rows are shuffled at a time where ranks are written: 128 million rows at most.
RANGES_AT_ONCE = 4
BLOCK_ROWS = 1 << 20


def buckets_for(n: int) -> int:
    return max(BUCKETS, 1 << max(0, -(-n // ROWS_PER_BUCKET) - 1).bit_length())


def dense_position(assigned: DataFrame, buckets: int | None = None, save=None) -> DataFrame:
    """assigned with bucket and pos, 0 to n_i - 1 in each stratum by (bucket, row_id), at every size.

    Rows are ranked inside ranges of row_id of a hash bucket only; a range's first position is the sum of
    those before it, so no task sees a whole stratum.  The number of ranges follows the rows (buckets: their
    number in all, if known) and does not change a position.  With save some ranges at a time are ranked and
    written, so that only their rows are in shuffle files, and counted there, so that buckets are hashed once;
    what is returned then reads those tables.
    """
    ranges = (buckets or buckets_for(assigned.count())) // BUCKETS
    cuts = assigned.agg(F.percentile_approx("row_id", [i / ranges for i in range(1, ranges)], 10_000)).first()[0] if ranges > 1 else []

    def marked(first: int, last: int) -> DataFrame:
        """The rows of ranges first to last - 1; those without a row_id are in the first."""
        rows = assigned.where(F.col("row_id") > cuts[first - 1]) if first else assigned
        rows = rows.where((F.col("row_id") <= cuts[last - 1]) | F.col("row_id").isNull()) if last < ranges else rows
        inner = cuts[first : last - 1]
        range_ = F.coalesce(F.size(F.filter(F.array(*map(F.lit, inner)), lambda c: c < F.col("row_id"))), F.lit(0)) if inner else F.lit(0)
        return rows.withColumn("bucket", (hash52("bucket", F.col("row_id")) % BUCKETS).cast("int")).withColumn("range_", range_ + first)

    inside = F.row_number().over(Window.partitionBy("stratum", "bucket", "range_").orderBy("row_id")) - 1
    if save:
        parts = [save(marked(first, min(first + RANGES_AT_ONCE, ranges)).withColumn("inside", inside)) for first in range(0, ranges, RANGES_AT_ONCE)]
        ranked = counted = reduce(DataFrame.unionByName, parts)
    else:
        counted = marked(0, ranges)
        ranked = counted.withColumn("inside", inside)
    counts = counted.groupBy("stratum", "bucket", "range_").agg((F.max("inside") + 1 if save else F.count("*")).alias("rows_"))
    before = Window.partitionBy("stratum").orderBy("bucket", "range_").rowsBetween(Window.unboundedPreceding, -1)
    offsets = counts.select("stratum", "bucket", "range_", F.coalesce(F.sum("rows_").over(before), F.lit(0)).alias("offset"))
    if save:
        offsets = save(offsets)
    # strata times buckets rows
    return ranked.join(F.broadcast(offsets), ["stratum", "bucket", "range_"]).withColumn("pos", F.col("offset") + F.col("inside")).drop("offset", "inside", "range_")


def write(indexed: DataFrame, path: str) -> None:
    """Folders by stratum and block of positions: draws, which carry their block, read the folders that they hit (dynamic partition pruning)."""
    blocks = indexed.withColumn("block", F.floor(F.col("pos") / BLOCK_ROWS).cast("bigint"))
    blocks.repartition("stratum", "block").sortWithinPartitions("stratum", "block", "pos").write.mode("overwrite").partitionBy("stratum", "block").parquet(path)


def read(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)
