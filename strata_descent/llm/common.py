"""What the operators share: durable intermediate tables, size-checked joins, sources."""

from __future__ import annotations

import tempfile
import uuid
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A side of at most this many rows of a few numbers (tens of MB) may be broadcast.
BROADCAST_ROWS = 1_000_000
BATCH_ROWS = 1000
#: A set of keys that tells which texts move is 2**MARK_BITS bits, a million words, at every size.
MARK_BITS = 26
SPACE = r"[\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


_written: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """A new folder below spark.checkpoint.dir; only a session on one machine may do without, as in tests."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not root:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        root = Path(tempfile.mkdtemp(prefix="shared-")).as_uri()
        spark.sparkContext.setCheckpointDir(root)
    return f"{root.rstrip('/')}/{uuid.uuid4().hex}"


def saved(df: DataFrame) -> DataFrame:
    """The rows of df written to the shared folder and read back: lineage is cut, losing an executor loses nothing."""
    spark = df.sparkSession
    path = shared_dir(spark)
    df.write.parquet(path)
    _written.append(path)
    return spark.read.schema(df.schema).parquet(path)


def clear(spark: SparkSession, *keep: DataFrame) -> None:
    """Delete the tables that saved() has written, but for those that keep reads; for callers that are done with their results."""
    left = {f.rsplit("/", 1)[0].rsplit("/", 1)[-1] for df in keep for f in df.inputFiles()}
    for path in [p for p in _written if p.rsplit("/", 1)[-1] not in left]:
        where = spark._jvm.org.apache.hadoop.fs.Path(path)
        where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)
        _written.remove(path)


def small_batches(spark: SparkSession) -> None:
    """Arrow batches of at most BATCH_ROWS texts, so that a batch of long ones fits into a task; a setting of the running session."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(spark.conf.get(name)) <= BATCH_ROWS:
        spark.conf.set(name, str(BATCH_ROWS))


def documents(docs: DataFrame, *more: str) -> DataFrame:
    """doc_id and text (null: empty), and no other column unless named; extra columns never clash."""
    small_batches(docs.sparkSession)
    return docs.select(F.col("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"), *more)


def at_most(df: DataFrame, rows: int = BROADCAST_ROWS) -> bool:
    """Whether df has at most so many rows, without counting them all."""
    return df.select(F.lit(1).alias("one")).limit(rows + 1).count() <= rows


def checked(df: DataFrame, rows: int = BROADCAST_ROWS) -> DataFrame:
    """df with a broadcast hint if its size, looked up now, allows it; else as it is, to be joined by a shuffle."""
    return F.broadcast(df) if at_most(df, rows) else df


def words_column(text: str = "text") -> str:
    """SQL for the array of words of a text."""
    return rf"filter(split({text}, '[\\x20\\x09-\\x0D]+'), w -> w != '')"


def row_key() -> Column:
    """A hash that stands for a row in joins: rows without an id have one too, and rows of one id and text share it."""
    return F.xxhash64(F.col("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")))


def marks(keys: DataFrame, key: str = "rid") -> DataFrame:
    """A bitmap of the hashes in keys, as at most 2**MARK_BITS / 64 rows (word, bits), so it may be broadcast whatever their number."""
    place = F.shiftrightunsigned(key, 64 - MARK_BITS)
    words = keys.select(F.shiftright(place, 6).alias("mark word"), F.expr(f"shiftleft(1L, cast(shiftrightunsigned(`{key}`, {64 - MARK_BITS}) & 63 as int))").alias("bit"))
    return saved(words.groupBy("mark word").agg(F.bit_or("bit").alias("mark bits")))


def where_marked(df: DataFrame, bitmap: DataFrame, key: str = "rid", marked: bool = True) -> DataFrame:
    """The rows of df whose key is in the bitmap, and few others while it is sparse; or all other rows.

    A filter before an exact join, which keeps most texts that the join would drop from moving.
    """
    place = f"shiftrightunsigned(`{key}`, {64 - MARK_BITS})"
    found = df.withColumn("mark word", F.expr(f"shiftright({place}, 6)")).join(F.broadcast(bitmap), "mark word", "left")
    hit = F.expr(f"coalesce(shiftrightunsigned(`mark bits`, cast({place} & 63 as int)) & 1 = 1, false)")
    return found.where(hit if marked else ~hit).select(*(f"`{c}`" for c in df.columns))


def only(df: DataFrame, ids: DataFrame, key: str = "doc_id", how: str = "left_semi") -> DataFrame:
    """The rows of df whose key is among ids (distinct); where ids are too many to broadcast, a bitmap keeps most others from moving."""
    if at_most(ids):
        return df.join(F.broadcast(ids), key, how)
    name = "id hash"
    some = where_marked(df.withColumn(name, F.xxhash64(key)), marks(ids.select(F.xxhash64(key).alias(name)), name), name)
    return some.drop(name).join(ids, key, how)
