"""Sources and sinks: tables with contracts, a catalog of views, LIBSVM, bucketed tables, traces, a rate stream, round trips through other formats."""

from __future__ import annotations

from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
EXAMPLE = {"row_id": "bigint", "y": "int", "x": "array<double>", "split": "string"}


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    if table not in TABLES:
        raise ValueError(f"unknown table {table}")
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


@contextmanager
def short_lived(spark: SparkSession):
    """Shuffle files of the queries run inside go as each query ends, not when the driver happens to collect its garbage."""
    name = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(name, "false")
    spark.conf.set(name, "true")
    try:
        yield
    finally:
        spark.conf.set(name, before)


def assert_contract(df: DataFrame, contract: dict[str, str] = EXAMPLE) -> DataFrame:
    """df, if it has the contract's columns with their types."""
    have = dict(df.dtypes)
    wrong = {c: (t, have.get(c)) for c, t in contract.items() if have.get(c) != t}
    if wrong:
        raise TypeError(f"columns (wanted, found): {wrong}")
    return df


def write_libsvm(ex: DataFrame, path: str) -> None:
    """Examples as LIBSVM text: label, then 1-based index:value of the nonzero features."""
    pairs = F.expr("array_join(transform(filter(transform(x, (v, j) -> struct(j + 1 as j, v as v)), p -> p.v != 0), p -> concat(p.j, ':', p.v)), ' ')")
    ex.select(F.concat_ws(" ", F.col("y").cast("string"), pairs).alias("value")).write.mode("overwrite").text(path)


def read_libsvm(spark: SparkSession, path: str, d: int) -> DataFrame:
    """(y, x) with dense x."""
    from pyspark.ml.functions import vector_to_array

    rows = spark.read.format("libsvm").option("numFeatures", str(d)).load(path)
    return rows.select(F.col("label").cast("int").alias("y"), vector_to_array("features").alias("x"))


def roundtrip(df: DataFrame, fmt: str, path: str) -> DataFrame:
    """df written as csv, json, orc or parquet and read back with its own schema."""
    df.write.mode("overwrite").format(fmt).option("header", "true").save(path)
    return df.sparkSession.read.schema(df.schema).format(fmt).option("header", "true").load(path)


def register(spark: SparkSession, sf_dir: str) -> list[str]:
    """Every table of a folder as a temporary view of its name, for SQL; returns the names."""
    for table in TABLES:
        load(spark, sf_dir, table).createOrReplaceTempView(table)
    return list(TABLES)


def write_bucketed(df: DataFrame, name: str, keys: list[str], buckets: int) -> DataFrame:
    """df as a table of the warehouse, bucketed and sorted by keys, so that joins and aggregates on them need no shuffle."""
    df.write.mode("overwrite").format("parquet").bucketBy(buckets, *keys).sortBy(*keys).saveAsTable(name)
    return df.sparkSession.table(name)


def export_trace(trace: DataFrame, path: str, fmt: str = "csv") -> None:
    """A trace in files by workload and sampler, as plotting tools read them."""
    trace.write.mode("overwrite").format(fmt).option("header", "true").partitionBy("workload", "sampler").save(path)


def rate_examples(spark: SparkSession, d: int, classes: int, rows_per_second: int = 100) -> DataFrame:
    """A stream of made-up examples (row_id, ts, y, x) at a steady rate, to try online descent on."""
    rows = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    y = F.pmod(F.xxhash64("value"), F.lit(classes)).cast("int")
    x = F.transform(F.sequence(F.lit(0), F.lit(d - 1)), lambda j: F.pmod(F.xxhash64("value", j), F.lit(1000)) / 500.0 - 1 + F.when(j % classes == y, 1.0).otherwise(0.0))
    return rows.select(F.col("value").alias("row_id"), F.col("timestamp").alias("ts"), y.alias("y"), x.alias("x"))
