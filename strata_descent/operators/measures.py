"""Accuracy and cost measures over examples and traces."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import loss as L


def objective(ex: DataFrame, w: L.Weights, lam: float) -> DataFrame:
    """One row: mean softmax loss over ex plus lam / 2 of the squared weights."""
    ridge = lam / 2 * sum(v * v for row in w for v in row)
    return ex.agg((F.avg(L.softmax_value(L.logits(F.col("x"), w), F.col("y"))) + ridge).alias("objective"))


def error_rate(ex: DataFrame, w: L.Weights) -> DataFrame:
    """One row: share of rows whose class is not the one of largest score (ties: lowest code)."""
    wrong = L.predicted(L.logits(F.col("x"), w)) != F.col("y")
    return ex.agg(F.avg(wrong.cast("double")).alias("error"))


def confusion(ex: DataFrame, w: L.Weights) -> DataFrame:
    return ex.select("y", L.predicted(L.logits(F.col("x"), w)).alias("cls")).groupBy("y", "cls").agg(F.count("*").alias("n_rows"))


def epoch(t: F.Column, b: int, n: int) -> F.Column:
    return t * b / F.lit(n)


def gradient_evals(sampler: str, n: int, b: int) -> int:
    """Row gradients that one step needs."""
    return {"full": n, "single": 1, "uniform": b, "stratified": b, "dynamic": n + b}[sampler]


def summarise(trace: DataFrame, by: list[str], values: list[str]) -> DataFrame:
    """Mean, deviation, least and most of each value over seeds."""
    aggs = [f(v).alias(f"{v}_{name}") for v in values for name, f in (("mean", F.avg), ("sd", F.stddev_samp), ("min", F.min), ("max", F.max))]
    return trace.groupBy(*by).agg(F.count("*").alias("runs"), *aggs)


def stability(trace: DataFrame, by: list[str], value: str, order: str = "t") -> DataFrame:
    """Mean absolute change from one evaluation to the next."""
    change = F.abs(F.col(value) - F.lag(value).over(Window.partitionBy(*by).orderBy(order)))
    return trace.withColumn("change", change).groupBy(*by).agg(F.avg("change").alias("mean_change"))


def moving_average(df: DataFrame, by: list[str], value: str, order: list[str], width: int = 5) -> DataFrame:
    over = Window.partitionBy(*by).orderBy(*order).rowsBetween(-(width - 1), 0)
    return df.withColumn("moving", F.avg(value).over(over))


def align_epochs(left: DataFrame, right: DataFrame, value: str) -> DataFrame:
    """As-of join: for each epoch of left the last value of right at or before it."""
    both = left.select("epoch", F.lit(1).alias("side"), F.col(value).alias("left_value"), F.lit(None).cast("double").alias("right_value")).unionByName(
        right.select("epoch", F.lit(0).alias("side"), F.lit(None).cast("double").alias("left_value"), F.col(value).alias("right_value"))
    )
    seen = F.last("right_value", ignorenulls=True).over(Window.partitionBy(F.lit(1)).orderBy("epoch", "side").rowsBetween(Window.unboundedPreceding, 0))
    return both.withColumn("right_value", seen).where("side = 1").select("epoch", "left_value", "right_value")


def rate_slope(trace: DataFrame, gap: str = "gap") -> DataFrame:
    """One row: slope of log gap against log t."""
    ok = trace.where(F.col(gap) > 0)
    return ok.agg(F.regr_slope(F.log(gap), F.log("t")).alias("slope"))


def ratio(trace: DataFrame, value: str, of: str, to: str, by: list[str]) -> DataFrame:
    """Mean of a value under one sampler over that under another, by the given columns."""
    mean = lambda name: F.avg(F.when(F.col("sampler") == name, F.col(value)))
    return trace.groupBy(*by).agg(F.try_divide(mean(of), mean(to)).alias("ratio"))


class Cost:
    """What the jobs inside a with block took, from Spark's own status store: seconds, jobs, stages run, bytes read and shuffled."""

    SCHEMA = "seconds double, stages bigint, tasks bigint, input_bytes bigint, shuffle_bytes bigint, spilled_bytes bigint"

    def __init__(self, spark: SparkSession):
        self.spark = spark
        self.seconds, self.values = 0.0, (0, 0, 0, 0, 0)

    def _stages(self) -> dict[tuple[int, int], tuple[int, ...]]:
        context = self.spark.sparkContext
        context._jsc.sc().listenerBus().waitUntilEmpty(30_000)
        lists = context._jvm.java.util.ArrayList
        found = context._jsc.sc().statusStore().stageList(lists(), False, False, context._gateway.new_array(context._jvm.double, 0), lists())
        return {(s.stageId(), s.attemptId()): (s.numCompleteTasks(), s.inputBytes(), s.shuffleWriteBytes(), s.diskBytesSpilled()) for s in (found.apply(i) for i in range(found.size()))}

    def __enter__(self) -> Cost:
        self.before, self.began = self._stages(), time.time()
        return self

    def __exit__(self, *_) -> None:
        self.seconds = time.time() - self.began
        new = [v for k, v in self._stages().items() if k not in self.before and v[0]]
        self.values = (len(new), *(sum(v[i] for v in new) for i in range(4)))

    def row(self) -> tuple:
        return (float(self.seconds), *map(int, self.values))
