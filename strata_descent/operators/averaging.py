"""Averages of iterates (t, cls, component, w)."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def last(iterates: DataFrame) -> DataFrame:
    return iterates.groupBy("cls", "component").agg(F.max_by("w", "t").alias("w"))


def mean(iterates: DataFrame) -> DataFrame:
    return iterates.groupBy("cls", "component").agg(F.avg("w").alias("w"))


def best(iterates: DataFrame, objective: DataFrame) -> DataFrame:
    """The iterate whose step has the least objective (t, objective)."""
    step = objective.agg(F.min_by("t", F.struct("objective", "t")).alias("t"))
    return iterates.join(F.broadcast(step), "t").select("cls", "component", "w")


def suffix(iterates: DataFrame, alpha: float, steps: int) -> DataFrame:
    """Mean of the last alpha share of the steps."""
    return mean(iterates.where(F.col("t") > math.floor((1 - alpha) * steps)))


def polynomial(iterates: DataFrame, q: int) -> DataFrame:
    """Polynomial decay: each new iterate weighs (q + 1) / (t + q), all before it the rest."""
    rho = F.lit(float(q + 1)) / (F.col("t") + q)
    later = Window.partitionBy("cls", "component").orderBy("t").rowsBetween(1, Window.unboundedFollowing)
    kept = F.exp(F.coalesce(F.sum(F.log(1 - F.lit(float(q + 1)) / (F.greatest(F.col("t"), F.lit(2)) + q))).over(later), F.lit(0.0)))
    return iterates.withColumn("weight", rho * kept).groupBy("cls", "component").agg(F.sum(F.col("weight") * F.col("w")).alias("w"))
