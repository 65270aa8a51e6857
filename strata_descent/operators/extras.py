"""Methods that combine with stratified draws: snapshot correction, moment control, importance draws."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import loss as L
from ..functions.rng import hash52, unit
from ..plans.plan import DescentConfig, StratumPlan
from . import cluster, index, sampling, variance


Step = tuple[np.ndarray, np.ndarray, np.ndarray]  # x, y and weight of a step's draws


def _kernel(rows: Step, w: np.ndarray, config: DescentConfig) -> np.ndarray:
    x, y, weight = rows
    return (L.get(config.loss).residual(x @ w.T, y) * weight[:, None]).T @ x + config.lam * w


def gradient_matrix(ex: DataFrame, w: np.ndarray, lam: float, loss: str = "softmax") -> np.ndarray:
    g = np.zeros_like(w)
    for r in variance.full_gradient(ex, w.tolist(), lam, loss).collect():
        g[r.cls, r.component] = r.g
    return g


def snapshot(ex: DataFrame, indexed: DataFrame, plan: StratumPlan, config: DescentConfig, epochs: int, classes: int, d: int) -> list[np.ndarray]:
    """Iterates of snapshot-corrected descent: each outer epoch takes one full gradient, each step a minibatch at both points."""
    from .descent import by_step, schedule_of

    w, out, step = np.zeros((classes, d)), [], schedule_of(config)
    rows = cluster.train_rows(ex)
    for epoch in range(epochs):
        anchor = w.copy()
        full = gradient_matrix(rows, anchor, config.lam, config.loss)
        first = epoch * config.steps + 1
        drawn = sampling.fetch(sampling.plan_chunk(ex.sparkSession, plan, config.seed, first, first + config.steps - 1), indexed, n_draws=config.steps * config.b)
        for t, mine in by_step(drawn, d).items():  # one epoch's draws
            w = w - step.at(t) * (_kernel(mine, w, config) - _kernel(mine, anchor, config) + full)
            out.append(w)
    return out


def moments(ex: DataFrame, d: int, classes: int) -> tuple[np.ndarray, np.ndarray]:
    """(mean of onehot(y) x^T, mean of x x^T): all that the linearised softmax needs of the data."""
    rows = cluster.train_rows(ex)
    second = [F.avg(F.col("x")[i] * F.col("x")[j]).alias(f"s{i}_{j}") for i in range(d) for j in range(i, d)]
    first = [F.avg(F.when(F.col("y") == c, F.col("x")[j]).otherwise(0.0)).alias(f"f{c}_{j}") for c in range(classes) for j in range(d)]
    r = rows.agg(F.avg(F.col("x")[0]).alias("one"), *first, *second).first()
    gram = np.array([[r[f"s{min(i, j)}_{max(i, j)}"] for j in range(d)] for i in range(d)])
    return np.array([[r[f"f{c}_{j}"] for j in range(d)] for c in range(classes)]), gram


def moment_control(rows: Step, w: np.ndarray, config: DescentConfig, first: np.ndarray, gram: np.ndarray, mean_x: np.ndarray) -> np.ndarray:
    """A minibatch gradient less the linearised model's minibatch gradient plus its exact mean.

    At zero scores the softmax is 1/m + (s - mean of s)/m to first order, so its gradient is linear in
    x x^T and x, whose means are known.
    """
    m = len(w)
    x, y, weight = rows
    centred = (w - w.mean(axis=0)) / m
    linear = (1 / m + x @ centred.T - np.eye(m)[y]) * weight[:, None]
    expected = np.outer(np.full(m, 1 / m), mean_x) + centred @ gram - first
    return _kernel(rows, w, config) - linear.T @ x + expected


def importance_index(assigned: DataFrame, buckets: int | None = None) -> DataFrame:
    """Rows (row_id, y, x, stratum) with p = |x| over its stratum's sum and the interval [lo, hi) of the stratum's cumulative sum.

    A row without length keeps a little.  One stratum for all rows gives plain importance draws.
    """
    buckets = buckets or index.buckets_for(assigned.count())
    rows = assigned.withColumn("size", F.round(F.sqrt(L.norm2(F.col("x"))) + 1e-6, 9))
    rows = rows.withColumn("bucket", (hash52("bucket", F.col("row_id")) % buckets).cast("int"))
    sums = rows.groupBy("stratum", "bucket").agg(F.sum("size").alias("mass"), F.count("*").alias("rows_"))
    own = Window.partitionBy("stratum")  # a row per bucket
    over = own.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    sums = sums.select("stratum", "bucket", F.coalesce(F.sum("mass").over(over), F.lit(0.0)).alias("before"), F.sum("mass").over(own).alias("total"), F.sum("rows_").over(own).alias("n_i"))
    inside = Window.partitionBy("stratum", "bucket").orderBy("row_id").rowsBetween(Window.unboundedPreceding, 0)
    placed = rows.withColumn("upto", F.sum("size").over(inside)).join(F.broadcast(sums), ["stratum", "bucket"])  # strata times buckets
    lo, hi = (F.col("before") + F.col("upto") - F.col("size")) / F.col("total"), (F.col("before") + F.col("upto")) / F.col("total")
    return placed.select("row_id", "y", "x", "stratum", "n_i", (F.col("size") / F.col("total")).alias("p"), "bucket", lo.alias("lo"), hi.alias("hi"))


def importance_draws(indexed: DataFrame, plan: StratumPlan, seed: int, steps: int) -> DataFrame:
    """(t, stratum, r, row_id, y, x, draw_weight): b_i rows of each stratum drawn with chance p, weighed by 1 / (n p b_i), by a range lookup.

    A draw first finds its bucket, of which a stratum has few, so the inequality join runs inside a bucket.
    """
    spark = indexed.sparkSession
    bounds = indexed.groupBy("stratum", "bucket").agg(F.min("lo").alias("b_lo"), F.max("hi").alias("b_hi"))
    draws = spark.range(1, steps + 1).select(F.col("id").cast("int").alias("t")).crossJoin(plan.frame(spark).select("stratum", "b_i")).withColumn("r", F.explode(F.sequence(F.lit(1), "b_i")))
    draws = draws.withColumn("u", unit(seed, F.col("t"), "importance", F.col("stratum"), F.col("r")))
    draws = draws.join(F.broadcast(bounds), "stratum").where("u >= b_lo and u < b_hi").drop("b_lo", "b_hi")
    hit = F.broadcast(draws).join(indexed, ["stratum", "bucket"]).where("u >= lo and u < hi")
    return hit.select("t", "stratum", "r", "row_id", "y", "x", (1.0 / (F.lit(plan.n) * F.col("p") * F.col("b_i"))).alias("draw_weight"))
