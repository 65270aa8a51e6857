"""The experiment workloads: uniform against stratified minibatches, same b, lambda, schedule and seeds."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.features import VIEWS, view
from ..operators import bounds, cluster, descent, index, measures
from .plan import AllocationConfig, DescentConfig, StrataConfig, StratumPlan

SEEDS = (1, 2, 3, 4, 5)


@dataclass(frozen=True)
class Workload:
    """b, lam and the split fraction (in the view) are those of the experiment that a workload stands for."""

    view: str
    classes: int
    b: int
    lam: float
    k: int  # 0: one stratum per class
    epochs: float = 5.0  # steps of b draws; an epoch is as many draws as training rows
    points: int = 10  # evaluations, evenly over the steps
    schedule: str = "inverse"
    builder: str = "kmeans"
    fit_rows: int = 50_000  # rows that strata are fitted on; all rows are assigned


WORKLOADS = {
    "w1": Workload("f1", 2, 10, 1e-5, 10, epochs=1.0),
    "w1c": Workload("f2", 2, 10, 1e-5, 10, epochs=1.0),
    "w2": Workload("f3", 25, 25, 1e-4, 0),
    "w3": Workload("f4", 10, 10, 1e-4, 0),
    "w4": Workload("f5", 4, 13, 1e-3, 8),
    "w5": Workload("f6", 4, 48, 1e-3, 16, builder="kmeans"),
    "w6": Workload("f7", 2, 8, 1e-2, 4, builder="dispersion"),
    "w7": Workload("f8", 5, 20, 1e-2, 10, builder="dispersion"),
}


def curves(spark: SparkSession, sf_dir: str, name: str, seeds: tuple[int, ...] = SEEDS, *, save, **changes) -> DataFrame:
    """The trace of both samplers for all seeds: objective, test error and exact variance by epoch; save writes a table and reads it back."""
    load = replace(WORKLOADS[name], **changes)
    d = VIEWS[load.view].d
    ex = save(view(spark, sf_dir, load.view))
    rows = cluster.train_rows(ex)
    n = rows.count()
    steps = max(1, math.ceil(load.epochs * n / load.b))
    config = DescentConfig(load.lam, load.b, steps, load.schedule, eval_every=-(-steps // load.points))
    fitted = StrataConfig(load.builder, load.k, iters=5, fit_fraction=min(1.0, load.fit_rows / n))
    assigned, strata, plan = descent.prepare(ex, d, load.classes, load.b, fitted, AllocationConfig(), save)
    single = StratumPlan.single(n, load.b)
    one = rows.withColumn("stratum", F.lit(0))
    places = {k: save(index.dense_position(v).select("stratum", "pos", "row_id", "y", "x")) for k, v in (("uniform", one), ("stratified", assigned))}
    plans = {"uniform": single, "stratified": plan}
    zero = np.zeros((load.classes, d))
    runs = [descent.Run(f"{sampler}|{seed}", places[sampler], plans[sampler], replace(config, seed=seed), zero, sampler) for sampler in plans for seed in seeds]
    models = save(descent.run_chains(runs))
    scored = descent.evaluate(models, ex, load.lam)
    spread = descent.variances(models.where("run_id like 'uniform|%'"), one, single).unionByName(descent.variances(models.where("run_id like 'stratified|%'"), assigned, plan))
    trace = scored.join(spread, ["run_id", "t"])
    sampler, seed = F.split("run_id", "[|]")[0], F.split("run_id", "[|]")[1].cast("int")
    eta = {"inverse": 1.0 / (F.lit(load.lam) * F.col("t"))}.get(load.schedule, F.lit(None).cast("double"))
    smoothness = bounds.constants(rows, load.lam).first().smoothness
    return trace.select(
        F.lit(name).alias("workload"), sampler.alias("sampler"), F.lit(load.builder if load.k else "by_class").alias("strata_builder"), seed.alias("seed"), "t",
        measures.epoch(F.col("t"), load.b, n).alias("epoch"), (F.col("t") * load.b).alias("gradient_evals"), eta.alias("eta"), "objective", "test_error", "est_variance", "w_norm", (eta <= 1.0 / smoothness + 1e-15).alias("theory_covered"),
    )


def summary(trace: DataFrame) -> DataFrame:
    """Mean, deviation, least and most over the seeds, by sampler and step."""
    return measures.summarise(trace, ["workload", "sampler", "t"], ["objective", "test_error", "est_variance"])


def ratios(trace: DataFrame) -> DataFrame:
    """Mean stratified over mean uniform variance and the differences of the other measures, by step."""
    by = trace.groupBy("workload", "t").pivot("sampler", ["uniform", "stratified"]).agg(F.avg("est_variance").alias("variance"), F.avg("objective").alias("objective"), F.avg("test_error").alias("error"))
    return by.select("workload", "t", F.try_divide("stratified_variance", "uniform_variance").alias("variance_ratio"), (F.col("stratified_objective") - F.col("uniform_objective")).alias("objective_difference"), (F.col("stratified_error") - F.col("uniform_error")).alias("error_difference"))


def gaps(spark: SparkSession, sf_dir: str, name: str, trace: DataFrame) -> DataFrame:
    """Objective gap to the workload's optimum (by a quasi-Newton fit), mean over the seeds, and the slope of its logarithm over that of t."""
    load = WORKLOADS[name]
    ex = view(spark, sf_dir, load.view)
    best = bounds.reference_optimum(spark, ex, load.lam, load.classes)
    least = measures.objective(cluster.train_rows(ex), best.tolist(), load.lam).first()[0]
    gap = trace.groupBy("workload", "sampler", "t").agg((F.avg("objective") - least).alias("gap"))
    slopes = gap.where("gap > 0").groupBy("sampler").agg(F.regr_slope(F.log("gap"), F.log("t")).alias("slope"))
    return gap.join(F.broadcast(slopes), "sampler", "left").select("workload", "sampler", "t", "gap", "slope")


def scale_run(spark: SparkSession, sf_dir: str, save, replicas: tuple[int, ...] = (1, 4, 16), steps: int = 200) -> DataFrame:
    """Cost of setting up and of training on the first workload's rows, repeated so many times: (replicas, rows, phase, seconds, jobs, stages, input and shuffle bytes).

    Tables that no later step reads go at once, so that the copies stand on disk as few times as they can.
    """
    load, out = WORKLOADS["w1"], []
    d = VIEWS[load.view].d
    ex = save(view(spark, sf_dir, load.view))
    for k in replicas:
        copies = spark.range(k).withColumnRenamed("id", "copy")
        many = save(ex.crossJoin(F.broadcast(copies)).withColumn("row_id", F.col("row_id") * k + F.col("copy")).drop("copy"))  # a few copies of the rows
        n = cluster.train_rows(many).count()
        with measures.Cost(spark) as setup:
            assigned, _, plan = descent.prepare(many, d, load.classes, load.b, StrataConfig(load.builder, load.k, iters=3, fit_fraction=min(1.0, load.fit_rows / n)), AllocationConfig(), save)
            save.clear(ex, assigned)
            indexed = index.dense_position(assigned, index.buckets_for(plan.n), save)
        save.clear(ex, indexed)  # the index has all rows
        config = DescentConfig(load.lam, load.b, steps, load.schedule, eval_every=steps)
        with measures.Cost(spark) as train:
            descent.run_chains([descent.Run("run", indexed, plan, config, np.zeros((load.classes, d)))]).count()
        out += [(k, n, name, *cost.row()) for name, cost in (("setup", setup), ("train", train))]
        save.clear(ex)
    return spark.createDataFrame(out, f"replicas int, rows bigint, phase string, {measures.Cost.SCHEMA}")


def ablation(spark: SparkSession, sf_dir: str, view_name: str, classes: int, b: int, k: int, save) -> DataFrame:
    """Surrogate and exact origin variance for every builder, allocation and rounding."""
    from ..operators import allocate, variance

    d = VIEWS[view_name].d
    ex = save(view(spark, sf_dir, view_name))
    out = None
    for builder in ("by_class", "kmeans", "dispersion", "frozen", "random", "quantile"):
        assigned = save(cluster.build(ex, d, StrataConfig(builder, k, iters=5), save))
        strata = save(cluster.stats(assigned, d))
        for kind in ("dispersion", "proportional", "equal"):
            for rounding in ("greedy", "remainder", "systematic"):
                counted = allocate.allocate(strata, b, kind, rounding)
                row = allocate.surrogate(counted).crossJoin(variance.at_origin(counted, classes)).select(F.lit(builder).alias("builder"), F.lit(kind).alias("kind"), F.lit(rounding).alias("rounding"), "bound", "variance")
                out = row if out is None else out.unionByName(row)
    return out
