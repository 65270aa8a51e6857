"""Splitting the draws of a step over the strata (stratum, n_i, v_i)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window, WindowSpec
from pyspark.sql import functions as F

from ..functions.rng import unit

def everything() -> WindowSpec:
    """All strata: a row each, so the window is small."""
    return Window.partitionBy(F.lit(1))


def weight(kind: str) -> Column:
    if kind == "dispersion":
        return F.col("n_i") * F.sqrt("v_i")
    if kind == "proportional":
        return F.col("n_i").cast("double")
    if kind == "equal":
        return F.lit(1.0)
    raise ValueError(kind)


def shares(strata: DataFrame, kind: str) -> DataFrame:
    """strata with share, adding up to 1; proportional where no stratum has any dispersion."""
    weighed = strata.withColumn("w", weight(kind))
    total = F.sum("w").over(everything())
    share = F.when(total > 0, F.try_divide(F.col("w"), total)).otherwise(F.col("n_i") / F.sum("n_i").over(everything()))
    return weighed.withColumn("share", share).drop("w")


def real(strata: DataFrame, b: int, kind: str = "dispersion") -> DataFrame:
    return shares(strata, kind).withColumn("b_real", F.col("share") * b)


def round_greedy(strata: DataFrame, b: int, kind: str = "dispersion") -> DataFrame:
    """Whole draws that minimise the sum of weight^2 / b_i, for dispersion of n_i^2 v_i / b_i, with one draw each at least.

    The sum is convex in each b_i, so the b - k largest gains of one more draw are the best ones.  With
    no dispersion at all every gain is 0 and shares of rows decide.
    """
    k = strata.count()
    squares = {"dispersion": F.col("n_i") * F.col("n_i") * F.col("v_i"), "proportional": F.col("n_i") * F.col("n_i"), "equal": F.lit(1.0)}[kind]
    mass = F.when(F.sum(weight(kind)).over(everything()) > 0, squares).otherwise(F.col("n_i") * F.col("n_i"))
    weighed = strata.withColumn("mass", mass.cast("double"))
    spare = max(0, b - k)
    steps = strata.sparkSession.range(1, spare + 1).withColumnRenamed("id", "j")
    gains = weighed.select("stratum", "mass").crossJoin(F.broadcast(steps))  # at most b strata times b draws
    gains = gains.withColumn("gain", F.round(F.col("mass") / (F.col("j") * (F.col("j") + 1)), 9))
    best = gains.withColumn("place", F.row_number().over(everything().orderBy(F.desc("gain"), "stratum", "j"))).where(F.col("place") <= spare)
    won = best.groupBy("stratum").agg(F.count("*").alias("won"))
    return strata.join(won, "stratum", "left").withColumn("b_i", (1 + F.coalesce("won", F.lit(0))).cast("int")).drop("won")


def round_remainder(strata: DataFrame, b: int, kind: str = "dispersion") -> DataFrame:
    """One draw each, the others by share with the largest remainders rounded up."""
    k = F.count("*").over(everything())
    spare = shares(strata, kind).withColumn("real", F.round(F.col("share") * (F.lit(b) - k), 9))
    spare = spare.withColumns({"whole": F.floor("real"), "rest": F.round(F.col("real") - F.floor("real"), 9)})
    left = F.lit(b) - F.count("*").over(everything()) - F.sum("whole").over(everything())
    place = F.row_number().over(everything().orderBy(F.desc("rest"), "stratum"))
    return spare.withColumns({"left": left, "place": place}).withColumn("b_i", (1 + F.col("whole") + F.when(F.col("place") <= F.col("left"), 1).otherwise(0)).cast("int")).drop("share", "real", "whole", "rest", "left", "place")


def round_systematic(strata: DataFrame, b: int, seed: int = 1, kind: str = "dispersion") -> DataFrame:
    """One draw each, the others at whole numbers of one line of shares with a random offset: unbiased, sum kept."""
    k = F.count("*").over(everything())
    line = shares(strata, kind).withColumn("real", F.round(F.col("share") * (F.lit(b) - k), 9))
    upto = F.round(F.sum("real").over(everything().orderBy("stratum").rowsBetween(Window.unboundedPreceding, 0)), 6)
    before = F.coalesce(F.round(F.sum("real").over(everything().orderBy("stratum").rowsBetween(Window.unboundedPreceding, -1)), 6), F.lit(0.0))
    offset = F.round(unit("systematic", seed), 6)
    counted = line.withColumns({"upto": upto, "before": before})
    return counted.withColumn("b_i", (1 + F.floor(F.col("upto") + offset) - F.floor(F.col("before") + offset)).cast("int")).drop("share", "real", "upto", "before")


def allocate(strata: DataFrame, b: int, kind: str = "dispersion", rounding: str = "greedy", seed: int = 1) -> DataFrame:
    """strata with b_i; without rounding, the real shares of b, which bounds may be evaluated at but no step can draw."""
    match rounding:
        case "greedy":
            return round_greedy(strata, b, kind)
        case "remainder":
            return round_remainder(strata, b, kind)
        case "systematic":
            return round_systematic(strata, b, seed, kind)
        case "none":
            return real(strata, b, kind).withColumnRenamed("b_real", "b_i").drop("share")
    raise ValueError(f"unknown rounding {rounding!r}")


def gradient_dispersion(within: DataFrame, labels: DataFrame) -> DataFrame:
    """(stratum, y, n_i, v_i) with v_i the mean squared deviation of the gradients, from variance.within and (stratum, y)."""
    return within.join(labels, "stratum").select("stratum", "y", F.col("cnt").alias("n_i"), (F.col("ss") / F.col("cnt")).alias("v_i"))


def surrogate(strata: DataFrame, counts: str = "b_i") -> DataFrame:
    """One row: the feature-space bound of the estimator's variance, with Lipschitz constant 1."""
    n = F.sum("n_i")
    return strata.agg((F.sum(F.col("n_i") * F.col("n_i") * F.col("v_i") / F.col(counts)) / (n * n)).alias("bound"))
