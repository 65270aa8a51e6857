"""Right sides of the convergence bounds, their constants, and the inequalities as checks."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import loss as L
from . import measures, variance


def constants(ex: DataFrame, lam: float) -> DataFrame:
    """One row: smoothness (half the largest squared feature norm, plus lam) and strong convexity (lam)."""
    return ex.agg((0.5 * F.max(L.norm2(F.col("x"))) + lam).alias("smoothness"), F.lit(float(lam)).alias("convexity"))


def one_step(objective: float, gradient_norm2: float, variance: float, eta: float, smoothness: float) -> float:
    """Bound of the expected objective after one step."""
    return objective - eta * (1 - eta * smoothness / 2) * gradient_norm2 + eta * eta * smoothness / 2 * variance


def one_step_frame(cases: DataFrame) -> DataFrame:
    """one_step for a frame (objective, gradient_norm2, variance, eta, smoothness)."""
    eta, smooth = F.col("eta"), F.col("smoothness")
    return cases.withColumn("bound", F.col("objective") - eta * (1 - eta * smooth / 2) * F.col("gradient_norm2") + eta * eta * smooth / 2 * F.col("variance"))


def lemma1(eta: float, dist2_before: float, dist2_after: float, h: float, variance: float) -> float:
    """Right side for one step: what the distances to the optimum and the variance allow."""
    return (dist2_before - dist2_after) / (2 * eta) - h / 2 * dist2_before + eta * variance


def theorem1(trace: DataFrame, a: float, h: float, optimum_norm2: float) -> DataFrame:
    """One row: bound of the mean objective gap for steps 1 / (a + h t); trace has (t, variance)."""
    return trace.agg(((a * optimum_norm2 / 2 + F.sum(F.col("variance") / (a + h * F.col("t")))) / F.count("*")).alias("bound"))


def contraction(eta: float, h: float, smoothness: float) -> float:
    return 1 - 2 * eta * h * smoothness / (h + smoothness)


def theorem2(trace: DataFrame, eta: float, h: float, smoothness: float, optimum_norm2: float) -> DataFrame:
    """One row: bound of the last objective gap for a constant step in (0, 2 / (h + smoothness)]."""
    if not 0 < eta <= 2 / (h + smoothness) + 1e-15:
        raise ValueError(f"step {eta} is outside the bound's range")
    alpha = max(contraction(eta, h, smoothness), 0.0)
    terms = trace.crossJoin(F.broadcast(trace.agg(F.max("t").alias("last_t"))))  # one row
    decayed = F.sum(F.pow(F.lit(alpha), F.col("last_t") - F.col("t")) * F.col("variance"))
    return terms.agg((F.pow(F.lit(alpha), F.max("last_t")) * optimum_norm2 * smoothness / 2 + eta * eta * smoothness / 2 * decayed).alias("bound"))


def lemma2_sides(gu: np.ndarray, gv: np.ndarray, u: np.ndarray, v: np.ndarray, h: float, smoothness: float) -> tuple[float, float]:
    """Inner product of gradient and model differences, and its lower bound for strongly convex smooth functions."""
    if smoothness < h - 1e-15:
        raise ValueError("smoothness below convexity")
    g, w = gu - gv, u - v
    return float((g * w).sum()), float(h * smoothness / (h + smoothness) * (w * w).sum() + (g * g).sum() / (h + smoothness))


def check_definitions(rows: DataFrame, pairs: list[tuple[np.ndarray, np.ndarray]], lam: float) -> DataFrame:
    """(pair, check, left_side, right_side, holds) of the inequalities that the bounds rest on, at pairs (U, V) of models.

    For the regularised objective P with convexity lam and smoothness of constants(): convexity and strong
    convexity from below, smoothness from above, the gradient's Lipschitz bound, co-coercivity, and the two
    together.  One pass over rows per model.
    """
    c = constants(rows, lam).first()
    smooth = c.smoothness
    seen: dict[bytes, tuple[float, np.ndarray]] = {}

    def at(w: np.ndarray) -> tuple[float, np.ndarray]:
        if w.tobytes() not in seen:
            g = np.zeros_like(w)
            for r in variance.full_gradient(rows, w.tolist(), lam).collect():  # one matrix
                g[r.cls, r.component] = r.g
            seen[w.tobytes()] = (measures.objective(rows, w.tolist(), lam).first()[0], g)
        return seen[w.tobytes()]

    out = []
    for i, (u, v) in enumerate(pairs):
        (pu, gu), (pv, gv) = at(u), at(v)
        gap, turn = u - v, gu - gv
        inner, distance, bend = float((gv * gap).sum()), float((gap * gap).sum()), float((turn * turn).sum())
        both = lemma2_sides(gu, gv, u, v, lam, smooth)
        sides = {
            "convex": (pu, pv + inner),
            "strongly_convex": (pu, pv + inner + lam / 2 * distance),
            "smooth": (pv + inner + smooth / 2 * distance, pu),
            "lipschitz_gradient": (smooth * np.sqrt(distance), np.sqrt(bend)),
            "co_coercive": (float((turn * gap).sum()), bend / smooth),
            "strongly_convex_and_smooth": both,
        }
        out += [(i, name, round(float(a), 6), round(float(b), 6), bool(a >= b - 1e-9)) for name, (a, b) in sides.items()]
    return rows.sparkSession.createDataFrame(out, "pair int, check string, left_side double, right_side double, holds boolean")


def on_run(trace: DataFrame, a: float, h: float, optimum_norm2: float) -> DataFrame:
    """(sampler, mean_gap, bound, holds) of runs from zero with steps 1 / (a + h t); trace: (sampler, t, gap, variance), means over seeds, of every step.

    A step's variance is the one at the model before it.
    """
    step = F.lit(a) + F.lit(h) * F.col("t")
    sums = trace.groupBy("sampler").agg(F.avg("gap").alias("mean_gap"), ((a * optimum_norm2 / 2 + F.sum(F.col("variance") / step)) / F.count("*")).alias("bound"))
    return sums.withColumn("holds", F.col("mean_gap") <= F.col("bound") + 1e-12)


def reference_optimum(spark: SparkSession, ex: DataFrame, lam: float, classes: int, iterations: int = 500) -> np.ndarray:
    """The minimiser of the regularised softmax objective over the training rows, by MLlib."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.functions import array_to_vector

    rows = ex.where("split = 'train'").select(F.col("y").cast("double").alias("label"), array_to_vector("x").alias("features"))
    fitted = LogisticRegression(family="multinomial", regParam=lam, elasticNetParam=0.0, fitIntercept=False, standardization=False, maxIter=iterations, tol=1e-12).fit(rows)
    return np.array(fitted.coefficientMatrix.toArray())
