"""Exact, surrogate and resampled variance of the gradient estimators, and full-gradient sums.

A row's gradient is the outer product of its residual and its features, so a stratum needs the count,
the sum of |r|^2 |x|^2 and the sum of r x^T: each partition sends one partial sum per stratum.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import loss as L
from ..functions.rng import hash52

Weights = L.Weights
arrays = L.arrays


def gradient_sums(assigned: DataFrame, w: Weights, loss: str = "softmax") -> DataFrame:
    """(stratum, cnt, squares, cell, g): sums over each stratum, g by cell (class * d + component)."""
    matrix, kernel = np.array(w, dtype=float), L.get(loss)
    m, d = matrix.shape

    def partial(batches):
        state: dict[int, list] = {}
        for batch in batches:
            y, x = arrays(batch, d)
            stratum = batch.column(batch.schema.get_field_index("stratum")).to_numpy(zero_copy_only=False)
            r = kernel.residual(x @ matrix.T, y)
            squares = (r * r).sum(axis=1) * (x * x).sum(axis=1)
            for s in np.unique(stratum):
                at = stratum == s
                have = state.setdefault(int(s), [0, 0.0, np.zeros((m, d))])
                have[0] += int(at.sum())
                have[1] += float(squares[at].sum())
                have[2] += r[at].T @ x[at]
        for s, (n, q, g) in state.items():
            cells = m * d
            yield pa.RecordBatch.from_arrays(
                [pa.array(np.full(cells, s, dtype=np.int32)), pa.array(np.full(cells, n, dtype=np.int64)), pa.array(np.full(cells, q)), pa.array(np.arange(cells, dtype=np.int32)), pa.array(g.ravel())],
                ["stratum", "cnt", "squares", "cell", "g"],
            )

    parts = assigned.select(F.col("stratum").cast("int").alias("stratum"), "y", "x").mapInArrow(partial, "stratum int, cnt bigint, squares double, cell int, g double")
    return parts.groupBy("stratum", "cell").agg(F.sum("cnt").alias("cnt"), F.sum("squares").alias("squares"), F.sum("g").alias("g"))


def centred_within(assigned: DataFrame, w: Weights, loss: str = "softmax") -> DataFrame:
    """within() in two passes: deviations from the means are summed themselves, so nothing cancels where strata are tight.

    |r x^T - G|^2 = |r|^2 |x|^2 - 2 r^T G x + |G|^2 is taken row by row, on x and r moved by nothing else.
    """
    means = gradient_sums(assigned, w, loss).select("stratum", "cell", (F.col("g") / F.col("cnt")).alias("g"))
    matrix, kernel = np.array(w, dtype=float), L.get(loss)
    m, d = matrix.shape
    by: dict[int, np.ndarray] = {}
    for row in means.collect():  # strata times one matrix
        by.setdefault(row.stratum, np.zeros(m * d))[row.cell] = row.g

    def partial(batches):
        state: dict[int, list] = {}
        for batch in batches:
            y, x = arrays(batch, d)
            stratum = batch.column(batch.schema.get_field_index("stratum")).to_numpy(zero_copy_only=False)
            r = kernel.residual(x @ matrix.T, y)
            for s in np.unique(stratum):
                at = stratum == s
                have = state.setdefault(int(s), [0, 0.0])
                for a in range(0, int(at.sum()), 4096):  # a bounded number of gradients at a time
                    gap = np.einsum("nm,nd->nmd", r[at][a : a + 4096], x[at][a : a + 4096]).reshape(-1, m * d) - by[int(s)]
                    have[1] += float((gap * gap).sum())
                have[0] += int(at.sum())
        yield pa.RecordBatch.from_arrays([pa.array(list(state), pa.int32()), pa.array([v[0] for v in state.values()], pa.int64()), pa.array([v[1] for v in state.values()], pa.float64())], ["stratum", "cnt", "ss"])

    parts = assigned.select(F.col("stratum").cast("int").alias("stratum"), "y", "x").mapInArrow(partial, "stratum int, cnt bigint, ss double")
    return parts.groupBy("stratum").agg(F.sum("cnt").alias("cnt"), F.sum("ss").alias("ss"))


def within(sums: DataFrame) -> DataFrame:
    """(stratum, cnt, ss): sum of squared deviations of the gradients from their stratum's mean."""
    return sums.groupBy("stratum").agg(F.first("cnt").alias("cnt"), F.greatest(F.first("squares") - F.sum(F.col("g") * F.col("g")) / F.first("cnt"), F.lit(0.0)).alias("ss"))


def stratified(assigned: DataFrame, w: Weights, strata: DataFrame, loss: str = "softmax") -> DataFrame:
    """One row: exact variance of the stratified estimator with strata's draws b_i."""
    ss = within(gradient_sums(assigned, w, loss)).join(F.broadcast(strata.select("stratum", "b_i")), "stratum")
    n = F.sum("cnt")
    return ss.agg((F.sum(F.col("cnt") / F.col("b_i") * F.col("ss")) / (n * n)).alias("variance"))


def uniform(ex: DataFrame, w: Weights, b: int, loss: str = "softmax") -> DataFrame:
    """One row: exact variance of a uniform minibatch of b draws; the same with a single stratum."""
    ss = within(gradient_sums(ex.withColumn("stratum", F.lit(0)), w, loss))
    return ss.agg((F.sum(F.col("ss") / F.col("cnt")) / b).alias("variance"))


def at_origin(strata: DataFrame, m: int) -> DataFrame:
    """One row: the stratified variance at W = 0, where the residual is constant in a stratum."""
    n = F.sum("n_i")
    return strata.agg(((1 - 1 / m) * F.sum(F.col("n_i") * F.col("n_i") * F.col("v_i") / F.col("b_i")) / (n * n)).alias("variance"))


def at_centroid(assigned: DataFrame, w: Weights, strata: DataFrame) -> DataFrame:
    """One row: the bound that compares each gradient with the gradient at its stratum's mean."""
    joined = assigned.select("stratum", "y", "x").join(F.broadcast(strata.select("stratum", "n_i", "b_i", "mean")), "stratum")
    joined = joined.withColumns({"r": L.softmax_residual(L.logits(F.col("x"), w), F.col("y")), "q": L.softmax_residual(L.logits(F.col("mean"), w), F.col("y"))})
    cross = L.dot(F.col("r"), F.col("q")) * L.dot(F.col("x"), F.col("mean"))
    gap = L.norm2(F.col("r")) * L.norm2(F.col("x")) + L.norm2(F.col("q")) * L.norm2(F.col("mean")) - 2 * cross
    n = F.count("*")
    return joined.agg((F.sum(F.col("n_i") / F.col("b_i") * gap) / (n * n)).alias("bound"))


def lipschitz_x(ex: DataFrame, w: Weights, pairs: int = 4, seed: int = 1) -> DataFrame:
    """One row: the largest ratio of gradient to feature distance among sampled same-class pairs, a lower bound of the constant.

    All pairs would be quadratic.  Each row of ex is compared with the next pairs rows of its class and
    bucket in a random order, so the sample has a share of every row's pairs and grows with the table.
    """
    rows = ex.select("row_id", "y", "x", L.softmax_residual(L.logits(F.col("x"), w), F.col("y")).alias("r"))
    buckets = 1 << (ex.count() // 100_000).bit_length()
    rows = rows.withColumns({"bucket": hash52("bucket", F.col("row_id")) % buckets, "place": hash52("pair", seed, F.col("row_id"))})
    order = Window.partitionBy("y", "bucket").orderBy("place", "row_id")
    ahead = {f"ahead{k}": F.when(F.lead("x", k).over(order).isNotNull(), F.struct(F.lead("x", k).over(order).alias("x2"), F.lead("r", k).over(order).alias("r2"))) for k in range(1, pairs + 1)}
    rows = rows.withColumns(ahead).select("x", "r", F.explode(F.array_compact(F.array(*ahead))).alias("other"))
    pairs = rows.select("x", "r", "other.x2", "other.r2")
    top = L.norm2(F.col("r")) * L.norm2(F.col("x")) + L.norm2(F.col("r2")) * L.norm2(F.col("x2")) - 2 * L.dot(F.col("r"), F.col("r2")) * L.dot(F.col("x"), F.col("x2"))
    bottom = L.norm2(F.zip_with("x", "x2", lambda a, b: a - b))
    return pairs.where(bottom > 1e-12).agg(F.max(F.sqrt(F.greatest(top, F.lit(0.0)) / bottom)).alias("lipschitz"))


def full_gradient(ex: DataFrame, w: Weights, lam: float = 0.0, loss: str = "softmax") -> DataFrame:
    """(cls, component, g): the gradient of the regularised mean loss over all rows of ex."""
    d = len(w[0])
    sums = gradient_sums(ex.withColumn("stratum", F.lit(0)), w, loss)
    cls, component = F.floor(F.col("cell") / d).cast("int"), (F.col("cell") % d).cast("int")
    weights = L.literal(w)
    return sums.select(cls.alias("cls"), component.alias("component"), (F.col("g") / F.col("cnt") + lam * F.get(F.get(weights, cls), component)).alias("g"))


def draw_gradient(fetched: DataFrame, w: Weights, lam: float, keys: list[str]) -> DataFrame:
    """(keys, cls, component, g): the weighted sum over a step's draws, plus the ridge term."""
    r = L.softmax_residual(L.logits(F.col("x"), w), F.col("y"))
    # a row per cell of a draw's gradient, added up before they move: no plan is as wide as the model
    scaled = F.transform(r, lambda v: F.transform("x", lambda u: F.col("draw_weight") * v * u))
    rows = fetched.select(*keys, F.posexplode(scaled).alias("cls", "row")).select(*keys, "cls", F.posexplode("row").alias("component", "g"))
    ridge = lam * F.get(F.get(L.literal(w), F.col("cls")), F.col("component"))
    return rows.groupBy(*keys, "cls", "component").agg(F.sum("g").alias("g")).select(*keys, "cls", "component", (F.col("g") + ridge).alias("g"))


def resampled(fetched: DataFrame, full: DataFrame, w: Weights) -> DataFrame:
    """One row: mean over the steps t of fetched of the squared distance of a step's gradient from the full one."""
    steps = draw_gradient(fetched, w, 0.0, ["t"]).join(F.broadcast(full.select("cls", "component", F.col("g").alias("full"))), ["cls", "component"])
    per_step = steps.groupBy("t").agg(F.sum((F.col("g") - F.col("full")) * (F.col("g") - F.col("full"))).alias("d2"))
    return per_step.agg(F.avg("d2").alias("variance"), (F.stddev_samp("d2") / F.sqrt(F.count("*"))).alias("std_error"))
