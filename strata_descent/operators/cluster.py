"""Strata: partitions of the training rows into single-class clusters.

One job moves all classes: a row is compared with the centres of its own class only, which go to the
tasks with the function that places Arrow batches (at most b centres in all).
"""

from __future__ import annotations

import math
from decimal import ROUND_HALF_UP, Decimal

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.loss import arrays, norm2
from ..functions.rng import hash52, unit
from ..plans.plan import StrataConfig

RULES = {
    "euclid": lambda dist, sigma: dist,
    "frozen": lambda dist, sigma: dist / sigma,
    # tangent of the concave sum of n * sigma: rows move to where the bound falls most, so the sum cannot rise
    "dispersion": lambda dist, sigma: dist / sigma + sigma,
}


def train_rows(ex: DataFrame) -> DataFrame:
    return ex.where("split = 'train'").select("row_id", "y", "x")


def by_class(ex: DataFrame) -> DataFrame:
    return ex.withColumn("stratum", F.col("y"))


#: Views wider than this send partial sums per partition instead of two aggregates per feature.
WIDE = 32


def stats(assigned: DataFrame, d: int) -> DataFrame:
    """(stratum, y, n_i, mean, v_i): v_i is the mean squared distance from the mean, by stable moments."""
    if d > WIDE:
        return wide_stats(assigned, d)
    mean = F.array(*(F.avg(F.col("x")[j]) for j in range(d)))
    spread = sum((F.var_pop(F.col("x")[j]) for j in range(1, d)), F.var_pop(F.col("x")[0]))
    return assigned.groupBy("stratum").agg(F.min("y").alias("y"), F.count("*").alias("n_i"), mean.alias("mean"), spread.alias("v_i"))


def wide_stats(assigned: DataFrame, d: int) -> DataFrame:
    """stats() of many features: each partition sends a row per stratum, with its mean and squared distances from that."""

    def partial(batches):
        state: dict[int, list] = {}
        for batch in batches:
            y, x = arrays(batch, d)
            stratum = batch.column(batch.schema.get_field_index("stratum")).to_numpy(zero_copy_only=False)
            for s in np.unique(stratum):
                rows = x[stratum == s]
                n, mean = len(rows), rows.mean(axis=0)
                have = state.setdefault(int(s), [int(y[stratum == s].min()), 0, np.zeros(d), 0.0])
                gap, total = mean - have[2], have[1] + n
                have[3] += float(((rows - mean) ** 2).sum()) + float((gap * gap).sum()) * have[1] * n / total
                have[2], have[1], have[0] = have[2] + gap * n / total, total, min(have[0], int(y[stratum == s].min()))
        keys = list(state)
        yield pa.RecordBatch.from_arrays(
            [pa.array(keys, pa.int32()), pa.array([state[k][0] for k in keys], pa.int32()), pa.array([state[k][1] for k in keys], pa.int64()), pa.array([state[k][2].tolist() for k in keys], pa.list_(pa.float64())), pa.array([state[k][3] for k in keys], pa.float64())],
            ["stratum", "y", "n", "mean", "ss"],
        )

    parts = assigned.select(F.col("stratum").cast("int").alias("stratum"), "y", "x").mapInArrow(partial, "stratum int, y int, n bigint, mean array<double>, ss double")

    def merged(rows: pa.Table) -> pa.Table:  # a row per partition
        n, means = rows["n"].to_numpy(), np.array(rows["mean"].to_pylist())
        order = np.lexsort((rows["ss"].to_numpy(), n, means[:, 0]))
        n, means, ss = n[order], means[order], rows["ss"].to_numpy()[order]
        mean = (n[:, None] * means).sum(axis=0) / n.sum()
        v = (ss.sum() + (n * ((means - mean) ** 2).sum(axis=1)).sum()) / n.sum()
        return pa.table({"stratum": rows["stratum"][:1], "y": pa.array([min(rows["y"].to_pylist())], pa.int32()), "n_i": pa.array([int(n.sum())], pa.int64()), "mean": pa.array([mean.tolist()], pa.list_(pa.float64())), "v_i": pa.array([float(v)])})

    return parts.groupBy("stratum").applyInArrow(merged, "stratum int, y int, n_i bigint, mean array<double>, v_i double")


def dispersion_objective(strata: DataFrame) -> DataFrame:
    """One row: the sum of n_i * sqrt(v_i)."""
    return strata.agg(F.sum(F.col("n_i") * F.sqrt("v_i")).alias("objective"))


def class_counts(k: int, rows: dict[int, int], sigma: dict[int, float] | None = None, how: str = "equal") -> dict[int, int]:
    """Strata per class: one each, the rest by largest remainder of the weights; never more than rows."""
    weight = {y: 1.0 if how == "equal" else float(n) * (sigma[y] if how == "by_rows_times_sigma" and sigma else 1.0) for y, n in rows.items()}
    total = sum(weight.values()) or 1.0
    spare = max(0, k - len(rows))
    share = {y: spare * w / total for y, w in weight.items()}
    out = {y: 1 + math.floor(share[y]) for y in rows}
    for y in sorted(rows, key=lambda y: (math.floor(share[y]) - share[y], y))[: max(0, k - sum(out.values()))]:
        out[y] += 1
    surplus = sum(max(0, out[y] - rows[y]) for y in rows)
    out = {y: min(out[y], rows[y]) for y in rows}
    for y in sorted(rows):
        more = min(surplus, rows[y] - out[y])
        out[y] += more
        surplus -= more
    return out


def quantile_strata(ex: DataFrame, per_class: dict[int, int] | int, axis: int = 0) -> DataFrame:
    """Bins of equal size along one feature within each class; exact ranks, for samples and small tables."""
    order = Window.partitionBy("y").orderBy(F.col("x")[axis], "row_id")
    bins = F.lit(per_class) if isinstance(per_class, int) else F.element_at(F.create_map(*(F.lit(v) for kv in sorted(per_class.items()) for v in kv)), F.col("y"))
    most = per_class if isinstance(per_class, int) else max(per_class.values())
    ranked = ex.withColumns({"rank_": F.row_number().over(order) - 1, "rows_": F.count("*").over(Window.partitionBy("y"))})
    # the first rows % bins bins have one row more, as ntile deals them
    big, size = F.col("rows_") % bins, F.floor(F.col("rows_") / bins)
    bin_ = F.when(F.col("rank_") < big * (size + 1), F.floor(F.col("rank_") / (size + 1))).otherwise(big + F.floor((F.col("rank_") - big * (size + 1)) / F.greatest(size, F.lit(1))))
    return ex.sparkSession.createDataFrame([], ex.schema).withColumn("stratum", F.lit(0)) if most < 1 else ranked.withColumn("stratum", (F.col("y") * most + bin_).cast("int")).drop("rank_", "rows_")


def random_strata(ex: DataFrame, per_class: int, seed: int = 1) -> DataFrame:
    return ex.withColumn("stratum", (F.col("y") * per_class + hash52("strata", seed, F.col("row_id")) % per_class).cast("int"))


def _least(cost: np.ndarray) -> np.ndarray:
    """The row of least cost in each column, of costs to 9 places (half up in decimals), the first among equals."""
    cost = np.where(np.isnan(cost), np.inf, cost)
    best, low = cost.argmin(axis=0), cost.min(axis=0)
    gap = cost - np.where(np.isinf(low), 0.0, low)
    for i in np.flatnonzero(((gap > 0) & (gap <= 2e-9)).any(axis=0)):  # only there can the places matter
        near = np.flatnonzero(gap[:, i] <= 2e-9)
        best[i] = min(near, key=lambda k: (Decimal(repr(float(cost[k, i]))).quantize(Decimal("1e-9"), ROUND_HALF_UP), k))
    return best


def assign(ex: DataFrame, strata: DataFrame, rule: str = "euclid", eps: float = 1e-6) -> DataFrame:
    """ex with the stratum of its class that the rule likes best; costs to 9 places, ties to the lowest id."""
    of_class: dict[int, list] = {}
    for r in strata.select("y", "stratum", "mean", F.sqrt(F.col("v_i") + eps).alias("sigma")).collect():  # at most b in all
        of_class.setdefault(r.y, []).append((r.stratum, r.mean, r.sigma))
    centres = {}
    for y, own in of_class.items():
        ids, means, sigmas = zip(*sorted(own, key=lambda c: c[0]), strict=True)
        centres[y] = (np.array(ids, dtype=np.int32), np.array(means, dtype=float), np.array(sigmas, dtype=float))
    d = next((means.shape[1] for _, means, _ in centres.values()), 1)
    score = RULES[rule]

    def place(batches):
        for batch in batches:
            if not centres or not batch.num_rows:
                continue
            y, x = arrays(batch, d)
            stratum, known = np.zeros(len(y), dtype=np.int32), np.zeros(len(y), dtype=bool)
            for c, (ids, means, sigmas) in centres.items():
                mine = y == c
                rows = np.ascontiguousarray(x[mine].T)
                if not rows.shape[1]:
                    continue
                cost = np.empty((len(ids), rows.shape[1]))
                for k in range(len(ids)):
                    dist = np.zeros(rows.shape[1])
                    for j in range(d):
                        gap = rows[j] - means[k, j]
                        dist += gap * gap
                    cost[k] = score(dist + eps if rule != "euclid" else dist, sigmas[k])
                stratum[mine], known[mine] = ids[_least(cost)], True
            out = pa.RecordBatch.from_arrays([*batch.columns, pa.array(stratum)], ["row_id", "y", "x", "stratum"])
            yield out if known.all() else out.filter(pa.array(known))

    rows = ex.select("row_id", "y", "x")
    return rows.mapInArrow(place, ", ".join(f"{c} {t}" for c, t in rows.dtypes) + ", stratum int")


def approximate_quantile_strata(rows: DataFrame, per_class: dict[int, int], axis: int = 0) -> DataFrame:
    """Bins along one feature within each class, cut at approximate quantiles: one aggregate and a projection, no window.

    A class of few different values may fill fewer bins than it has.
    """
    most = max(per_class.values(), default=1)
    if most < 2:
        return rows.withColumn("stratum", (F.col("y") * most).cast("int"))
    sizes = sorted(set(per_class.values()))  # bins of a class; few different numbers
    bounds = rows.groupBy("y").agg(*(F.percentile_approx(F.col("x")[axis], [i / k for i in range(1, k)] or [0.5], 10_000).alias(f"by_{k}") for k in sizes))
    wanted = F.element_at(F.create_map(*(F.lit(v) for kv in sorted(per_class.items()) for v in kv)), F.col("y"))
    cuts = F.array().cast("array<double>")
    for k in sizes:
        cuts = F.when(wanted == k, F.col(f"by_{k}") if k > 1 else F.array().cast("array<double>")).otherwise(cuts)
    bounds = bounds.select("y", cuts.alias("cuts"))
    placed = rows.join(F.broadcast(bounds), "y")  # a row per class
    bin_ = F.size(F.filter(F.array_distinct("cuts"), lambda c: c < F.col("x")[axis]))
    return placed.select("row_id", "y", "x", (F.col("y") * most + bin_).cast("int").alias("stratum"))


def first_centres(rows: DataFrame, per_class: dict[int, int], init: str, seed: int) -> DataFrame:
    """(stratum, y, mean, v_i) of single rows as centres: random ones, or each far from those before it (plusplus), by hash.

    A centre of plusplus is drawn with chance in proportion to the squared distance from the nearest one
    so far: the row of largest log distance plus Gumbel variate, one aggregate per centre.
    """
    most = max(per_class.values())
    wanted = F.element_at(F.create_map(*(F.lit(v) for kv in sorted(per_class.items()) for v in kv)), F.col("y"))
    gumbel = lambda j: -F.log(-F.log(unit("start", seed, j, F.col("row_id")) + F.lit(1e-16)))
    if init == "random":
        place = F.row_number().over(Window.partitionBy("y").orderBy(hash52("start", seed, F.col("row_id")), "row_id"))
        few = rows.withColumn("place", place).where((F.col("place") <= most) & (F.col("place") <= wanted))  # each task sends that many
        return few.select((F.col("y") * most + F.col("place") - 1).cast("int").alias("stratum"), "y", F.col("x").alias("mean"), F.lit(0.0).alias("v_i"))
    if init != "plusplus":
        raise ValueError(f"unknown start {init!r}")
    spark, found, schema = rows.sparkSession, [], "stratum int, y int, mean array<double>, v_i double"
    for j in range(most):
        some = rows.where(wanted > j)
        if found:
            centres = spark.createDataFrame(found, schema).groupBy("y").agg(F.collect_list("mean").alias("centres"))  # at most b in all
            some = some.join(F.broadcast(centres), "y")
            near = F.array_min(F.transform("centres", lambda c: norm2(F.zip_with("x", c, lambda a, b: a - b))))
            some = some.withColumn("weight", F.log(near)).where(near > 0)
        else:
            some = some.withColumn("weight", F.lit(0.0))
        drawn = some.groupBy("y").agg(F.max_by(F.struct("row_id", "x"), F.struct(F.round(F.col("weight") + gumbel(j), 9), F.col("row_id"))).alias("r"))
        found += [(r.y * most + j, r.y, r.r.x, 0.0) for r in drawn.collect()]  # a row per class
    return spark.createDataFrame(found, schema)


def reseeded(assigned: DataFrame, strata: DataFrame, per_class: dict[int, int]) -> DataFrame:
    """strata, with as many as each class should have: lost ones start again at the rows farthest from their stratum's mean.

    Splitting a stratum cannot raise the sum of n_i sigma_i, so this never makes a later optimum worse.
    """
    have = {r.y: set(r.ids) for r in strata.groupBy("y").agg(F.collect_set("stratum").alias("ids")).collect()}  # at most b ids
    most = max(per_class.values())
    free = {y: [s for s in range(y * most, y * most + k) if s not in have.get(y, set())][: max(0, k - len(have.get(y, set())))] for y, k in per_class.items()}
    if not any(free.values()):
        return strata
    far = farthest(assigned, strata, max(map(len, free.values()))).where("dist > 0")
    ids = assigned.sparkSession.createDataFrame([(y, i + 1, s) for y, ids in free.items() for i, s in enumerate(ids)], "y int, place int, stratum int")
    rows = far.join(F.broadcast(ids), ["y", "place"]).join(assigned.select("row_id", "x"), "row_id")
    return strata.unionByName(rows.select("stratum", "y", F.lit(1).cast("bigint").alias("n_i"), F.col("x").alias("mean"), F.lit(0.0).alias("v_i")))


def rounds(start: DataFrame, d: int, n: int, rule: str, eps: float = 1e-6, save=None, per_class: dict[int, int] | None = None, tol: float = 0.0) -> DataFrame:
    """n rounds of statistics and assignment from start; save, if given, cuts the lineage of each round.

    With per_class, empty strata are seeded again; with tol, rounds end when the sum of n_i sigma_i falls
    by no more than that share.
    """
    assigned, last = start, None
    for _ in range(n):
        strata = stats(assigned, d)
        strata = save(strata) if save else strata
        if tol > 0:
            value = dispersion_objective(strata).first()[0]
            if last is not None and last - value <= tol * last:
                break
            last = value
        if per_class:
            strata = reseeded(assigned, strata, per_class)
        assigned = assign(assigned, strata, rule, eps)
        assigned = save(assigned) if save else assigned
    return assigned


def build(ex: DataFrame, d: int, config: StrataConfig, save=None) -> DataFrame:
    """Training rows with their strata by config's builder; the run of lowest objective over the restarts."""
    rows = train_rows(ex)
    if config.builder == "by_class" or not config.k:
        return by_class(rows)
    of_class = {r.y: (r.n_i, math.sqrt(r.v_i or 0.0)) for r in stats(by_class(rows), d).collect()}  # a row per class
    per_class = class_counts(config.k, {y: n for y, (n, _) in of_class.items()}, {y: s for y, (_, s) in of_class.items()}, config.k_split)
    if config.builder == "random":
        return random_strata(rows, max(per_class.values()), config.seed)
    if config.builder == "quantile":
        return approximate_quantile_strata(rows, per_class)
    sample = rows.where(unit("fit", config.seed, F.col("row_id")) < config.fit_fraction) if config.fit_fraction < 1 else rows
    if save and config.fit_fraction < 1:
        sample = save(sample)  # all rows are hashed once, not by each start's quantiles and placing
    rule = {"kmeans": "euclid", "dispersion": "dispersion", "frozen": "frozen"}[config.builder]
    best = None
    for restart in range(max(1, config.restarts)):
        if config.init == "quantile":
            start = approximate_quantile_strata(sample, per_class, axis=restart % d)
        else:
            start = assign(sample, first_centres(sample, per_class, config.init, config.seed + restart), "euclid", config.eps)
        fitted = rounds(save(start) if save else start, d, config.iters, rule, config.eps, save, per_class, config.tol)
        strata = stats(fitted, d)
        strata = save(strata) if save else strata
        value = dispersion_objective(strata).first()[0]
        if best is None or value < best[0] - 1e-12:
            best = (value, strata)
    assigned = assign(rows, best[1], rule, config.eps)
    return save(assigned) if save else assigned


def validate(assigned: DataFrame, rows: DataFrame | None = None, strata: DataFrame | None = None) -> DataFrame:
    """(check, stratum, n): what is wrong with strata that should be disjoint, cover rows, hold one class each and count their rows.

    mixed: classes of a stratum of several; unplaced: rows without a stratum; repeated: row ids in more than
    one place; missing, foreign: ids that only rows, or only assigned, has; miscounted: rows of a stratum
    whose n_i in strata is another, or that strata does not have, or that has no rows.  Nothing for valid strata.
    """
    seen = assigned.groupBy("stratum").agg(F.count("*").alias("n_rows"), F.countDistinct("y").alias("n_classes"))
    none = F.lit(None).cast("int")
    out = seen.where("stratum is not null and n_classes > 1").select(F.lit("mixed").alias("check"), F.col("stratum").cast("int").alias("stratum"), F.col("n_classes").alias("n"))
    out = out.unionByName(seen.where("stratum is null").select(F.lit("unplaced").alias("check"), none.alias("stratum"), F.col("n_rows").alias("n")))
    total = lambda df, name: df.agg(F.count("*").alias("n")).where("n > 0").select(F.lit(name).alias("check"), none.alias("stratum"), "n")
    out = out.unionByName(total(assigned.groupBy("row_id").count().where("count > 1"), "repeated"))
    if rows is not None:
        out = out.unionByName(total(rows.join(assigned, "row_id", "left_anti"), "missing")).unionByName(total(assigned.join(rows, "row_id", "left_anti"), "foreign"))
    if strata is not None:
        both = seen.where("stratum is not null").join(strata.select("stratum", "n_i"), "stratum", "full").where("not n_rows <=> n_i")
        out = out.unionByName(both.select(F.lit("miscounted").alias("check"), F.col("stratum").cast("int").alias("stratum"), F.coalesce("n_rows", F.lit(0)).alias("n")))
    return out


def farthest(assigned: DataFrame, strata: DataFrame, k: int) -> DataFrame:
    """The k rows of each class that lie farthest from their stratum's mean."""
    joined = assigned.join(F.broadcast(strata.select("stratum", "mean")), "stratum")
    joined = joined.withColumn("dist", F.round(norm2(F.zip_with("x", "mean", lambda a, b: a - b)), 9))
    place = F.row_number().over(Window.partitionBy("y").orderBy(F.desc("dist"), "row_id"))
    return joined.withColumn("place", place).where(F.col("place") <= k).select("y", "place", "row_id", "dist")
