"""Draws with replacement, computed from counters, and their rows."""

from __future__ import annotations

import math
from itertools import accumulate

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.rng import hash52, unit
from ..plans.plan import Stratum, StratumPlan
from . import index

#: A chunk of at most so many draws may be broadcast to the rows.
BROADCAST_DRAWS = 500_000


def in_order(plan: StratumPlan) -> list[Stratum]:
    """The strata as a step's draws are folded."""
    return sorted(plan.strata, key=lambda s: s.stratum)


def plan_runs(spark: SparkSession, runs: list[tuple[str, StratumPlan, int, int]], first: int, last: int) -> DataFrame:
    """run_id, t, stratum, r, pos, draw_weight, slot of steps first to last for all runs (name, plan, seed, last step): a bag, one row per draw.

    slot numbers the draws of a step from 0, by stratum and r.
    """
    rows = []
    for name, plan, seed, end in runs:
        before = 0
        for s in in_order(plan):
            rows.append((name, str(seed), end, s.stratum, s.n_i, s.b_i, s.n_i / (plan.n * s.b_i), before))
            before += s.b_i
    strata = F.broadcast(spark.createDataFrame(rows, "run_id string, seed string, end int, stratum int, n_i bigint, b_i int, draw_weight double, before int"))  # runs times strata
    steps = spark.range(first, last + 1).select(F.col("id").cast("int").alias("t"))
    each = steps.crossJoin(strata).where("t <= end").withColumn("r", F.explode(F.sequence(F.lit(1), "b_i")))
    pos = hash52(F.col("seed"), F.col("t"), F.col("stratum"), F.col("r")) % F.col("n_i")
    return each.select("run_id", "t", "stratum", "r", pos.alias("pos"), "draw_weight", (F.col("before") + F.col("r") - 1).alias("slot"))


def plan_chunk(spark: SparkSession, plan: StratumPlan, seed: int, first: int, last: int, run: str = "run") -> DataFrame:
    """plan_runs of a single run."""
    return plan_runs(spark, [(run, plan, seed, last)], first, last)


def fetch(draws: DataFrame, indexed: DataFrame, how: str = "auto", n_draws: int | None = None) -> DataFrame:
    """The rows of the draws, repeats included; an inner join on the position, and on its block where the index is written by blocks."""
    keys = ["stratum", "pos"]
    if "block" in indexed.columns:
        keys.append("block")
        # Spark prunes folders only by a side that it takes for filtered
        draws = draws.where("pos >= 0").withColumn("block", F.floor(F.col("pos") / index.BLOCK_ROWS).cast("bigint"))
    rows = indexed.select(*keys, "row_id", "y", "x")
    if how in ("merge", "shuffle_hash"):
        return draws.join(rows.hint(how), keys)
    small = how == "broadcast" or (n_draws is not None and n_draws <= BROADCAST_DRAWS)
    return (F.broadcast(draws) if small else draws).join(rows, keys)


def ever_drawn(indexed: DataFrame, draws: DataFrame) -> DataFrame:
    return indexed.join(draws, ["stratum", "pos"], "left_semi")


def never_drawn(indexed: DataFrame, draws: DataFrame) -> DataFrame:
    return indexed.join(draws, ["stratum", "pos"], "left_anti")


def overlap(a: DataFrame, b: DataFrame) -> DataFrame:
    """Distinct (t, stratum, pos) that both draw."""
    c = ["t", "stratum", "pos"]
    return a.select(*c).intersect(b.select(*c))


def bernoulli(assigned: DataFrame, fractions: dict[int, float], seed: int = 1) -> DataFrame:
    """Each row with its stratum's chance, by a hash, so the same rows wherever they are; strata without a chance give none."""
    chance = F.coalesce(F.try_element_at(F.create_map(*(F.lit(v) for kv in sorted(fractions.items()) for v in kv)), F.col("stratum")), F.lit(0.0))
    return assigned.where(unit("bernoulli", seed, F.col("row_id")) < chance)


def by_scan(assigned: DataFrame, plan: StratumPlan, seed: int, first: int, last: int, most: int = 32) -> DataFrame:
    """Approximate draws of steps first to last without positions: each row falls into a Poisson number of draws.

    A stratum's draws in a step are then b_i on average only, so a draw weighs by how many there were; a
    step that hits no row of some stratum has no draw of it.  Counts come from the row's hash by inverting
    the distribution, up to most draws of a row.
    """
    steps = last - first + 1
    rows = []
    for s in plan.strata:
        rate = s.b_i * steps / s.n_i
        rows.append((s.stratum, s.n_i, list(accumulate(math.exp(-rate + k * math.log(rate) - math.lgamma(k + 1)) for k in range(most)))))
    chances = F.broadcast(assigned.sparkSession.createDataFrame(rows, "stratum int, n_i bigint, chances array<double>"))
    counted = assigned.join(chances, "stratum").withColumn("u", unit("poisson", seed, first, F.col("row_id")))
    counted = counted.withColumn("times", F.size(F.filter("chances", lambda c: c <= F.col("u")))).where("times > 0")
    each = counted.select("stratum", "n_i", "row_id", "y", "x", F.explode(F.sequence(F.lit(1), F.col("times"))).alias("k"))
    each = each.withColumn("t", (first + hash52("step", seed, first, F.col("row_id"), F.col("k")) % steps).cast("int"))
    drawn = each.groupBy("t", "stratum").agg(F.count("*").alias("drawn"))  # steps times strata rows
    return each.join(F.broadcast(drawn), ["t", "stratum"]).select("t", "stratum", "row_id", "k", "y", "x", (F.col("n_i") / (F.lit(plan.n) * F.col("drawn"))).alias("draw_weight"))


def without_replacement(indexed: DataFrame, plan: StratumPlan, seed: int, t: int) -> DataFrame:
    """For one step, the b_i rows of least hash in each stratum."""
    order = Window.partitionBy("stratum").orderBy(hash52(seed, t, F.col("stratum"), F.col("row_id")), "row_id")
    picked = indexed.join(plan.frame(indexed.sparkSession), "stratum").withColumn("r", F.row_number().over(order)).where("r <= b_i")
    return picked.withColumn("t", F.lit(t)).select("t", "stratum", "r", "pos", "row_id", "y", "x", "draw_weight")
