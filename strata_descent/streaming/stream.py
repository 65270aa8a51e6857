"""Streaming twins: windowed class statistics, late rows, a stratum reservoir, and online descent."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators import cluster, variance


def class_stats(events: DataFrame, window: F.Column, label: str = "event_type", value: str = "value") -> DataFrame:
    """Mergeable moments per window and class; the same on a batch and on a stream with a watermark."""
    grouped = events.groupBy(window.alias("w"), label)
    return grouped.agg(F.count("*").alias("n_rows"), F.sum(value).alias("sum_value"), F.sum(F.col(value) * F.col(value)).alias("sum_squares")).select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), label, "n_rows", "sum_value", "sum_squares")


def with_late(events: DataFrame, delay: str, ts: str = "ts") -> DataFrame:
    """A stream that waits delay for late rows; later ones are dropped by the windows above it."""
    return events.withWatermark(ts, delay)


def nearby(events: DataFrame, hours: int = 1) -> DataFrame:
    """Interval join: pairs of events of one user at most so many hours apart, by hour slots so that it stays an equi-join."""
    slot = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / F.lit(3_600_000_000 * hours))
    a = events.select("user_id", F.col("event_id").alias("a_id"), F.col("ts").alias("a_ts"), slot.alias("slot"))
    b = events.select("user_id", F.col("event_id").alias("b_id"), F.col("ts").alias("b_ts"), F.explode(F.array(slot, slot - 1)).alias("slot"))
    # b is at or after a, so it lies in a's slot or the next
    within = (F.col("b_ts") > F.col("a_ts")) | ((F.col("b_ts") == F.col("a_ts")) & (F.col("b_id") > F.col("a_id")))
    return a.join(b, ["user_id", "slot"]).where(within & (F.col("b_ts") <= F.col("a_ts") + F.expr(f"interval {hours} hours"))).select("user_id", "a_id", "b_id")


def reservoir(stream: DataFrame, cap: int) -> DataFrame:
    """(stratum, row_id, priority): for each stratum the cap rows of least priority so far, kept as state."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def keep(key, frames: Iterator[pd.DataFrame], state: GroupState):
        ids, priorities = state.get if state.exists else ([], [])
        held = list(zip(priorities, ids, strict=True))
        for f in frames:
            held += list(zip(f["priority"].tolist(), f["row_id"].tolist(), strict=True))
        held = sorted(set(held))[:cap]
        state.update(([i for _, i in held], [p for p, _ in held]))
        yield pd.DataFrame({"stratum": [key[0]] * len(held), "row_id": [i for _, i in held], "priority": [p for p, _ in held]})

    rows = stream.select("stratum", "row_id", "priority")
    return rows.groupBy("stratum").applyInPandasWithState(keep, "stratum int, row_id bigint, priority bigint", "ids array<bigint>, priorities array<bigint>", "update", GroupStateTimeout.NoTimeout)


class OnlineDescent:
    """A foreachBatch sink: one stratified step per micro-batch, strata by the nearest fixed centre of the class.

    A batch's strata weigh by the rows seen so far, so the step is unbiased for those rows, not for a
    fixed population.  A batch that is delivered again is skipped.
    """

    def __init__(self, centres: dict[int, np.ndarray], classes: int, d: int, lam: float, eta: Callable[[int], float]):
        self.centres, self.lam, self.eta = centres, lam, eta
        self.w = np.zeros((classes, d))
        self.seen: dict[int, int] = {}
        self.t, self.last = 0, -1

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        if batch_id <= self.last:
            return
        self.last = batch_id
        most = max(map(len, self.centres.values()))
        centres = [(y * most + i, y, c.tolist(), 0.0) for y, of_class in self.centres.items() for i, c in enumerate(of_class)]
        strata = batch.sparkSession.createDataFrame(centres, "stratum int, y int, mean array<double>, v_i double")
        assigned = cluster.assign(batch.select("row_id", "y", "x"), strata)
        # a row per stratum, class and feature, whatever the batch's size
        self.step([(r.stratum, r.cnt, r.cell, r.g) for r in variance.gradient_sums(assigned, self.w.tolist()).collect()])

    def step(self, sums: list[tuple[int, int, int, float]]) -> None:
        """One step from (stratum, rows, cell, gradient sum) of a batch."""
        here = {s: n for s, n, _, _ in sums}
        if not here:
            return
        for s, n in here.items():
            self.seen[s] = self.seen.get(s, 0) + n
        total, g = sum(self.seen.values()), np.zeros(self.w.size)
        for s, n, cell, value in sorted(sums):
            g[cell] += self.seen[s] / (total * n) * value
        self.t += 1
        self.w = self.w - self.eta(self.t) * (g.reshape(self.w.shape) + self.lam * self.w)
