"""Configurations and the plan of strata that a run draws from."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class DescentConfig:
    lam: float
    b: int
    steps: int
    schedule: str = "inverse"  # inverse, shifted, constant
    eta: float = 0.0
    shift: float = 0.0
    seed: int = 1
    loss: str = "softmax"
    fit_intercept: bool = False
    eval_every: int = 10


@dataclass(frozen=True)
class StrataConfig:
    builder: str = "dispersion"  # by_class, kmeans, dispersion, frozen, random, quantile
    k: int = 0  # 0: one stratum per class
    k_split: str = "equal"  # equal, by_rows, by_rows_times_sigma
    init: str = "quantile"  # quantile, random, plusplus: centres of the first round
    iters: int = 10
    tol: float = 0.0  # rounds end when the bound falls by no more than this share
    eps: float = 1e-6
    restarts: int = 1
    fit_fraction: float = 1.0  # of the rows, by hash, for the rounds; all rows are assigned at the end
    seed: int = 1


@dataclass(frozen=True)
class AllocationConfig:
    kind: str = "dispersion"  # dispersion, proportional, equal
    rounding: str = "greedy"  # greedy, remainder, systematic, none
    seed: int = 1


@dataclass(frozen=True)
class DynamicConfig:
    refresh_every: int = 1
    refresh: str = "both"  # both, counts
    iters: int = 3  # rounds of the gradient strata at each refresh


@dataclass(frozen=True)
class Stratum:
    stratum: int
    y: int
    n_i: int
    v_i: float
    b_i: int


@dataclass(frozen=True)
class StratumPlan:
    """The strata (their number is bounded by b), with draws per step."""

    strata: tuple[Stratum, ...]
    n: int
    b: int
    generation: int = 0

    @staticmethod
    def single(n: int, b: int, v: float = 0.0) -> StratumPlan:
        """One stratum of all rows: uniform minibatches."""
        return StratumPlan((Stratum(0, -1, n, v, b),), n, b)

    @staticmethod
    def from_frame(strata: DataFrame, b: int, classes: int, generation: int = 0) -> StratumPlan:
        rows = strata.select("stratum", "y", "n_i", "v_i", "b_i").orderBy("stratum").limit(b + 1).collect()  # at most b strata are valid
        plan = StratumPlan(tuple(Stratum(r.stratum, r.y, r.n_i, float(r.v_i), int(r.b_i)) for r in rows), sum(r.n_i for r in rows), b, generation)
        plan.check(classes)
        return plan

    def check(self, classes: int) -> None:
        if self.n < 1 or classes < 2:
            raise ValueError("no rows, or fewer than two classes")
        if not classes <= len(self.strata) <= self.b:
            raise ValueError(f"{len(self.strata)} strata; {classes} classes and {self.b} draws need that many at least and at most")
        for s in self.strata:
            if s.n_i < 1 or s.b_i < 1:
                raise ValueError(f"stratum {s.stratum} has {s.n_i} rows and {s.b_i} draws")
        if sum(s.b_i for s in self.strata) != self.b:
            raise ValueError(f"draws add up to {sum(s.b_i for s in self.strata)}, not {self.b}")

    def frame(self, spark) -> DataFrame:
        rows = [(s.stratum, s.n_i, s.b_i, s.n_i / (self.n * s.b_i)) for s in self.strata]
        return F.broadcast(spark.createDataFrame(rows, "stratum int, n_i bigint, b_i int, draw_weight double"))
