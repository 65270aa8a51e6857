"""Gradient descent: full, single-example, uniform minibatch, stratified with fixed and with dynamic strata.

A chunk of steps is drawn and fetched by one join for all runs on the same index (all seeds of a sampler);
each run then folds its steps in order in one task (a run is a chain of tiny updates), which reads its sorted draws as a stream, and
runs go side by side.  Between chunks the driver carries one matrix per run.  Full passes send one partial sum per partition.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import loss as L
from ..functions import schedule as S
from ..plans.plan import AllocationConfig, DescentConfig, DynamicConfig, StrataConfig, StratumPlan
from ..sources.load import short_lived
from . import allocate, cluster, index, sampling, variance

#: Drawn rows that one chunk fetches for one run, at least.
CHUNK_ROWS = 200_000
MODELS = "run_id string, t int, cls int, w array<double>"


def schedule_of(config: DescentConfig) -> S.Schedule:
    return {"inverse": lambda: S.inverse(config.lam), "shifted": lambda: S.shifted_inverse(config.shift, config.lam), "constant": lambda: S.constant(config.eta)}[config.schedule]()


@dataclass
class Run:
    """One chain: its rows by position, its plan, and its state."""

    name: str
    indexed: DataFrame
    plan: StratumPlan
    config: DescentConfig
    w: np.ndarray
    sampler: str = "stratified"
    tags: dict = field(default_factory=dict)


class _Chain:
    """A run's steps from its draws, fed in order; the draws of a step may come in pieces."""

    def __init__(self, name: str, w: np.ndarray, config: DescentConfig, weights: np.ndarray, keep_all: bool):
        self.name, self.w, self.config, self.weights, self.keep_all = name, w, config, weights, keep_all
        self.kernel, self.step, self.eye = L.get(config.loss), schedule_of(config), np.eye(len(w))
        self.rest, self.now, self.kept = None, 0, []

    def feed(self, at: np.ndarray, y: np.ndarray, x: np.ndarray, end: bool = False) -> None:
        if self.rest is not None:
            at, y, x = (np.concatenate(pair) for pair in zip(self.rest, (at, y, x), strict=True))
        t, slot = np.divmod(at, len(self.weights))
        edges = np.append(np.flatnonzero(np.diff(t, prepend=t[:1] - 1)), len(t)).tolist()
        if not end:  # the last step may go on in the next piece
            self.rest = (at[edges[-2] :], y[edges[-2] :], x[edges[-2] :])
            edges.pop()
        if len(edges) < 2:
            return
        onehot, weight = self.eye[y], self.weights[slot][:, None]
        w, lam, every, steps, residual = self.w, self.config.lam, self.config.eval_every, t[edges[:-1]].tolist(), self.kernel.residual_of
        for now, a, z in zip(steps, edges[:-1], edges[1:], strict=True):
            rows = x[a:z]
            w = w - self.step.at(now) * ((residual(rows @ w.T, onehot[a:z]) * weight[a:z]).T @ rows + lam * w)
            if self.keep_all or now % every == 0:
                self.kept.append((now, w))
        self.w, self.now = w, steps[-1]

    def models(self) -> pa.RecordBatch:
        """What is kept, and the last model."""
        self.feed(*(c[:0] for c in self.rest), end=True)
        kept = self.kept if self.kept and self.kept[-1][0] == self.now else [*self.kept, (self.now, self.w)]
        m = len(self.w)
        flat = [row.tolist() for _, w in kept for row in w]
        return pa.RecordBatch.from_arrays([pa.array([self.name] * len(flat)), pa.array(np.repeat([t for t, _ in kept], m).astype(np.int32)), pa.array(np.tile(np.arange(m), len(kept)).astype(np.int32)), pa.array(flat, pa.list_(pa.float64()))], ["run_id", "t", "cls", "w"])


def _fold(runs: list[tuple[str, np.ndarray, DescentConfig, np.ndarray]], keep_all: bool):
    """Rows (run, at, y, x), sorted, to the models of their runs: a batch at a time is in memory."""

    def fold(batches):
        chain, of = None, -1
        for batch in batches:
            run, at, y = (batch.column(i).to_numpy() for i in range(3))
            flat = batch.column(3).flatten().to_numpy()
            edges = np.append(np.flatnonzero(np.diff(run, prepend=run[:1] - 1)), len(run))
            for a, z in zip(edges[:-1], edges[1:], strict=True):
                if run[a] != of:
                    if chain:
                        yield chain.models()
                    of = int(run[a])
                    chain = _Chain(*runs[of], keep_all)
                d = chain.w.shape[1]
                chain.feed(at[a:z], y[a:z], flat.reshape(-1, d)[a:z])
        if chain:
            yield chain.models()

    return fold


def chunk_rows(plan: StratumPlan, steps: int, runs: int) -> int:
    """Draws of a chunk for each of the runs on an index: where they are too many to broadcast, together as many as rows at least, as each chunk then moves the rows once."""
    return CHUNK_ROWS if steps * plan.b * runs <= sampling.BROADCAST_DRAWS else max(CHUNK_ROWS, plan.n // runs)


def run_chains(runs: list[Run], keep_all: bool = False) -> DataFrame:
    """The models of all runs at every eval_every-th step, the last step and, with keep_all, every step."""
    spark: SparkSession = runs[0].indexed.sparkSession
    steps, width = max(r.config.steps for r in runs), max(r.plan.b for r in runs)
    shared: dict[int, list[int]] = {}
    for i, r in enumerate(runs):
        shared.setdefault(id(r.indexed), []).append(i)
    size = max(1, max(chunk_rows(runs[group[0]].plan, steps, len(group)) for group in shared.values()) // width)
    state = [r.w for r in runs]
    weights = [np.resize([s.n_i / (r.plan.n * s.b_i) for s in sampling.in_order(r.plan) for _ in range(s.b_i)], width) for r in runs]
    place = {r.name: i for i, r in enumerate(runs)}
    parts = []
    for first in range(1, steps + 1, size):
        last = min(first + size - 1, steps)
        drawn = None
        for group in shared.values():
            live = [(i, runs[i]) for i in group if first <= runs[i].config.steps]
            if live:
                plans = sampling.plan_runs(spark, [(str(i), r.plan, r.config.seed, min(last, r.config.steps)) for i, r in live], first, last)
                # a run and a place in it are two numbers: all that moves beside the rows
                plans = plans.select(F.col("run_id").cast("int").alias("run"), (F.col("t").cast("bigint") * width + F.col("slot")).alias("at"), "stratum", "pos")
                got = sampling.fetch(plans, live[0][1].indexed, n_draws=sum((min(last, r.config.steps) - first + 1) * r.plan.b for _, r in live)).select("run", "at", "y", "x")
                drawn = got if drawn is None else drawn.unionByName(got)
        now = [(r.name, w, r.config, v) for r, w, v in zip(runs, state, weights, strict=True)]
        with short_lived(spark):
            # a task per run; a few matrices per run come back: the state of the next chunk
            rows = drawn.repartitionById(len(runs), F.col("run")).sortWithinPartitions("run", "at").mapInArrow(_fold(now, keep_all), MODELS).collect()
        ends: dict[str, int] = {}
        for row in rows:
            ends[row.run_id] = max(ends.get(row.run_id, 0), row.t)
            config = runs[place[row.run_id]].config
            if keep_all or row.t % config.eval_every == 0 or row.t == config.steps:
                parts.append(row)
        last_rows: dict[str, list] = {}
        for row in rows:
            if row.t == ends[row.run_id]:
                last_rows.setdefault(row.run_id, []).append(row)
        for name, found in last_rows.items():
            state[place[name]] = np.array([row.w for row in sorted(found, key=lambda x: x.cls)])
    return spark.createDataFrame(parts, MODELS)


def by_step(drawn: DataFrame, d: int) -> dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(x, y, weight) of each step of some draws that the driver folds itself, in the order of strata and draws."""
    rows = drawn.select("t", "stratum", "r", "y", "x", "draw_weight").toArrow().sort_by([("t", "ascending"), ("stratum", "ascending"), ("r", "ascending")])
    t, y, weight = (rows[c].to_numpy() for c in ("t", "y", "draw_weight"))
    x = rows["x"].combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(-1, d)
    edges = np.append(np.flatnonzero(np.diff(t, prepend=t[:1] - 1)), len(t))
    return {int(t[a]): (x[a:z], y[a:z], weight[a:z]) for a, z in zip(edges[:-1], edges[1:], strict=True)}


def indexed_uniform(ex: DataFrame) -> DataFrame:
    return index.dense_position(cluster.train_rows(ex).withColumn("stratum", F.lit(0)))


def prepare(ex: DataFrame, d: int, classes: int, b: int, strata: StrataConfig, allocation: AllocationConfig, save=None) -> tuple[DataFrame, DataFrame, StratumPlan]:
    """(assigned, strata with b_i, plan) of the fixed strategy."""
    assigned = cluster.build(ex, d, strata, save)
    frame = allocate.allocate(cluster.stats(assigned, d), b, allocation.kind, allocation.rounding, allocation.seed)
    frame = save(frame) if save else frame
    return assigned, frame, StratumPlan.from_frame(frame, b, classes)


def full_gradient_descent(ex: DataFrame, w: np.ndarray, config: DescentConfig, averaged: bool = False) -> list[np.ndarray]:
    """All iterates after the start; one pass and one matrix to the driver per step."""
    out, step = [], schedule_of(config)
    rows = cluster.train_rows(ex)
    for t in range(1, config.steps + 1):
        g = np.zeros_like(w)
        for r in variance.full_gradient(rows, w.tolist(), config.lam, config.loss).collect():
            g[r.cls, r.component] = r.g
        w = w - step.at(t) * g
        out.append(w)
    return out


def gradient_strata(assigned: DataFrame, w: np.ndarray, iters: int = 3, eps: float = 1e-9, loss: str = "softmax", save=None) -> DataFrame:
    """Strata moved by the dispersion rule on the gradients at w, inside each class; save cuts the lineage of each round.

    |r x^T - G|^2 = |r|^2 |x|^2 - 2 r^T G x + |G|^2, so no gradient is ever written out.
    """
    m, d = w.shape
    kernel = L.get(loss)
    schema = "row_id bigint, y int, x array<double>, stratum int"
    for _ in range(iters):
        sums = variance.gradient_sums(assigned, w.tolist(), loss)
        rows = sums.collect()  # strata times one matrix
        of_class = {r.stratum: r.y for r in assigned.groupBy("stratum").agg(F.first("y").alias("y")).collect()}
        ids = sorted({r.stratum for r in rows})
        at = {s: i for i, s in enumerate(ids)}
        g, n, q = np.zeros((len(ids), m * d)), np.zeros(len(ids)), np.zeros(len(ids))
        for r in rows:
            g[at[r.stratum], r.cell], n[at[r.stratum]], q[at[r.stratum]] = r.g, r.cnt, r.squares
        g /= n[:, None]
        norm = (g * g).sum(axis=1)
        sigma = np.sqrt(np.maximum(q / n - norm, 0) + eps)
        classes = np.array([of_class[s] for s in ids])

        def move(batches, ids=np.array(ids), g=g.reshape(-1, m, d), norm=norm, sigma=sigma, classes=classes):
            for batch in batches:
                y, x = variance.arrays(batch, d)
                r = kernel.residual(x @ w.T, y)
                cost = ((r * r).sum(1) * (x * x).sum(1))[:, None] - 2 * np.einsum("nm,kmd,nd->nk", r, g, x) + norm[None, :] + eps
                cost = np.round(cost / sigma + sigma, 9)
                cost[y[:, None] != classes[None, :]] = np.inf
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), batch.column(2), pa.array(ids[cost.argmin(axis=1)].astype(np.int32))], ["row_id", "y", "x", "stratum"])

        assigned = assigned.select("row_id", "y", "x", F.col("stratum").cast("int").alias("stratum")).mapInArrow(move, schema)
        assigned = save(assigned) if save else assigned
    return assigned


def dynamic(ex: DataFrame, d: int, classes: int, config: DescentConfig, strata: StrataConfig, dynamic_config: DynamicConfig, save) -> list[np.ndarray]:
    """All iterates of descent whose strata, or draw counts only, follow the gradients every refresh_every steps."""
    assigned = save(cluster.build(ex, d, strata, save))
    w, out, step, kernel = np.zeros((classes, d)), [], schedule_of(config), L.get(config.loss)
    for first in range(1, config.steps + 1, dynamic_config.refresh_every):
        if dynamic_config.refresh == "both":
            assigned = gradient_strata(assigned, w, dynamic_config.iters, loss=config.loss, save=save)
        ss = variance.within(variance.gradient_sums(assigned, w.tolist(), config.loss))
        frame = allocate.gradient_dispersion(ss, assigned.groupBy("stratum").agg(F.min("y").alias("y")))
        plan = StratumPlan.from_frame(allocate.round_greedy(save(frame), config.b), config.b, classes, first)
        indexed = save(index.dense_position(assigned))
        last = min(first + dynamic_config.refresh_every - 1, config.steps)
        drawn = sampling.fetch(sampling.plan_chunk(ex.sparkSession, plan, config.seed, first, last), indexed, n_draws=(last - first + 1) * config.b)
        for t, (x, y, weight) in by_step(drawn, d).items():  # one refresh interval's draws
            g = (kernel.residual(x @ w.T, y) * weight[:, None]).T @ x + config.lam * w
            w = w - step.at(t) * g
            out.append(w)
    return out


def evaluate(models: DataFrame, ex: DataFrame, lam: float, loss: str = "softmax") -> DataFrame:
    """(run_id, t, objective, test_error) of every model, in one pass over ex for all of them together."""
    rows = models.collect()  # checkpoints of some runs: c matrices
    keys = sorted({(r.run_id, r.t) for r in rows})
    at = {k: i for i, k in enumerate(keys)}
    m = max(r.cls for r in rows) + 1
    tensor = np.zeros((len(keys), m, len(rows[0].w)))
    for r in rows:
        tensor[at[r.run_id, r.t], r.cls] = r.w
    kernel, d = L.get(loss), tensor.shape[2]

    def scored(batches):
        total = np.zeros((len(keys), 4))
        for batch in batches:
            y, x = variance.arrays(batch, d)
            train = pc.equal(batch.column(batch.schema.get_field_index("split")), "train").to_numpy(zero_copy_only=False)
            total[:, 0] += train.sum()
            total[:, 2] += (~train).sum()
            for c in range(len(keys)):
                s = x @ tensor[c].T
                total[c, 1] += kernel.value(s[train], y[train]).sum()
                total[c, 3] += (s[~train].argmax(axis=1) != y[~train]).sum()
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(len(keys), dtype=np.int32)), *(pa.array(total[:, j]) for j in range(4))], ["model", "n", "loss", "n_test", "wrong"])

    sums = ex.select("y", "x", "split").mapInArrow(scored, "model int, n double, loss double, n_test double, wrong double")
    sums = sums.groupBy("model").agg(*(F.sum(c).alias(c) for c in ("n", "loss", "n_test", "wrong")))
    names = ex.sparkSession.createDataFrame([(i, k[0], int(k[1]), float(lam / 2 * (tensor[i] ** 2).sum()), float(np.sqrt((tensor[i] ** 2).sum()))) for k, i in at.items()], "model int, run_id string, t int, ridge double, w_norm double")
    return sums.join(F.broadcast(names), "model").select("run_id", "t", (F.try_divide("loss", "n") + F.col("ridge")).alias("objective"), F.try_divide("wrong", "n_test").alias("test_error"), "w_norm")


def variances(models: DataFrame, assigned: DataFrame, plan: StratumPlan, loss: str = "softmax") -> DataFrame:
    """(run_id, t, est_variance): exact variance at every model of one sampler's plan, in one pass for all of them."""
    rows = models.collect()
    keys = sorted({(r.run_id, r.t) for r in rows})
    m, d = max(r.cls for r in rows) + 1, len(rows[0].w)
    tensor = np.zeros((len(keys), m, d))
    at = {k: i for i, k in enumerate(keys)}
    for r in rows:
        tensor[at[r.run_id, r.t], r.cls] = r.w
    kernel = L.get(loss)

    def partial(batches):
        state: dict[tuple[int, int], list] = {}
        for batch in batches:
            y, x = variance.arrays(batch, d)
            stratum = batch.column(batch.schema.get_field_index("stratum")).to_numpy(zero_copy_only=False)
            order = np.argsort(stratum, kind="stable")  # a stratum's rows stand together, so each is a slice
            y, x, stratum = y[order], x[order], stratum[order]
            x2 = (x * x).sum(axis=1)
            edges = np.append(np.flatnonzero(np.diff(stratum, prepend=stratum[:1] - 1)), len(stratum))
            for c in range(len(keys)):
                r = kernel.residual(x @ tensor[c].T, y)
                squares = (r * r).sum(axis=1) * x2
                for a, z in zip(edges[:-1], edges[1:], strict=True):
                    have = state.setdefault((c, int(stratum[a])), [0, 0.0, np.zeros((m, d))])
                    have[0] += int(z - a)
                    have[1] += float(squares[a:z].sum())
                    have[2] += r[a:z].T @ x[a:z]
        items = sorted(state.items())
        yield pa.RecordBatch.from_arrays(
            [pa.array([k[0] for k, _ in items], pa.int32()), pa.array([k[1] for k, _ in items], pa.int32()), pa.array([v[0] for _, v in items], pa.int64()), pa.array([v[1] for _, v in items], pa.float64()), pa.array([v[2].ravel().tolist() for _, v in items], pa.list_(pa.float64()))],
            ["model", "stratum", "cnt", "squares", "g"],
        )

    parts = assigned.select("y", "x", F.col("stratum").cast("int").alias("stratum")).mapInArrow(partial, "model int, stratum int, cnt bigint, squares double, g array<double>")
    cells = parts.select("model", "stratum", "cnt", "squares", F.posexplode("g").alias("cell", "g"))
    sums = cells.groupBy("model", "stratum", "cell").agg(F.sum("cnt").alias("cnt"), F.sum("squares").alias("squares"), F.sum("g").alias("g"))
    ss = sums.groupBy("model", "stratum").agg(F.first("cnt").alias("cnt"), F.greatest(F.first("squares") - F.sum(F.col("g") * F.col("g")) / F.first("cnt"), F.lit(0.0)).alias("ss"))
    spark = assigned.sparkSession
    ss = ss.join(plan.frame(spark), "stratum")
    n = F.sum("cnt")
    out = ss.groupBy("model").agg((F.sum(F.col("cnt") / F.col("b_i") * F.col("ss")) / (n * n)).alias("est_variance"))
    names = spark.createDataFrame([(i, k[0], int(k[1])) for k, i in at.items()], "model int, run_id string, t int")
    return out.join(F.broadcast(names), "model").select("run_id", "t", "est_variance")
