"""Worked examples, enumeration, invariants and bounds of the engine."""

from __future__ import annotations

import itertools
import math
from dataclasses import replace
from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

from strata_descent import queries
from strata_descent.functions import features, schedule
from strata_descent.functions import loss as L
from strata_descent.operators import allocate, averaging, bounds, cluster, descent, extras, index, measures, sampling, variance
from strata_descent.plans import experiments
from strata_descent.plans.plan import AllocationConfig, DescentConfig, DynamicConfig, StrataConfig, Stratum, StratumPlan

SIX = [(1, 0, [0.0], "train", 0), (2, 0, [2.0], "train", 0), (3, 0, [10.0], "train", 1), (4, 0, [14.0], "train", 1), (5, 1, [5.0], "train", 2), (6, 1, [5.0], "train", 2)]
SCHEMA = "row_id bigint, y int, x array<double>, split string, stratum int"


@pytest.fixture(scope="module")
def six(spark):
    return spark.createDataFrame(SIX, SCHEMA).cache()


def counted(spark, strata, counts):
    extra = spark.createDataFrame(list(enumerate(counts)), "stratum int, b_i int")
    return strata.join(extra, "stratum")


def test_worked_example(spark, six):
    strata = cluster.stats(six, 1).cache()
    assert [(r.n_i, r.v_i) for r in strata.orderBy("stratum").collect()] == [(2, 1.0), (2, 4.0), (2, 0.0)]
    assert [r.b_real for r in allocate.real(strata, 6).orderBy("stratum").collect()] == [2.0, 4.0, 0.0]
    greedy = allocate.round_greedy(strata, 6)
    assert [r.b_i for r in greedy.orderBy("stratum").collect()] == [2, 3, 1]
    assert allocate.surrogate(greedy).first()[0] == pytest.approx(0.203704, abs=1e-6)
    assert allocate.surrogate(counted(spark, strata, [2, 2, 2])).first()[0] == pytest.approx(0.277778, abs=1e-6)
    origin = [[0.0], [0.0]]
    assert variance.stratified(six, origin, greedy).first()[0] == pytest.approx(0.101852, abs=1e-6)
    assert variance.at_origin(greedy, 2).first()[0] == pytest.approx(0.101852, abs=1e-6)
    assert variance.uniform(six, origin, 6).first()[0] == pytest.approx(4.268519, abs=1e-6)
    g = {r.cls: r.g for r in variance.full_gradient(six, origin).collect()}
    assert g == {0: pytest.approx(-4 / 3), 1: pytest.approx(4 / 3)}
    assert measures.objective(six, origin, 0.0).first()[0] == pytest.approx(math.log(2))
    assert cluster.dispersion_objective(strata).first()[0] == pytest.approx(6.0)


def gradient(w, x, y):
    return L.get("softmax").residual(x @ w.T, y)[:, :, None] * x[:, None, :]


@pytest.mark.parametrize("w", [np.zeros((2, 1)), np.array([[0.3], [-0.1]])])
def test_enumeration_is_unbiased_with_the_exact_variance(spark, six, w):
    """All 16 bags for counts (1, 2, 1)."""
    x, y, s = np.array([r[2] for r in SIX]), np.array([r[1] for r in SIX]), np.array([r[4] for r in SIX])
    g = gradient(w, x, y)
    bags = []
    for a, b1, b2, c in itertools.product([0, 1], [2, 3], [2, 3], [4, 5]):
        bags.append(sum(2 / (6 * b) * g[i] for i, b in ((a, 1), (b1, 2), (b2, 2), (c, 1))))
    full = g.mean(axis=0)
    assert np.allclose(np.mean(bags, axis=0), full)
    exact = np.mean([((one - full) ** 2).sum() for one in bags])
    strata = counted(spark, cluster.stats(six, 1), [1, 2, 1])
    assert variance.stratified(six, w.tolist(), strata).first()[0] == pytest.approx(exact, abs=1e-9)
    assert s.tolist() == [0, 0, 1, 1, 2, 2]


def test_bag_keeps_repeats(spark, six):
    one = index.dense_position(six.where("row_id = 1"))
    plan = StratumPlan((Stratum(0, 0, 1, 0.0, 3),), 1, 3)
    drawn = sampling.fetch(sampling.plan_chunk(spark, plan, 1, 1, 4), one, "broadcast")
    assert drawn.count() == 12
    assert drawn.where("t = 1").agg(F.sum("draw_weight")).first()[0] == pytest.approx(1.0)


def test_greedy_is_the_best_whole_split(spark):
    rng = np.random.default_rng(3)
    for _ in range(4):
        n, v, b = rng.integers(1, 30, 3), rng.random(3).round(3), 9
        strata = spark.createDataFrame([(i, i, int(n[i]), float(v[i])) for i in range(3)], "stratum int, y int, n_i bigint, v_i double")
        cost = lambda c: sum(float(n[i]) ** 2 * v[i] / c[i] for i in range(3))
        best = min(cost(c) for c in itertools.product(range(1, b), repeat=3) if sum(c) == b)
        got = [r.b_i for r in allocate.round_greedy(strata, b).orderBy("stratum").collect()]
        assert sum(got) == b and cost(got) == pytest.approx(best)
        for how in (allocate.round_remainder(strata, b), allocate.round_systematic(strata, b, 5)):
            other = [r.b_i for r in how.orderBy("stratum").collect()]
            assert sum(other) == b and min(other) >= 1


def test_plan_rejects_bad_strata():
    with pytest.raises(ValueError):
        StratumPlan((Stratum(0, 0, 5, 1.0, 2),), 5, 2).check(2)  # fewer strata than classes
    with pytest.raises(ValueError):
        StratumPlan((Stratum(0, 0, 5, 1.0, 1), Stratum(1, 1, 5, 1.0, 2)), 10, 2).check(2)  # draws do not add up
    with pytest.raises(ValueError):
        StratumPlan((Stratum(0, 0, 5, 1.0, 2), Stratum(1, 1, 0, 1.0, 1)), 5, 3).check(2)  # an empty stratum


def blobs(spark, n=120, seed=1):
    rng = np.random.default_rng(seed)
    centre = rng.normal(size=(6, 2)) * 4
    return spark.createDataFrame([(i, i % 2, (centre[i % 6] + rng.normal(size=2) * (0.2 + i % 3)).tolist(), "train") for i in range(n)], "row_id bigint, y int, x array<double>, split string")


def test_dispersion_rounds_never_raise_the_objective(spark):
    for seed in (1, 2):
        at = cluster.quantile_strata(cluster.train_rows(blobs(spark, seed=seed)), 3)
        values = []
        for _ in range(4):
            strata = cluster.stats(at, 2).cache()
            values.append(strata.agg(F.sum(F.col("n_i") * F.sqrt(F.col("v_i") + 1e-6))).first()[0])
            at = cluster.assign(at, strata, "dispersion").cache()
        assert all(b <= a + 1e-9 for a, b in zip(values, values[1:], strict=False))
        assert cluster.validate(at).count() == 0


def test_single_stratum_is_uniform_and_proportional_is_no_worse(spark):
    ex = blobs(spark).cache()
    w = [[0.1, -0.2], [0.0, 0.3]]
    strata = cluster.stats(cluster.by_class(ex), 2)
    real = allocate.real(strata, 10, "proportional").withColumn("b_i", F.col("b_real"))
    uniform = variance.uniform(ex, w, 10).first()[0]
    assert variance.stratified(cluster.by_class(ex), w, real).first()[0] <= uniform + 1e-9
    one = cluster.stats(ex.withColumn("stratum", F.lit(0)), 2).withColumn("b_i", F.lit(10))
    assert variance.stratified(ex.withColumn("stratum", F.lit(0)), w, one).first()[0] == pytest.approx(uniform)


def test_centroid_bound_holds(spark):
    ex = cluster.by_class(blobs(spark)).cache()
    w = [[0.4, -0.2], [0.1, 0.3]]
    strata = allocate.round_greedy(cluster.stats(ex, 2), 8).cache()
    assert variance.stratified(ex, w, strata).first()[0] <= variance.at_centroid(ex, w, strata).first()[0] + 1e-12


def test_gradient_is_the_derivative_and_scores_may_be_huge(spark):
    rng = np.random.default_rng(0)
    x, y = rng.normal(size=(5, 3)), np.array([0, 1, 2, 1, 0])
    for name in ("softmax", "squared", "logistic", "squared_hinge"):
        kernel, w = L.get(name), rng.normal(size=(3, 3))
        g = kernel.residual(x @ w.T, y).T @ x
        for c, j in ((0, 0), (2, 1)):
            e = np.zeros_like(w)
            e[c, j] = 1e-6
            slope = (kernel.value(x @ (w + e).T, y).sum() - kernel.value(x @ (w - e).T, y).sum()) / 2e-6
            assert slope == pytest.approx(g[c, j], rel=1e-4, abs=1e-6)
    big = spark.createDataFrame([(0, [1e5, -1e5])], "y int, x array<double>")
    row = big.select(L.softmax_value(F.col("x"), F.col("y")).alias("v"), L.softmax_residual(F.col("x"), F.col("y")).alias("r")).first()
    assert row.v == pytest.approx(0.0) and row.r == [pytest.approx(0.0), pytest.approx(0.0)]


def test_paths_agree_and_partitioning_does_not_matter(spark):
    ex = blobs(spark)
    w = [[0.1, -0.2], [0.0, 0.3]]
    arrow = {(r.cls, r.component): r.g for r in variance.full_gradient(ex, w).collect()}
    native = {(r.cls, r.component): r.g for r in variance.draw_gradient(ex.withColumn("draw_weight", F.lit(1 / 120)), w, 0.0, []).collect()}
    assert arrow.keys() == native.keys() and all(arrow[k] == pytest.approx(native[k], abs=1e-12) for k in arrow)
    config = DescentConfig(0.1, 6, 7, "constant", 0.2, eval_every=7)
    ends = []
    for parts in (1, 5):
        some = ex.repartition(parts)
        assigned, _, plan = descent.prepare(some, 2, 2, 6, StrataConfig("by_class"), AllocationConfig())
        models = descent.run_chains([descent.Run("run", index.dense_position(assigned), plan, config, np.zeros((2, 2)))]).where("t = 7").orderBy("cls").collect()
        ends.append([r.w for r in models])
    assert np.allclose(ends[0], ends[1], atol=1e-12)


def test_chunks_carry_the_state(spark, monkeypatch):
    ex = blobs(spark)
    config = DescentConfig(0.1, 6, 9, "constant", 0.2, eval_every=9)
    assigned, _, plan = descent.prepare(ex, 2, 2, 6, StrataConfig("by_class"), AllocationConfig())
    run = lambda: [r.w for r in descent.run_chains([descent.Run("a", index.dense_position(assigned), plan, config, np.zeros((2, 2)))]).where("t = 9").orderBy("cls").collect()]
    whole = run()
    monkeypatch.setattr(descent, "CHUNK_ROWS", 24)
    assert np.allclose(whole, run(), atol=1e-12)


def test_optimum_and_bounds(spark):
    """Mean gap of plain gradient descent stays below the bound with no variance; the inequalities hold."""
    ex, lam = blobs(spark).withColumn("x", F.transform("x", lambda v: v / 5)).cache(), 0.1
    best = bounds.reference_optimum(spark, ex, lam, 2)
    c = bounds.constants(ex, lam).first()
    at = lambda w: measures.objective(ex, w.tolist(), lam).first()[0]
    assert np.abs(extras.gradient_matrix(cluster.train_rows(ex), best, lam)).max() < 1e-4
    steps = 12
    config = DescentConfig(lam, 1, steps, "shifted", shift=c.smoothness - lam)
    iterates = descent.full_gradient_descent(ex, np.zeros_like(best), config)
    gaps = [at(w) - at(best) for w in iterates]
    trace = spark.createDataFrame([(t, 0.0) for t in range(1, steps + 1)], "t int, variance double")
    assert np.mean(gaps) <= bounds.theorem1(trace, c.smoothness - lam, lam, float((best**2).sum())).first()[0] + 1e-9
    eta = 1.0 / (lam + c.smoothness)
    last = descent.full_gradient_descent(ex, np.zeros_like(best), DescentConfig(lam, 1, steps, "constant", eta))[-1]
    assert at(last) - at(best) <= bounds.theorem2(trace, eta, lam, c.smoothness, float((best**2).sum())).first()[0] + 1e-9
    left, right = bounds.lemma2_sides(extras.gradient_matrix(ex, iterates[3], lam), extras.gradient_matrix(ex, best, lam), iterates[3], best, lam, c.smoothness)
    assert left >= right - 1e-9
    assert not schedule.theory_covered(schedule.inverse(lam), c.smoothness, 5)
    assert schedule.theory_covered(schedule.constant(1 / c.smoothness), c.smoothness, 5)


def test_averages(spark):
    it = spark.createDataFrame([(t, 0, 0, float(t)) for t in range(1, 7)], "t int, cls int, component int, w double")
    mean = 0.0
    for t in range(1, 7):
        rho = 4 / (t + 3)
        mean = (1 - rho) * mean + rho * t
    assert averaging.polynomial(it, 3).first().w == pytest.approx(mean)
    assert averaging.suffix(it, 0.5, 6).first().w == pytest.approx(5.0)
    assert averaging.last(it).first().w == 6.0


def test_class_counts():
    assert cluster.class_counts(5, {0: 10, 1: 10}) == {0: 3, 1: 2}
    assert cluster.class_counts(6, {0: 1, 1: 10}) == {0: 1, 1: 5}


def test_null_policy(spark):
    df = spark.createDataFrame([(1, 1.0), (2, None), (3, float("nan")), (4, 3.0)], "i int, v double")
    assert features.null_policy(df, ["v"], "drop").count() == 2
    assert sorted(r.v for r in features.null_policy(df, ["v"], "impute_mean").collect()) == [1.0, 2.0, 2.0, 3.0]
    with pytest.raises(ValueError):
        features.null_policy(df, ["v"], "reject")


def test_rounding_and_kinds(spark):
    strata = spark.createDataFrame([(0, 0, 10, 4.0), (1, 1, 30, 1.0), (2, 1, 5, 0.0)], "stratum int, y int, n_i bigint, v_i double")
    counts = lambda df: [r.b_i for r in df.orderBy("stratum").collect()]
    assert counts(allocate.allocate(strata, 10, "dispersion", "none")) == pytest.approx([4.0, 6.0, 0.0])
    assert counts(allocate.allocate(strata, 9, "equal", "greedy")) == [3, 3, 3]
    mass = [100.0, 900.0, 25.0]
    best = min((sum(m / b for m, b in zip(mass, c, strict=True)), c) for c in itertools.product(range(1, 9), repeat=3) if sum(c) == 9)[1]
    assert tuple(counts(allocate.allocate(strata, 9, "proportional", "greedy"))) == best
    for kind, rounding in (("dispersion", "other"), ("other", "remainder")):
        with pytest.raises((ValueError, KeyError)):
            allocate.allocate(strata, 9, kind, rounding)


def test_wide_statistics_are_the_narrow_ones(spark, monkeypatch):
    ex = cluster.quantile_strata(cluster.train_rows(blobs(spark)), 3).repartition(5)
    narrow = {r.stratum: r for r in cluster.stats(ex, 2).collect()}
    wide = {r.stratum: r for r in cluster.wide_stats(ex, 2).collect()}
    assert narrow.keys() == wide.keys()
    for s, r in narrow.items():
        assert (wide[s].y, wide[s].n_i) == (r.y, r.n_i) and wide[s].v_i == pytest.approx(r.v_i) and wide[s].mean == pytest.approx(r.mean)


def test_starts_need_no_window_and_seed_lost_strata_again(spark):
    ex = blobs(spark).cache()
    rows = cluster.train_rows(ex)
    start = cluster.approximate_quantile_strata(rows, {0: 3, 1: 3})
    assert "Window" not in start._jdf.queryExecution().toString()
    exact = {(r.row_id, r.stratum) for r in cluster.quantile_strata(rows, 3).collect()}
    assert len(exact & {(r.row_id, r.stratum) for r in start.select("row_id", "stratum").collect()}) > 110  # bins may differ by a row at their edges
    flat = rows.withColumn("x", F.array(F.lit(1.0), F.col("x")[1]))  # no spread along the first feature: one bin a class
    lost = cluster.approximate_quantile_strata(flat, {0: 3, 1: 3})
    assert lost.select("stratum").distinct().count() == 2
    again = cluster.rounds(lost, 2, 3, "dispersion", per_class={0: 3, 1: 3}, save=lambda df: df.cache())
    assert again.select("stratum").distinct().count() == 6 and cluster.validate(again, flat).count() == 0
    before, after = (cluster.dispersion_objective(cluster.stats(x, 2)).first()[0] for x in (lost, again))
    assert after < before


@pytest.mark.parametrize("init", ["random", "plusplus"])
def test_centres_start_in_their_class(spark, init):
    rows = cluster.train_rows(blobs(spark)).cache()
    centres = cluster.first_centres(rows, {0: 3, 1: 2}, init, 5).collect()
    own = {(r.y, tuple(r.x)) for r in rows.collect()}
    assert sorted((c.y, c.stratum) for c in centres) == [(0, 0), (0, 1), (0, 2), (1, 3), (1, 4)] and all((c.y, tuple(c.mean)) in own for c in centres)
    built = cluster.build(blobs(spark), 2, StrataConfig("kmeans", 5, init=init, iters=4, tol=1e-3, fit_fraction=0.6), lambda df: df.cache())
    assert cluster.validate(built, rows, cluster.stats(built, 2)).count() == 0


def test_two_passes_and_one_agree(spark):
    ex = cluster.by_class(blobs(spark)).cache()
    w = [[0.4, -0.2], [0.1, 0.3]]
    one = {r.stratum: r.ss for r in variance.within(variance.gradient_sums(ex, w)).collect()}
    two = {r.stratum: r.ss for r in variance.centred_within(ex, w).collect()}
    assert one.keys() == two.keys() and all(one[s] == pytest.approx(two[s]) for s in one)
    far = ex.withColumn("x", F.transform("x", lambda v: v / 1e9 + 1e6))  # nothing is left of a difference of large sums
    assert all(0 <= r.ss < 1e-3 for r in variance.centred_within(far, [[0.0, 0.0], [0.0, 0.0]]).collect())


def test_index_by_blocks_reads_what_draws_hit(spark, tmp_path, monkeypatch):
    monkeypatch.setattr(index, "BLOCK_ROWS", 10)
    indexed = index.dense_position(cluster.by_class(cluster.train_rows(blobs(spark)))).cache()
    index.write(indexed, str(tmp_path / "index"))
    plan = StratumPlan((Stratum(0, 0, 60, 1.0, 2), Stratum(1, 1, 60, 1.0, 2)), 120, 4)
    draws = sampling.plan_chunk(spark, plan, 1, 1, 2)
    key = lambda df: sorted((r.t, r.stratum, r.r, r.row_id) for r in df.collect())
    got = sampling.fetch(draws, index.read(spark, str(tmp_path / "index")), "broadcast")
    assert key(got) == key(sampling.fetch(draws, indexed, "broadcast"))
    assert "dynamicpruning" in got._jdf.queryExecution().toString()
    assert index.buckets_for(10) == 64 and index.buckets_for(10**9) == 2048


def test_positions_do_not_follow_the_size(spark, monkeypatch):
    """Many rows are ranked in more tasks, but their order stays: by one of 64 buckets, then by id."""
    rows = cluster.by_class(cluster.train_rows(blobs(spark))).withColumn("row_id", F.when(F.col("row_id") % 7 == 0, F.col("row_id") * 1000).otherwise(F.col("row_id")))
    few = {r.row_id: (r.stratum, r.pos) for r in index.dense_position(rows).collect()}
    monkeypatch.setattr(index, "ROWS_PER_BUCKET", 1)
    monkeypatch.setattr(index, "BUCKETS", 4)
    few_in_four = {r.row_id: (r.stratum, r.pos) for r in index.dense_position(rows, 4).collect()}
    assert index.buckets_for(120) == 128
    assert {r.row_id: (r.stratum, r.pos) for r in index.dense_position(rows).collect()} == few_in_four
    assert sorted(few.values()) == sorted(few_in_four.values()) == [(s, p) for s in (0, 1) for p in range(60)]


def test_large_runs_move_the_rows_few_times(spark, monkeypatch):
    """Draws that are too many to broadcast come in chunks of as many as rows; a chain reads its draws as a stream of any pieces."""
    assert descent.chunk_rows(StratumPlan.single(32_000_000, 10), 3_200_000, 5) == 6_400_000
    assert descent.chunk_rows(StratumPlan.single(1000, 10), 100, 5) == descent.CHUNK_ROWS
    ex = blobs(spark)
    assigned, _, plan = descent.prepare(ex, 2, 2, 6, StrataConfig("by_class"), AllocationConfig())
    config = DescentConfig(0.1, 6, 9, "constant", 0.2, eval_every=4)
    runs = [descent.Run(f"s{i}", index.dense_position(assigned), plan, replace(config, seed=i, steps=9 - i), np.zeros((2, 2))) for i in range(3)]
    key = lambda df: {(r.run_id, r.t, r.cls): r.w for r in df.collect()}
    whole = key(descent.run_chains(runs))
    assert {k[:2] for k in whole} == {("s0", 4), ("s0", 8), ("s0", 9), ("s1", 4), ("s1", 8), ("s2", 4), ("s2", 7)}
    monkeypatch.setattr(descent, "CHUNK_ROWS", 24)
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(name)
    spark.conf.set(name, "5")
    try:
        pieces = key(descent.run_chains(runs))
    finally:
        spark.conf.set(name, before)
    assert whole.keys() == pieces.keys() and all(np.allclose(whole[k], pieces[k], atol=1e-12) for k in whole)


def test_positions_are_counted_where_the_ranks_are_written(spark, tmp_path, monkeypatch):
    """With save the ranked rows are written once, and the positions stay."""
    rows = cluster.by_class(cluster.train_rows(blobs(spark)))
    plain = {r.row_id: (r.stratum, r.pos) for r in index.dense_position(rows).collect()}
    written = []

    def save(df):
        written.append(df.columns)
        df.write.parquet(f"{tmp_path}/{len(written)}")
        return spark.read.parquet(f"{tmp_path}/{len(written)}")

    monkeypatch.setattr(index, "ROWS_PER_BUCKET", 1)
    for buckets in (None, 64, 256):
        found = index.dense_position(rows, buckets, save)
        assert {r.row_id: (r.stratum, r.pos) for r in found.collect()} == plain
        assert "md5" not in found._jdf.queryExecution().optimizedPlan().toString()
    assert len(written) == 6


def test_ranks_are_written_in_parts(spark, tmp_path, monkeypatch):
    """Where ranks are written, no shuffle has the rows of more than some ranges, and positions stay; rows without an id are in the first."""
    rows = cluster.by_class(cluster.train_rows(blobs(spark)))
    rows = rows.unionByName(rows.limit(1).withColumn("row_id", F.lit(None).cast("bigint")))
    plain = {r.row_id: (r.stratum, r.pos) for r in index.dense_position(rows).collect()}
    written = []

    def save(df):
        df.write.parquet(f"{tmp_path}/{len(written)}")
        written.append(spark.read.parquet(f"{tmp_path}/{len(written)}"))
        return written[-1]

    for ranges in (32, 7):
        written.clear()
        tmp_path = tmp_path / str(ranges)
        found = index.dense_position(rows, ranges * index.BUCKETS, save)
        assert {r.row_id: (r.stratum, r.pos) for r in found.collect()} == plain and found.count() == rows.count()
        parts = [w for w in written if "row_id" in w.columns]
        assert sum(w.count() for w in parts) == rows.count() and len(parts) == -(-ranges // 4)
        assert all(w.select("range_").distinct().count() <= 4 for w in parts)


def test_scale_run_keeps_no_tables_of_copies(spark):
    """All copies and phases are there, and what a turn has written goes with it."""
    root = Path(spark.conf.get("spark.checkpoint.dir").removeprefix("file:"))
    before = set(root.glob("cut-*"))
    got = experiments.scale_run(spark, "/root/testdata/sf0.001", queries.saver(spark), (1, 3), steps=4).collect()
    rows = {(r.replicas, r.phase): r.rows for r in got}
    assert len(rows) == 4 and rows[3, "setup"] > 2 * rows[1, "train"] > 0
    assert len(set(root.glob("cut-*")) - before) == 1  # the view


def test_rows_are_placed_in_batches(spark):
    """The least cost to 9 places, ties to the lowest id; rows of a class without centres go."""
    centres = spark.createDataFrame([(3, 0, 5, [1.0, 0.0], 4.0), (2, 0, 5, [-1.0, 0.0], 1.0), (7, 1, 5, [0.0, 0.0], 1.0)], "stratum int, y int, n_i bigint, mean array<double>, v_i double")
    rows = spark.createDataFrame([(1, 0, [0.0, 9.0]), (2, 0, [1e-10, 0.0]), (3, 0, [1e-9, 0.0]), (4, 0, [float("nan"), 0.0]), (5, 1, [50.0, 0.0]), (6, 2, [0.0, 0.0]), (7, 0, [-5.0, 0.0])], "row_id bigint, y int, x array<double>")
    placed = cluster.assign(rows, centres)
    assert {r.row_id: r.stratum for r in placed.collect()} == {1: 2, 2: 2, 3: 3, 4: 2, 5: 7, 7: 2}
    assert placed.dtypes == [("row_id", "bigint"), ("y", "int"), ("x", "array<double>"), ("stratum", "int")]
    assert {r.row_id: r.stratum for r in cluster.assign(rows, centres, "dispersion").collect()} == {1: 3, 2: 2, 3: 2, 4: 2, 5: 7, 7: 2}
    plan = placed._jdf.queryExecution().optimizedPlan().toString()
    assert "MapInArrow" in plan and "transform(" not in plan
    assert cluster.assign(rows, centres.where("y > 5")).count() == 0


def test_a_sample_is_hashed_once(spark, tmp_path):
    """What strata are fitted on is written before it is looked at."""
    written = []

    def save(df):
        written.append(df)
        df.write.parquet(f"{tmp_path}/{len(written)}")
        return spark.read.schema(df.schema).parquet(f"{tmp_path}/{len(written)}")

    cluster.build(blobs(spark), 2, StrataConfig("kmeans", 4, iters=2, fit_fraction=0.5), save)
    assert ["md5" in df._jdf.queryExecution().optimizedPlan().toString() for df in written].count(True) == 1
    assert written[0].columns == ["row_id", "y", "x"]


def test_all_seeds_share_one_join(spark):
    ex = blobs(spark)
    assigned, _, plan = descent.prepare(ex, 2, 2, 6, StrataConfig("by_class"), AllocationConfig())
    indexed = index.dense_position(assigned)
    together = sampling.plan_runs(spark, [(f"s{i}", plan, i, 4 + i) for i in range(3)], 1, 6)
    alone = [r for i in range(3) for r in sampling.plan_chunk(spark, plan, i, 1, min(6, 4 + i), f"s{i}").collect()]
    assert sorted(map(repr, together.collect())) == sorted(map(repr, alone))
    config = DescentConfig(0.1, 6, 5, "constant", 0.2, eval_every=5)
    runs = [descent.Run(f"s{i}", indexed, plan, DescentConfig(0.1, 6, 5, "constant", 0.2, seed=i, eval_every=5), np.zeros((2, 2))) for i in range(3)]
    many = {(r.run_id, r.cls): r.w for r in descent.run_chains(runs).collect()}
    for i, run in enumerate(runs):
        one = {(r.run_id, r.cls): r.w for r in descent.run_chains([run]).collect()}
        assert all(many[k] == pytest.approx(v) for k, v in one.items())
    assert config.steps == 5


def twin(rows, plan, positions, config, classes, steps):
    """Stratified descent in plain NumPy from the same hashes."""
    import hashlib

    w = np.zeros((classes, len(rows[0][1])))
    for t in range(1, steps + 1):
        g = config.lam * w
        for s in plan.strata:
            for r in range(1, s.b_i + 1):
                pos = int(hashlib.md5(f"{config.seed}|{t}|{s.stratum}|{r}".encode()).hexdigest()[:13], 16) % s.n_i
                y, x = rows[positions[s.stratum, pos]]
                score = w @ x
                p = np.exp(score - score.max())
                p /= p.sum()
                g = g + s.n_i / (plan.n * s.b_i) * np.outer(p - np.eye(classes)[y], x)
        w = w - descent.schedule_of(config).at(t) * g
    return w


def test_published_schedule_against_a_plain_twin(spark):
    """60 steps of 1 / (lam t) over k-means strata, a model in NumPy beside the engine's."""
    ex = blobs(spark).cache()
    assigned, _, plan = descent.prepare(ex, 2, 2, 8, StrataConfig("kmeans", 4, iters=3), AllocationConfig(), lambda df: df.cache())
    indexed = index.dense_position(assigned).cache()
    rows = {r.row_id: (r.y, np.array(r.x)) for r in ex.collect()}
    positions = {(r.stratum, r.pos): r.row_id for r in indexed.collect()}
    config = DescentConfig(0.1, 8, 60, "inverse", seed=3, eval_every=60)
    got = descent.run_chains([descent.Run("run", indexed, plan, config, np.zeros((2, 2)))]).orderBy("cls").collect()
    assert np.allclose([r.w for r in got], twin(rows, plan, positions, config, 2, 60), atol=1e-9)


def test_counts_that_are_never_refreshed_are_fixed(spark):
    """Dynamic counts with one long interval are the fixed plan by gradient dispersion at the start."""
    ex = blobs(spark).cache()
    save = lambda df: df.cache()
    config = DescentConfig(0.1, 8, 6, "constant", 0.3, eval_every=6)
    moving = descent.dynamic(ex, 2, 2, config, StrataConfig("kmeans", 4, iters=2), DynamicConfig(6, "counts"), save)[-1]
    assigned = cluster.build(ex, 2, StrataConfig("kmeans", 4, iters=2), save)
    ss = variance.within(variance.gradient_sums(assigned, np.zeros((2, 2)).tolist()))
    frame = allocate.round_greedy(allocate.gradient_dispersion(ss, assigned.groupBy("stratum").agg(F.min("y").alias("y"))), 8)
    run = descent.Run("run", index.dense_position(assigned), StratumPlan.from_frame(frame, 8, 2), config, np.zeros((2, 2)))
    assert np.allclose([r.w for r in descent.run_chains([run]).orderBy("cls").collect()], moving, atol=1e-12)


def test_resampled_variance_is_the_exact_one(spark):
    """400 replayed steps lie within four standard errors of the exact variance, for positions and for draws by scan on average."""
    ex = cluster.by_class(blobs(spark)).cache()
    w = [[0.1, -0.2], [0.0, 0.3]]
    strata = allocate.round_greedy(cluster.stats(ex, 2), 6).cache()
    plan = StratumPlan.from_frame(strata, 6, 2)
    full = variance.full_gradient(ex, w).cache()
    drawn = sampling.fetch(sampling.plan_chunk(spark, plan, 11, 1, 400), index.dense_position(ex), "broadcast")
    r = variance.resampled(drawn, full, w).first()
    assert abs(r.variance - variance.stratified(ex, w, strata).first()[0]) < 4 * r.std_error
    scanned = sampling.by_scan(ex, plan, 11, 1, 400)
    per = scanned.groupBy("t", "stratum").agg(F.count("*").alias("n"), F.sum("draw_weight").alias("w")).groupBy("stratum").agg(F.avg("n").alias("n"), F.min("w").alias("w")).orderBy("stratum").collect()
    for s, row in zip(plan.strata, per, strict=True):
        assert row.n == pytest.approx(s.b_i, rel=0.25) and row.w == pytest.approx(s.n_i / plan.n)


def test_stratified_importance_is_unbiased(spark):
    """The mean over every draw of each stratum, weighed by its chance, is the full gradient."""
    ex = cluster.by_class(blobs(spark)).cache()
    w = np.array([[0.1, -0.2], [0.0, 0.3]])
    plan = StratumPlan((Stratum(0, 0, 60, 1.0, 3), Stratum(1, 1, 60, 1.0, 2)), 120, 5)
    indexed = extras.importance_index(ex).cache()
    rows = indexed.collect()
    assert {r.n_i for r in rows} == {60} and sum(r.p for r in rows) == pytest.approx(2.0)
    total = sum(r.p * L.get("softmax").residual(np.array([r.x]) @ w.T, np.array([r.y])).T @ np.array([r.x]) / (plan.n * r.p) for r in rows)
    assert np.allclose(total, extras.gradient_matrix(ex, w, 0.0))
    drawn = extras.importance_draws(indexed, plan, 1, 200).collect()
    assert len(drawn) == 1000 and all(r.draw_weight == pytest.approx(1 / (120 * next(x.p for x in rows if x.row_id == r.row_id) * (3, 2)[r.stratum])) for r in drawn[:20])


def test_definitions_hold(spark):
    rng = np.random.default_rng(4)
    pairs = [(rng.normal(size=(2, 2)), rng.normal(size=(2, 2))) for _ in range(3)]
    found = bounds.check_definitions(cluster.train_rows(blobs(spark)).cache(), pairs, 0.05).collect()
    assert len(found) == 18 and all(r.holds for r in found)


def test_mean_gap_of_runs_stays_below_the_bound(spark):
    rows = queries.QUERIES["theorem1_on_run"](spark, "/root/testdata/sf0.001").collect()
    assert {r.sampler for r in rows} == {"uniform", "stratified"} and all(r.holds for r in rows)


def test_one_step_inequality_by_enumeration(spark, six):
    """Lemma for one step from every model of a short run: the mean over all bags of what one step reaches."""
    x, y = np.array([r[2] for r in SIX]) / 10, np.array([r[1] for r in SIX])
    lam, w = 0.1, np.array([[0.3], [-0.2]])
    rows = spark.createDataFrame([(i, int(c), [float(v[0])], "train") for i, (c, v) in enumerate(zip(y, x, strict=True))], "row_id bigint, y int, x array<double>, split string")
    best = bounds.reference_optimum(spark, rows, lam, 2)
    smooth = bounds.constants(rows, lam).first().smoothness
    value = lambda v: L.get("softmax").value(x @ v.T, y).mean() + lam / 2 * (v * v).sum()
    each = L.get("softmax").residual(x @ w.T, y)[:, :, None] * x[:, None, :]
    eta = 0.5 / smooth
    ends = [w - eta * (g + lam * w) for g in each]
    spread = np.mean([((g - each.mean(axis=0)) ** 2).sum() for g in each])
    after = np.mean([((e - best) ** 2).sum() for e in ends])
    assert np.mean([value(e) for e in ends]) - value(best) <= bounds.lemma1(eta, ((w - best) ** 2).sum(), after, lam, spread) + 1e-12
    full = each.mean(axis=0) + lam * w
    assert np.mean([value(e) for e in ends]) <= bounds.one_step(value(w), (full * full).sum(), spread, eta, smooth) + 1e-12


def test_costs_come_from_the_status_store(spark):
    with measures.Cost(spark) as cost:
        spark.range(1000).repartition(3).groupBy((F.col("id") % 7).alias("k")).count().collect()
    seconds, stages, tasks, _, shuffled, spilled = cost.row()
    assert seconds > 0 and stages >= 2 and tasks >= 3 and shuffled > 0 and spilled == 0


def test_trigram_shares():
    text = "abcabc\U0001f600d"
    got = features.trigram_shares([text, "ab", None, ""], 16)
    import hashlib

    wanted = np.zeros(16)
    for i in range(len(text) - 2):
        wanted[int(hashlib.md5(text[i : i + 3].encode()).hexdigest()[:13], 16) % 16] += 1 / len(text)
    assert np.allclose(got[0], wanted) and not got[1:].any()


def test_workloads_run_whole_epochs(spark):
    trace = experiments.curves(spark, "/root/testdata/sf0.001", "w6", seeds=(1, 2), epochs=2.0, points=4, save=queries.saver(spark)).cache()
    ends = trace.groupBy("sampler", "seed").agg(F.max("epoch").alias("end"), F.count("*").alias("n")).collect()
    assert len(ends) == 4 and all(2.0 <= r.end < 2.5 and r.n == 4 for r in ends)
    rows = cluster.train_rows(features.view(spark, "/root/testdata/sf0.001", "f7"))
    smooth = bounds.constants(rows, experiments.WORKLOADS["w6"].lam).first().smoothness
    assert all(r.theory_covered == (r.eta <= 1 / smooth + 1e-15) for r in trace.collect())


#: Queries that made their data up, or read next to none.
READ = ["best_iterate", "exported_trace", "rate_slope", "rollup_trace", "seed_summary", "stability_trace", "asof_epoch_alignment", "epoch_axis", "hash_stream", "lemma1_rhs", "one_step_bound", "sql_draws"]


def rows_read(spark):
    """Records that tasks have read from tables so far; bytes of local files are not all counted."""
    context = spark.sparkContext
    context._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    lists = context._jvm.java.util.ArrayList
    found = context._jsc.sc().statusStore().stageList(lists(), False, False, context._gateway.new_array(context._jvm.double, 0), lists())
    return {found.apply(i).stageId(): found.apply(i).inputRecords() for i in range(found.size())}


@pytest.mark.parametrize("name", READ)
def test_spark_reads_the_table(spark, name):
    before = rows_read(spark)
    assert queries.QUERIES[name](spark, "/root/testdata/sf0.01").collect()
    assert sum(n for stage, n in rows_read(spark).items() if stage not in before) >= 10_000  # rows of events
