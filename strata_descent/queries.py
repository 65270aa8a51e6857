"""The registered queries of the engine, each beside its oracle where SQL can express it."""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Callable
from dataclasses import replace
from pathlib import Path

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import oracles as O
from .functions import features, rng
from .functions import sql as sql_functions
from .functions import loss as L
from .functions.features import VIEWS, view
from .operators import allocate, averaging, bounds, cluster, descent, extras, index, measures, sampling, variance
from .plans import experiments
from .plans.plan import AllocationConfig, DescentConfig, DynamicConfig, StrataConfig, StratumPlan
from .sources.load import assert_contract, export_trace, load, read_libsvm, register, roundtrip, short_lived, write_bucketed, write_libsvm
from .streaming import stream

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def add(name: str, query: Callable[[SparkSession, str], DataFrame], sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def r6(c: F.Column | str) -> F.Column:
    return F.round(c, 6) + F.lit(0.0)


def shared_path(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder; only a session on one machine may do without, as in tests."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if not root:
        if not spark.sparkContext.master.startswith("local[") and spark.sparkContext.master != "local":
            raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
        root = Path(tempfile.mkdtemp(prefix="descent-")).as_uri()
    return f"{root.rstrip('/')}/{name}-{uuid.uuid4().hex}"


def saver(spark: SparkSession):
    """Cuts the lineage through a written table in the shared folder; its clear() deletes those that the given ones do not read."""
    written: list[str] = []

    def save(df: DataFrame) -> DataFrame:
        path = shared_path(spark, "cut")
        with short_lived(spark):
            df.write.option("compression", "zstd").parquet(path)
        written.append(path)
        return spark.read.schema(df.schema).parquet(path)

    def clear(*keep: DataFrame) -> None:
        left = {f.rsplit("/", 2)[-2] for df in keep for f in df.inputFiles()}
        for path in [p for p in written if p.rsplit("/", 1)[-1] not in left]:
            where = spark._jvm.org.apache.hadoop.fs.Path(path)
            where.getFileSystem(spark._jsc.hadoopConfiguration()).delete(where, True)
            written.remove(path)

    save.clear = clear
    return save


def fixed_w(m: int, d: int) -> L.Weights:
    """Some model, the same everywhere."""
    return [[((c * 7 + j * 3) % 5 - 2) / 10 for j in range(d)] for c in range(m)]


def zeros(m: int, d: int) -> L.Weights:
    return [[0.0] * d for _ in range(m)]


# ---- data -----------------------------------------------------------------------------------------


def _label_counts(table: str, label: str) -> None:
    sql = f"select {label} as label, count(*) as n_rows from {table} group by {label}"
    add(f"label_counts_{table}", lambda s, d: load(s, d, table).groupBy(F.col(label).alias("label")).agg(F.count("*").alias("n_rows")), sql)


for _t, _l in (("embeddings", "label"), ("lineitem", "l_returnflag"), ("part", "p_brand"), ("events", "event_type"), ("documents", "lang"), ("labels", "toxic"), ("conversations", "role"), ("customer", "c_mktsegment")):
    _label_counts(_t, _l)


def _example_view(name: str) -> None:
    d = VIEWS[name].d

    def query(s, sf):
        ex = assert_contract(view(s, sf, name))
        total = F.aggregate("x", F.lit(0.0), lambda a, b: a + b)
        return ex.select("row_id", "y", "split", r6(F.col("x")[0]).alias("x_first"), r6(F.col("x")[d - 1]).alias("x_last"), r6(total).alias("x_sum"))

    add(f"example_view_{name}", query, f"with {O.view(name)} select row_id, y, split, {O.r6('x[1]')} as x_first, {O.r6(f'x[{d}]')} as x_last, {O.r6('list_sum(x)')} as x_sum from ex")


for _v in VIEWS:
    _example_view(_v)

_SPLITS = " union all ".join(f"select '{n}' as view, y, split, n_rows from (with {O.view(n)} select y, split, count(*) as n_rows from ex group by y, split)" for n in ("f3", "f4", "f8", "f9order"))
add("split_counts", lambda s, d: _union(*(view(s, d, n).groupBy("y", "split").agg(F.count("*").alias("n_rows")).select(F.lit(n).alias("view"), "y", "split", "n_rows") for n in ("f3", "f4", "f8", "f9order"))), _SPLITS)


def _union(*frames: DataFrame) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


add(
    "scaler_stats",
    lambda s, d: features.fit_scaler(features.raw_view(s, d, "f1"), 4).select(F.posexplode(F.arrays_zip("mean", "sd")).alias("component", "v")).select("component", r6("v.mean").alias("mean"), r6("v.sd").alias("sd")),
    f"with {O.view('f1')} " + " union all ".join(f"select {j} as component, {O.r6(f'm{j + 1}')} as mean, {O.r6(f's{j + 1}')} as sd from scaler" for j in range(4)),
)
add(
    "null_policy_counts",
    lambda s, d: _union(
        *(
            features.null_policy(load(s, d, "events").select("event_id", F.expr("nullif(value, 1.63)").alias("value")), ["value"], mode).agg(F.count("*").alias("n_rows"), r6(F.sum("value")).alias("total")).select(F.lit(mode).alias("mode"), "n_rows", "total")
            for mode in ("drop", "impute_mean")
        )
    ),
    f"""with e as (select nullif(value, 1.63) as value from events)
    select 'drop' as mode, count(*) as n_rows, {O.r6('sum(value)')} as total from e where value is not null
    union all select 'impute_mean', count(*), {O.r6('sum(coalesce(value, (select avg(value) from e)))')} from e""",
)
add(
    "json_field",
    lambda s, d: load(s, d, "events").groupBy("event_type").agg(r6(F.avg(F.get_json_object("props", "$.k").cast("double"))).alias("mean_k")),
    f"select event_type, {O.r6('''avg(cast(json_extract_string(props, '$.k') as double))''')} as mean_k from events group by event_type",
)
add(
    "date_parts",
    lambda s, d: load(s, d, "lineitem").groupBy(F.month("l_shipdate").alias("ship_month"), "l_returnflag").agg(F.count("*").alias("n_rows")),
    "select month(l_shipdate)::int as ship_month, l_returnflag, count(*) as n_rows from lineitem group by 1, 2",
)
add(
    "one_hot",
    lambda s, d: load(s, d, "part").groupBy("p_brand").agg(*(F.sum((F.col("p_type") == t).cast("bigint")).alias(t.lower()) for t in features.PART_TYPES)),
    "select p_brand, " + ", ".join(f"sum(case when p_type = '{t}' then 1 else 0 end)::bigint as {t.lower()}" for t in features.PART_TYPES) + " from part group by p_brand",
)
add(
    "letter_frequency",
    lambda s, d: load(s, d, "documents").groupBy("lang").agg(*(r6(F.avg(F.expr(features._letter(c)))).alias(f"letter_{c}") for c in features.LETTERS[:6])),
    "select lang, " + ", ".join(f"{O.r6(f'avg({features._letter(c)})')} as letter_{c}" for c in features.LETTERS[:6]) + " from documents group by lang",
)
add(
    "left_outer_labels",
    lambda s, d: load(s, d, "documents").select("doc_id", "lang").join(load(s, d, "labels"), "doc_id", "left").groupBy("lang", "quality").agg(F.count("*").alias("n_rows")),
    "select lang, quality, count(*) as n_rows from documents left join labels using (doc_id) group by lang, quality",
)
add(
    "vector_norms",
    lambda s, d: load(s, d, "embeddings").select("vec_id", r6(F.sqrt(L.norm2(F.col("embedding").cast("array<double>")))).alias("norm")),
    f"select vec_id, {O.r6('sqrt(list_inner_product(embedding::double[], embedding::double[]))')} as norm from embeddings",
)
add(
    "component_means",
    lambda s, d: cluster.stats(cluster.by_class(view(s, d, "f4")), 64).select("stratum", F.posexplode("mean").alias("component", "v")).select("stratum", "component", r6("v").alias("mean")),
    f"with {O.view('f4')} select y as stratum, (j - 1)::int as component, {O.r6('avg(x[j])')} as mean from ex cross join (select unnest(range(1, 65)) as j) group by y, j",
)


# ---- strata ---------------------------------------------------------------------------------------


def _strata_by_class(name: str) -> None:
    d = VIEWS[name].d
    add(
        f"strata_by_class_stats_{name}",
        lambda s, sf: cluster.stats(cluster.by_class(cluster.train_rows(view(s, sf, name))), d).select("stratum", "y", "n_i", r6("v_i").alias("v_i"), r6(F.col("mean")[0]).alias("mean_first")),
        f"with {O.view(name)}, {O.train()}, a as (select *, y as stratum from train), {O.stats('a', d)} select stratum, y, n_i, {O.r6('v_i')} as v_i, {O.r6('mean[1]')} as mean_first from strata",
    )


for _v in ("f1", "f3", "f4", "f5", "f7", "f8"):
    _strata_by_class(_v)

_F7 = f"with {O.view('f7')}, {O.train()}, {O.quantile(3, name='a0')}"


def start_f7(s: SparkSession, sf: str, per_class: int = 3, name: str = "f7") -> DataFrame:
    return cluster.quantile_strata(cluster.train_rows(view(s, sf, name)), per_class)


def _rounds_sql(rule: str, n: int) -> str:
    text = _F7
    for i in range(n):
        text += f", {O.stats(f'a{i}', 6, f's{i}')}, {O.assign(f'a{i}', f's{i}', rule, f'a{i + 1}')}"
    return f"{text} select row_id, y, stratum from a{n}"


add("quantile_strata", lambda s, d: start_f7(s, d).select("row_id", "y", "stratum"), f"{_F7} select row_id, y, stratum from a0")
for _name, _rule, _n in (("kmeans_assign_once", "euclid", 1), ("dispersion_assign_once", "dispersion", 1), ("frozen_assign_once", "frozen", 1), ("lloyd_three_rounds", "euclid", 3), ("dispersion_three_rounds", "dispersion", 3), ("frozen_three_rounds", "frozen", 3)):
    add(_name, lambda s, d, rule=_rule, n=_n: cluster.rounds(start_f7(s, d), 6, n, rule, save=saver(s) if n > 1 else None).select("row_id", "y", "stratum"), _rounds_sql(_rule, _n))
add(
    "kmeans_update_once",
    lambda s, d: cluster.stats(cluster.assign(start_f7(s, d), cluster.stats(start_f7(s, d), 6)), 6).select("stratum", "y", "n_i", r6("v_i").alias("v_i"), r6(F.col("mean")[1]).alias("mean_second")),
    _rounds_sql("euclid", 1).replace(" select row_id, y, stratum from a1", f", {O.stats('a1', 6, 's1')} select stratum, y, n_i, {O.r6('v_i')} as v_i, {O.r6('mean[2]')} as mean_second from s1"),
)


def _broken(s: SparkSession, d: str) -> DataFrame:
    """Strata with rows lost, repeated, unplaced and put to another class: what validity has to find."""
    good = start_f7(s, d)
    stratum = F.when(F.col("row_id") % 29 == 0, F.lit(None)).when(F.col("row_id") % 37 == 0, 0).otherwise(F.col("stratum")).cast("int")
    broken = good.where("row_id % 50 != 0").unionByName(good.where("row_id % 41 = 0")).withColumn("stratum", stratum)
    return cluster.validate(broken, cluster.train_rows(view(s, d, "f7")), cluster.stats(good, 6)).withColumn("stratum", F.coalesce("stratum", F.lit(-1)))


add("strata_validity", lambda s, d: cluster.validate(start_f7(s, d), cluster.train_rows(view(s, d, "f7")), cluster.stats(start_f7(s, d), 6)).agg(F.count("*").alias("violations")), "select 0::bigint as violations")
add("strata_violations", _broken, f"""{_F7}, b as (select row_id, y, case when row_id % 29 = 0 then null when row_id % 37 = 0 then 0 else stratum end as stratum
      from (select * from a0 where row_id % 50 <> 0 union all select * from a0 where row_id % 41 = 0)),
    seen as (select stratum, count(*) as n_rows, count(distinct y) as n_classes from b group by stratum), counts as (select stratum, count(*) as n_i from a0 group by stratum),
    found as (select 'mixed' as "check", stratum::int as stratum, n_classes as n from seen where stratum is not null and n_classes > 1
      union all select 'unplaced', null, n_rows from seen where stratum is null
      union all select 'repeated', null, count(*) from (select row_id from b group by row_id having count(*) > 1)
      union all select 'missing', null, count(*) from train where row_id not in (select row_id from b)
      union all select 'miscounted', stratum, coalesce(n_rows, 0) from (select * from seen where stratum is not null) full join counts using (stratum) where n_rows is distinct from n_i)
    select "check", coalesce(stratum, -1)::int as stratum, n from found where n > 0""")
add(
    "dispersion_objective",
    lambda s, d: cluster.dispersion_objective(cluster.stats(start_f7(s, d), 6)).select(r6("objective").alias("objective")),
    f"{_F7}, {O.stats('a0', 6)} select {O.r6('sum(n_i * sqrt(v_i))')} as objective from strata",
)
add(
    "farthest_rows",
    lambda s, d: (lambda a: cluster.farthest(a, cluster.stats(a, 64), 3))(cluster.by_class(cluster.train_rows(view(s, d, "f4")))).select("y", "place", "row_id", r6("dist").alias("dist")),
    f"""with {O.view('f4')}, {O.train()}, a as (select *, y as stratum from train), {O.stats('a', 64)},
    f as (select a.y, row_id, round(list_sum(list_transform(list_zip(x, mean), lambda p: (p[1] - p[2]) * (p[1] - p[2]))), 9) as dist from a join strata using (stratum))
    select y, place::int as place, row_id, {O.r6('dist')} as dist from (select *, row_number() over (partition by y order by dist desc, row_id) as place from f) where place <= 3""",
)
add("random_strata", lambda s, d: cluster.random_strata(cluster.train_rows(view(s, d, "f8")), 2).groupBy("stratum").agg(F.count("*").alias("n_rows")), f"with {O.view('f8')}, {O.train()} select (y * 2 + {O.hashed(chr(39) + 'strata' + chr(39), '1', 'row_id')} % 2)::int as stratum, count(*) as n_rows from train group by 1")
_BUILT = f"""with {O.view('f8')}, {O.train()}, {O.built(2, 'dispersion', 4, 3, 0, 'one', 'b')}, {O.built(2, 'dispersion', 4, 3, 1, 'two', 'c')},
    falls as (select (select sum(n_i * sqrt(v_i)) from cs) < (select sum(n_i * sqrt(v_i)) from bs) - 1e-12 as second), assigned as (select * from one where not (select second from falls) union all select * from two where (select second from falls)), {O.stats('assigned', 3)}"""
add("build_dispersion_f8", lambda s, d: cluster.stats(cluster.build(view(s, d, "f8"), 3, StrataConfig("dispersion", 10, iters=4, restarts=2), saver(s)), 3).select("stratum", "y", "n_i", r6("v_i").alias("v_i")), f"{_BUILT} select stratum, y, n_i, {O.r6('v_i')} as v_i from strata")
for _init in ("random", "plusplus"):
    add(f"build_kmeans_{_init}", lambda s, d, init=_init: cluster.stats(cluster.build(view(s, d, "f8"), 3, StrataConfig("kmeans", 10, init=init, iters=3, fit_fraction=0.5, tol=1e-3), saver(s)), 3).select("stratum", "y", "n_i", r6("v_i").alias("v_i")))

# ---- allocation -----------------------------------------------------------------------------------

_A8 = f"with {O.view('f8')}, {O.train()}, {O.quantile(2)}, {O.stats('assigned', 3)}"
_B = 20


def strata_f8(s: SparkSession, sf: str) -> DataFrame:
    """A row per stratum, kept, as allocation looks at it several times."""
    return saver(s)(cluster.stats(cluster.quantile_strata(cluster.train_rows(view(s, sf, "f8")), 2), 3))


def _share(kind: str) -> str:
    w = {"dispersion": "n_i * sqrt(v_i)", "proportional": "n_i::double", "equal": "1.0::double"}[kind]
    return f"shares as (select *, {w} / sum({w}) over () as share, count(*) over () as k from strata)"


for _kind in ("dispersion", "proportional", "equal"):
    add(
        f"alloc_{_kind}_real" if _kind == "dispersion" else f"alloc_{_kind}",
        lambda s, d, kind=_kind: allocate.real(strata_f8(s, d), _B, kind).select("stratum", "n_i", r6("b_real").alias("b_real")),
        f"{_A8}, {_share(_kind)} select stratum, n_i, {O.r6(f'share * {_B}')} as b_real from shares",
    )
add("alloc_greedy", lambda s, d: allocate.round_greedy(strata_f8(s, d), _B).select("stratum", "n_i", "b_i"), f"{_A8}, {O.greedy('strata', _B)} select stratum, n_i, b_i from counted")
add(
    "alloc_remainder",
    lambda s, d: allocate.round_remainder(strata_f8(s, d), _B).select("stratum", "n_i", "b_i"),
    f"""{_A8}, {_share('dispersion')}, x as (select *, round(share * ({_B} - k), 9) as spare from shares),
    y as (select *, row_number() over (order by round(spare - floor(spare), 9) desc, stratum) as place, {_B} - k - sum(floor(spare)) over () as rest from x)
    select stratum, n_i, (1 + floor(spare) + case when place <= rest then 1 else 0 end)::int as b_i from y""",
)
add(
    "alloc_systematic",
    lambda s, d: allocate.round_systematic(strata_f8(s, d), _B, 7).select("stratum", "n_i", "b_i"),
    f"""{_A8}, {_share('dispersion')}, x as (select *, round(share * ({_B} - k), 9) as spare, round({O.hashed("'systematic'", '7')} / 4503599627370496.0::double, 6) as u from shares),
    y as (select *, round(sum(spare) over (order by stratum rows between unbounded preceding and current row), 6) as upto,
      coalesce(round(sum(spare) over (order by stratum rows between unbounded preceding and 1 preceding), 6), 0) as before from x)
    select stratum, n_i, (1 + floor(upto + u) - floor(before + u))::int as b_i from y""",
)
add(
    "alloc_zero_dispersion",
    lambda s, d: allocate.round_greedy(strata_f8(s, d).withColumn("v_i", F.lit(0.0)), _B).select("stratum", "n_i", "b_i"),
    f"{_A8}, flat as (select stratum, y, n_i, 0.0::double as v_i from strata), {O.greedy('flat', _B)} select stratum, n_i, b_i from counted",
)
add(
    "surrogate_bound",
    lambda s, d: allocate.surrogate(allocate.round_greedy(strata_f8(s, d), _B)).select(r6("bound").alias("bound")),
    f"{_A8}, {O.greedy('strata', _B)} select {O.r6('sum(n_i::double * n_i * v_i / b_i) / (sum(n_i) * sum(n_i))')} as bound from counted",
)
add(
    "variance_ratio_by_allocation",
    lambda s, d: (
        lambda st: _union(
            *(allocate.surrogate(allocate.real(st, _B, kind), "b_real").select(F.lit(kind).alias("kind"), r6("bound").alias("bound")) for kind in ("dispersion", "proportional", "equal"))
        )
    )(strata_f8(s, d)),
    " union all ".join(f"select '{k}' as kind, bound from ({_A8}, {_share(k)} select {O.r6(f'sum(n_i::double * n_i * v_i / (share * {_B})) / (sum(n_i) * sum(n_i))')} as bound from shares)" for k in ("dispersion", "proportional", "equal")),
)

# ---- draws ----------------------------------------------------------------------------------------

_F4 = f"with {O.view('f4')}, {O.train()}, assigned as (select *, y as stratum from train)"
_F4S = f"{_F4}, {O.stats('assigned', 64)}, {O.greedy('strata', 20)}, {O.positions('assigned')}"


def f4_indexed(s: SparkSession, sf: str) -> DataFrame:
    return index.dense_position(cluster.by_class(cluster.train_rows(view(s, sf, "f4"))))


def f4_plan(s: SparkSession, sf: str, b: int = 20) -> StratumPlan:
    return StratumPlan.from_frame(allocate.round_greedy(cluster.stats(cluster.by_class(cluster.train_rows(view(s, sf, "f4"))), 64), b), b, 10)


def f4_single(s: SparkSession, sf: str, b: int) -> StratumPlan:
    return StratumPlan.single(cluster.train_rows(view(s, sf, "f4")).count(), b)


add("dense_position", lambda s, d: f4_indexed(s, d).select("row_id", "stratum", "pos"), f"{_F4}, {O.positions('assigned')} select row_id, stratum, pos from indexed")
add("uniform_draws", lambda s, d: sampling.plan_chunk(s, f4_single(s, d, 20), 1, 1, 5).select("t", "r", "pos", r6("draw_weight").alias("draw_weight")), f"{_F4}, {O.single('train', 20)}, {O.draws('counted', 1, 1, 5)} select t, r, pos, {O.r6('draw_weight')} as draw_weight from draws")
add("stratified_draws", lambda s, d: sampling.plan_chunk(s, f4_plan(s, d), 1, 1, 5).select("t", "stratum", "r", "pos", r6("draw_weight").alias("draw_weight")), f"{_F4S}, {O.draws('counted', 1, 1, 5)} select t, stratum, r, pos, {O.r6('draw_weight')} as draw_weight from draws")
for _how in ("broadcast", "merge", "shuffle_hash"):
    add(
        "drawn_rows_with_repeats" if _how == "broadcast" else f"drawn_rows_{_how}",
        lambda s, d, how=_how: sampling.fetch(sampling.plan_chunk(s, f4_plan(s, d), 1, 1, 3), f4_indexed(s, d), how).select("t", "stratum", "r", "row_id"),
        f"{_F4S}, {O.draws('counted', 1, 1, 3)} select t, stratum, r, row_id from draws join indexed using (stratum, pos)",
    )
add("draw_counts_per_stratum", lambda s, d: sampling.plan_chunk(s, f4_plan(s, d), 1, 1, 50).groupBy("stratum").agg(F.count("*").alias("draws"), F.countDistinct("pos").alias("rows")), f"{_F4S}, {O.draws('counted', 1, 1, 50)} select stratum, count(*) as draws, count(distinct pos) as rows from draws group by stratum")
add(
    "draw_overlap",
    lambda s, d: sampling.overlap(sampling.plan_chunk(s, f4_plan(s, d), 1, 1, 50), sampling.plan_chunk(s, f4_plan(s, d), 2, 1, 50)),
    f"{_F4S}, {O.draws('counted', 1, 1, 50, 'one')}, {O.draws('counted', 2, 1, 50, 'two')} select t, stratum, pos from one intersect select t, stratum, pos from two",
)
add("anti_never_drawn", lambda s, d: sampling.never_drawn(f4_indexed(s, d), sampling.plan_chunk(s, f4_plan(s, d), 1, 1, 50)).select("row_id", "stratum"), f"{_F4S}, {O.draws('counted', 1, 1, 50)} select row_id, stratum from indexed i where not exists (select 1 from draws d where d.stratum = i.stratum and d.pos = i.pos)")
add("semi_ever_drawn", lambda s, d: sampling.ever_drawn(f4_indexed(s, d), sampling.plan_chunk(s, f4_plan(s, d), 1, 1, 50)).groupBy("stratum").agg(F.count("*").alias("rows")), f"{_F4S}, {O.draws('counted', 1, 1, 50)} select stratum, count(*) as rows from indexed i where exists (select 1 from draws d where d.stratum = i.stratum and d.pos = i.pos) group by stratum")
add("without_replacement", lambda s, d: sampling.without_replacement(f4_indexed(s, d), f4_plan(s, d), 3, 1).select("stratum", "r", "row_id"), f"{_F4S} select stratum, r::int as r, row_id from (select i.*, b_i, row_number() over (partition by i.stratum order by {O.hashed('3', '1', 'i.stratum', 'row_id')}, row_id) as r from indexed i join counted c on c.stratum = i.stratum) where r <= b_i")
add("bernoulli_sample", lambda s, d: sampling.bernoulli(cluster.by_class(cluster.train_rows(view(s, d, "f4"))), {c: 0.5 for c in range(10)}).select("row_id", "stratum"), f"{_F4} select row_id, stratum from assigned where {O.hashed(chr(39) + 'bernoulli' + chr(39), '1', 'row_id')} < 2251799813685248")
add(
    "scan_draws",
    lambda s, d: sampling.by_scan(cluster.by_class(cluster.train_rows(view(s, d, "f4"))), f4_plan(s, d), 3, 1, 5).select("t", "stratum", "row_id", "k", r6("draw_weight").alias("draw_weight")),
    f"""{_F4S}, chances as (select stratum, n_i, list_transform(range(0, 32), lambda k: list_sum(list_transform(range(0, k + 1), lambda j: exp(-rate + j * ln(rate) - lgamma(j + 1))))) as chances from (select *, b_i * 5 / n_i::double as rate from counted)),
    hit as (select a.row_id, stratum, n_i, len(list_filter(chances, lambda c: c <= {O.hashed("'poisson'", '3', '1', 'a.row_id')} / 4503599627370496.0::double)) as times from assigned a join chances using (stratum)),
    each_draw as (select row_id, stratum, n_i, unnest(range(1, times + 1)) as k from hit where times > 0),
    placed as (select *, (1 + {O.hashed("'step'", '3', '1', 'row_id', 'k')} % 5)::int as t from each_draw)
    select t, stratum, row_id, k::int as k, {O.r6('n_i / ((select count(*) from train)::double * count(*) over (partition by t, stratum))')} as draw_weight from placed""",
)
add("leakage_check", lambda s, d: view(s, d, "f4").where("split = 'train'").select("row_id").intersect(view(s, d, "f4").where("split = 'test'").select("row_id")), f"with {O.view('f4')} select row_id from ex where split = 'train' intersect select row_id from ex where split = 'test'")
add("except_test_rows", lambda s, d: view(s, d, "f8").select("y", "split").exceptAll(view(s, d, "f8").where("split = 'test'").select("y", "split")).groupBy("y", "split").agg(F.count("*").alias("n_rows")), f"with {O.view('f8')} select y, split, count(*) as n_rows from ex where split <> 'test' group by y, split")

# ---- gradients ------------------------------------------------------------------------------------

_OUT = f"select cls, component, {O.r6('g')} as g from"


def _gradient(df: DataFrame) -> DataFrame:
    return df.select("cls", "component", r6("g").alias("g"))


def _full_sql(base: str, w: str, m: int, d: int) -> str:
    return f"{base}, {O.residuals('train', w, m)}, n as (select count(*) as n from train), g as ({O.cells('res', m, d)}) {_OUT} (select cls, component, g / n as g from g cross join n)"


add("full_gradient_origin", lambda s, d: _gradient(variance.full_gradient(cluster.train_rows(view(s, d, "f4")), zeros(10, 64))), _full_sql(_F4, O.literal(zeros(10, 64)), 10, 64))
add("full_gradient_fixed_w", lambda s, d: _gradient(variance.full_gradient(cluster.train_rows(view(s, d, "f4")), fixed_w(10, 64))), _full_sql(_F4, O.literal(fixed_w(10, 64)), 10, 64))
add("full_gradient_f1", lambda s, d: _gradient(variance.full_gradient(cluster.train_rows(view(s, d, "f1")), fixed_w(2, 4))), _full_sql(f"with {O.view('f1')}, {O.train()}", O.literal(fixed_w(2, 4)), 2, 4))


def _step(s: SparkSession, d: str, plan: StratumPlan, indexed: DataFrame) -> DataFrame:
    return _gradient(variance.draw_gradient(sampling.fetch(sampling.plan_chunk(s, plan, 1, 1, 1), indexed, "broadcast"), fixed_w(10, 64), 0.0, []))


def one_stratum(ex: DataFrame) -> DataFrame:
    return descent.indexed_uniform(ex)


_F4U = f"{_F4}, u as (select row_id, y, x, 0 as stratum from train), {O.positions('u')}"


def _step_sql(base: str, counted: str) -> str:
    return f"{base}, {counted}{O.draws('counted', 1, 1, 1)}, f as (select d.draw_weight, i.y, i.x from draws d join indexed i using (stratum, pos)), {O.residuals('f', O.literal(fixed_w(10, 64)), 10)} {_OUT} ({O.cells('res', 10, 64, 'draw_weight')})"


add("uniform_step_gradient", lambda s, d: _step(s, d, f4_single(s, d, 20), one_stratum(view(s, d, "f4"))), _step_sql(_F4U, f"{O.single('train', 20)}, "))
add("single_step_gradient", lambda s, d: _step(s, d, f4_single(s, d, 1), one_stratum(view(s, d, "f4"))), _step_sql(_F4U, f"{O.single('train', 1)}, "))
add("stratified_step_gradient", lambda s, d: _step(s, d, f4_plan(s, d), f4_indexed(s, d)), _step_sql(_F4S, ""))
add(
    "gradient_norms",
    lambda s, d: (lambda r: cluster.train_rows(view(s, d, "f4")).select("row_id", r6(L.norm2(r) * L.norm2(F.col("x"))).alias("norm2")))(L.softmax_residual(L.logits(F.col("x"), fixed_w(10, 64)), F.col("y"))),
    f"{_F4}, {O.residuals('train', O.literal(fixed_w(10, 64)), 10)} select row_id, {O.r6('list_inner_product(r, r) * list_inner_product(x, x)')} as norm2 from res",
)

# ---- variance -------------------------------------------------------------------------------------


def _within_sql(base: str, source: str, w: str, m: int, d: int) -> str:
    return f"""{base}, {O.residuals(source, w, m)}, sq as (select stratum, count(*) as cnt, sum(list_inner_product(r, r) * list_inner_product(x, x)) as squares from res group by stratum),
      g as ({O.cells('res', m, d, keys='stratum')}), ss as (select stratum, cnt, squares - g2 / cnt as ss from sq join (select stratum, sum(g * g) as g2 from g group by stratum) using (stratum))"""


def _strat_variance_sql(w: L.Weights) -> str:
    return f"{_within_sql(_F4S, 'assigned', O.literal(w), 10, 64)} select {O.r6('sum(cnt::double / b_i * ss) / (sum(cnt) * sum(cnt))')} as variance from ss join counted using (stratum)"


def _unif_variance_sql(w: L.Weights) -> str:
    return f"{_within_sql(_F4U, 'u', O.literal(w), 10, 64)} select {O.r6('sum(ss / cnt) / 20')} as variance from ss"


def f4_assigned(s: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    a = cluster.by_class(cluster.train_rows(view(s, sf, "f4")))
    return a, allocate.round_greedy(cluster.stats(a, 64), 20)


add("variance_uniform_origin", lambda s, d: variance.uniform(cluster.train_rows(view(s, d, "f4")), zeros(10, 64), 20).select(r6("variance").alias("variance")), _unif_variance_sql(zeros(10, 64)))
add("variance_stratified_origin", lambda s, d: (lambda a, c: variance.stratified(a, zeros(10, 64), c))(*f4_assigned(s, d)).select(r6("variance").alias("variance")), _strat_variance_sql(zeros(10, 64)))
add("variance_origin_closed_form", lambda s, d: variance.at_origin(f4_assigned(s, d)[1], 10).select(r6("variance").alias("variance")), f"{_F4S} select {O.r6('0.9::double * sum(n_i::double * n_i * v_i / b_i) / (sum(n_i) * sum(n_i))')} as variance from counted")
add(
    "variance_at_fixed_w",
    lambda s, d: _union(
        (lambda a, c: variance.stratified(a, fixed_w(10, 64), c))(*f4_assigned(s, d)).select(F.lit("stratified").alias("sampler"), r6("variance").alias("variance")),
        variance.uniform(cluster.train_rows(view(s, d, "f4")), fixed_w(10, 64), 20).select(F.lit("uniform").alias("sampler"), r6("variance").alias("variance")),
    ),
    f"select 'stratified' as sampler, variance from ({_strat_variance_sql(fixed_w(10, 64))}) union all select 'uniform', variance from ({_unif_variance_sql(fixed_w(10, 64))})",
)
add(
    "centroid_bound",
    lambda s, d: (lambda a, c: variance.at_centroid(a, fixed_w(10, 64), c))(*f4_assigned(s, d)).select(r6("bound").alias("bound")),
    f"""{_F4S}, {O.residuals('assigned', O.literal(fixed_w(10, 64)), 10)}, cm as (select stratum, y, mean as x, mean, n_i, b_i from counted), {O.residuals('cm', O.literal(fixed_w(10, 64)), 10, 'cen')}
    select {O.r6('''sum(n_i::double / b_i * (list_inner_product(a.r, a.r) * list_inner_product(a.x, a.x) + list_inner_product(c.r, c.r) * list_inner_product(c.x, c.x)
      - 2 * list_inner_product(a.r, c.r) * list_inner_product(a.x, c.x))) / (count(*)::double * count(*))''')} as bound from res a join cen c using (stratum)""",
)
_LEADS = " union all ".join(f"select y, x, r, lead(x, {k}) over w as x2, lead(r, {k}) over w as r2 from placed window w as (partition by y order by place, row_id)" for k in range(1, 5))
add("lipschitz_features", lambda s, d: variance.lipschitz_x(view(s, d, "f4"), fixed_w(10, 64)).select(r6("lipschitz").alias("lipschitz")), f"""with {O.view('f4')}, {O.residuals('ex', O.literal(fixed_w(10, 64)), 10)}, placed as (select *, {O.hashed("'pair'", '1', 'row_id')} as place from res), pairs as ({_LEADS}),
    gaps as (select *, list_inner_product(list_transform(x, lambda v, i: v - x2[i]), list_transform(x, lambda v, i: v - x2[i])) as bottom from pairs where x2 is not null)
    select {O.r6("""max(sqrt(greatest(list_inner_product(r, r) * list_inner_product(x, x) + list_inner_product(r2, r2) * list_inner_product(x2, x2) - 2 * list_inner_product(r, r2) * list_inner_product(x, x2), 0) / bottom))""")} as lipschitz from gaps where bottom > 1e-12""")
add(
    "variance_two_passes",
    lambda s, d: variance.centred_within(f4_assigned(s, d)[0], fixed_w(10, 64)).select("stratum", "cnt", r6("ss").alias("ss")),
    f"{_within_sql(_F4S, 'assigned', O.literal(fixed_w(10, 64)), 10, 64)} select stratum, cnt, {O.r6('ss')} as ss from ss",
)
_REPLAYS = 40


def _resampled(s: SparkSession, d: str) -> DataFrame:
    drawn = sampling.fetch(sampling.plan_chunk(s, f4_plan(s, d), 5, 1, _REPLAYS), f4_indexed(s, d), "broadcast")
    return variance.resampled(drawn, variance.full_gradient(cluster.train_rows(view(s, d, "f4")), zeros(10, 64)), zeros(10, 64)).select(r6("variance").alias("variance"), r6("std_error").alias("std_error"))


add(
    "variance_resampled",
    _resampled,
    f"""{_F4S}, {O.draws('counted', 5, 1, _REPLAYS)}, f as (select d.t, d.draw_weight, i.y, i.x from draws d join indexed i using (stratum, pos)), {O.residuals('f', O.literal(zeros(10, 64)), 10)},
    g as ({O.cells('res', 10, 64, 'draw_weight', 't')}), {O.residuals('train', O.literal(zeros(10, 64)), 10, 'all_r')}, full_g as (select cls, component, g / (select count(*) from train) as full_v from ({O.cells('all_r', 10, 64)})),
    d2 as (select t, sum((g - full_v) * (g - full_v)) as d2 from g join full_g using (cls, component) group by t)
    select {O.r6('avg(d2)')} as variance, {O.r6('stddev_samp(d2) / sqrt(count(*))')} as std_error from d2""",
)

# ---- measures -------------------------------------------------------------------------------------

_W1 = O.literal(fixed_w(2, 4))
_F1 = f"with {O.view('f1')}, {O.train()}"
add("objective_at_fixed_w", lambda s, d: measures.objective(cluster.train_rows(view(s, d, "f1")), fixed_w(2, 4), 0.1).select(r6("objective").alias("objective")), f"{_F1}, {O.residuals('train', _W1, 2)} select {O.r6(f'''avg(list_max(l) + ln(list_sum(e)) - l[y + 1]) + {0.05 * sum(v * v for r in fixed_w(2, 4) for v in r)!r}::double''')} as objective from res")
add("objective_f4", lambda s, d: measures.objective(cluster.train_rows(view(s, d, "f4")), fixed_w(10, 64), 0.0).select(r6("objective").alias("objective")), f"{_F4}, {O.residuals('train', O.literal(fixed_w(10, 64)), 10)} select {O.r6('avg(list_max(l) + ln(list_sum(e)) - l[y + 1])')} as objective from res")
_TEST1 = f"with {O.view('f1')}, test as (select row_id, y, x from ex where split = 'test'), {O.residuals('test', _W1, 2)}"
add("error_at_fixed_w", lambda s, d: measures.error_rate(view(s, d, "f1").where("split = 'test'"), fixed_w(2, 4)).select(r6("error").alias("error")), f"{_TEST1} select {O.r6('avg(case when list_position(l, list_max(l)) - 1 <> y then 1.0::double else 0 end)')} as error from res")
add("confusion_at_fixed_w", lambda s, d: measures.confusion(view(s, d, "f1").where("split = 'test'"), fixed_w(2, 4)), f"{_TEST1} select y, (list_position(l, list_max(l)) - 1)::int as cls, count(*) as n_rows from res group by 1, 2")


def _epoch_axis(s: SparkSession, d: str) -> DataFrame:
    """Steps, their epochs and row gradients over the training rows of the events."""
    n = cluster.train_rows(view(s, d, "f8")).count()
    return s.range(1, 101).select(F.col("id").alias("t"), r6(measures.epoch(F.col("id"), 10, n)).alias("epoch"), *(F.lit(measures.gradient_evals(k, n, 10)).cast("bigint").alias(f"evals_{k}") for k in ("full", "single", "uniform", "dynamic")))


add("epoch_axis", _epoch_axis, f"with {O.view('f8')}, {O.train()}, rows_of as (select count(*) as n from train) select t::bigint as t, {O.r6('t * 10 / n::double')} as epoch, n::bigint as evals_full, 1::bigint as evals_single, 10::bigint as evals_uniform, (n + 10)::bigint as evals_dynamic from rows_of cross join (select unnest(range(1, 101)) as t)")
_TRACE_SQL = """trace as (select event_type as workload, case when event_id % 2 = 0 then 'uniform' else 'stratified' end as sampler, (user_id % 3 + 1)::int as seed, (hour(ts) // 6 + 1)::int as t, avg(value) as objective
    from events group by 1, 2, 3, 4)"""


def trace_of(s: SparkSession, d: str) -> DataFrame:
    """Events as traces: a type is a workload, halves of the ids are samplers, users fall to three seeds, a quarter of the day is a step."""
    sampler = F.when(F.col("event_id") % 2 == 0, "uniform").otherwise("stratified")
    keys = [F.col("event_type").alias("workload"), sampler.alias("sampler"), (F.col("user_id") % 3 + 1).cast("int").alias("seed"), (F.floor(F.hour("ts") / 6) + 1).cast("int").alias("t")]
    return load(s, d, "events").groupBy(*keys).agg(F.avg("value").alias("objective"))


add("seed_summary", lambda s, d: measures.summarise(trace_of(s, d), ["workload", "sampler", "t"], ["objective"]).select("workload", "sampler", "t", "runs", *(r6(f"objective_{k}").alias(f"objective_{k}") for k in ("mean", "sd", "min", "max"))), f"with {_TRACE_SQL} select workload, sampler, t, count(*) as runs, {O.r6('avg(objective)')} as objective_mean, {O.r6('stddev_samp(objective)')} as objective_sd, {O.r6('min(objective)')} as objective_min, {O.r6('max(objective)')} as objective_max from trace group by 1, 2, 3")
add("stability_trace", lambda s, d: measures.stability(trace_of(s, d), ["workload", "sampler", "seed"], "objective").select("workload", "sampler", "seed", r6("mean_change").alias("mean_change")), f"with {_TRACE_SQL}, c as (select *, abs(objective - lag(objective) over (partition by workload, sampler, seed order by t)) as change from trace) select workload, sampler, seed, {O.r6('avg(change)')} as mean_change from c group by 1, 2, 3")
add("rollup_trace", lambda s, d: trace_of(s, d).rollup("workload", "sampler").agg(F.count("*").alias("n_rows"), r6(F.avg("objective")).alias("objective")), f"with {_TRACE_SQL} select workload, sampler, count(*) as n_rows, {O.r6('avg(objective)')} as objective from trace group by rollup (workload, sampler)")
add("cube_labels", lambda s, d: load(s, d, "documents").cube("lang", "source").agg(F.count("*").alias("n_rows")), "select lang, source, count(*) as n_rows from documents group by cube (lang, source)")
add("best_iterate", lambda s, d: trace_of(s, d).groupBy("workload", "sampler", "seed").agg(F.min_by("t", F.struct("objective", "t")).alias("best_t")), f"with {_TRACE_SQL} select workload, sampler, seed, t as best_t from (select *, row_number() over (partition by workload, sampler, seed order by objective, t) as place from trace) where place = 1")
add("rate_slope", lambda s, d: measures.rate_slope(trace_of(s, d).withColumn("gap", F.col("objective"))).select(r6("slope").alias("slope")), f"with {_TRACE_SQL} select {O.r6('regr_slope(ln(objective), ln(t))')} as slope from trace where objective > 0")


def _asof(s: SparkSession, d: str) -> DataFrame:
    """Largest values by the minute on the even events' epochs beside those by the hour on the odd events' coarser ones."""
    events = load(s, d, "events")
    curve = lambda half, place, over: events.where(F.col("event_id") % 2 == half).groupBy((place / over).alias("epoch")).agg(F.max("value").alias("v"))
    left, right = curve(0, (F.hour("ts") * 60 + F.minute("ts")) * 10, 10000.0), curve(1, F.hour("ts") * 48, 1000.0)
    return measures.align_epochs(left, right, "v").select("epoch", r6("left_value").alias("left_value"), r6("right_value").alias("right_value"))


add(
    "asof_epoch_alignment",
    _asof,
    f"""with a as (select (hour(ts) * 60 + minute(ts)) * 10 / 10000.0::double as epoch, max(value) as v from events where event_id % 2 = 0 group by 1), b as (select hour(ts) * 48 / 1000.0::double as epoch, max(value) as v from events where event_id % 2 = 1 group by 1)
    select a.epoch, {O.r6('a.v')} as left_value, {O.r6('(select b.v from b where b.epoch <= a.epoch order by b.epoch desc limit 1)')} as right_value from a""",
)
add("pivot_flags", lambda s, d: load(s, d, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1))).select("l_returnflag", F.col("F").alias("status_f"), F.col("O").alias("status_o")), "select l_returnflag, count(*) filter (l_linestatus = 'F') as status_f, count(*) filter (l_linestatus = 'O') as status_o from lineitem group by 1")
add("moving_average_events", lambda s, d: measures.moving_average(load(s, d, "events").select("user_id", "event_id", "ts", "value"), ["user_id"], "value", ["ts", "event_id"]).select("event_id", r6("moving").alias("moving")), f"select event_id, {O.r6('avg(value) over (partition by user_id order by ts, event_id rows between 4 preceding and current row)')} as moving from events")

# ---- training -------------------------------------------------------------------------------------

_GD = DescentConfig(lam=0.1, b=10, steps=3, schedule="constant", eta=0.5, eval_every=1)


def _weights(s: SparkSession, iterates: list[np.ndarray]) -> DataFrame:
    rows = [(t, c, j, float(w[c, j])) for t, w in enumerate(iterates, 1) for c in range(w.shape[0]) for j in range(w.shape[1])]
    return s.createDataFrame(rows, "t int, cls int, component int, w double")


def _out(df: DataFrame) -> DataFrame:
    return df.select("t", "cls", "component", r6("w").alias("w"))


def _long(models: DataFrame) -> DataFrame:
    return models.select("t", "cls", F.posexplode("w").alias("component", "w"))


def _update(t: int, source: str, m: int, d: int, weight: str, lam: float, eta: float) -> str:
    """CTEs that end with w{t}: the weights after a step from w{t-1} over source."""
    w = f"(select w from w{t - 1})"
    return f"""{O.residuals(source, w, m, f'res{t}')}, g{t} as ({O.cells(f'res{t}', m, d, weight)}),
      w{t} as (select list(row order by cls) as w from (select cls, list(v order by component) as row
        from (select cls, component, {w}[cls + 1][component + 1] - {eta!r}::double * (g + {lam!r}::double * {w}[cls + 1][component + 1]) as v from g{t}) group by cls))"""


def _iterates_sql(n: int, m: int, d: int) -> str:
    return " union all ".join(f"select {t} as t, (c - 1)::int as cls, (j - 1)::int as component, w[c][j] as w from w{t} cross join (select unnest(range(1, {m + 1})) as c) cross join (select unnest(range(1, {d + 1})) as j)" for t in range(1, n + 1))


_START = f"w0 as (select {O.literal(zeros(2, 4))} as w)"
_GD_SQL = f"{_F1}, {_START}" + "".join(f", {_update(t, 'train', 2, 4, '1.0::double / (select count(*) from train)', 0.1, 0.5)}" for t in range(1, 4))
add("gd_3_steps", lambda s, d: _out(_weights(s, descent.full_gradient_descent(saver(s)(view(s, d, "f1")), np.zeros((2, 4)), _GD))), f"{_GD_SQL} select t, cls, component, {O.r6('w')} as w from ({_iterates_sql(3, 2, 4)})")
_SGD = replace(_GD, steps=5)
_BASE = {
    "uniform": f"{_F1}, u as (select row_id, y, x, 0 as stratum from train), {O.positions('u')}, {O.single('train', 10)}",
    "single": f"{_F1}, u as (select row_id, y, x, 0 as stratum from train), {O.positions('u')}, {O.single('train', 1)}",
    "stratified": f"{_F1}, assigned as (select *, y as stratum from train), {O.stats('assigned', 4)}, {O.greedy('strata', 10)}, {O.positions('assigned')}",
}


def _sgd_sql(sampler: str) -> str:
    text = f"{_BASE[sampler]}, {O.draws('counted', 1, 1, 5)}, fetched as materialized (select d.t, d.draw_weight, i.y, i.x from draws d join indexed i using (stratum, pos)), {_START}"
    for t in range(1, 6):
        text += f", f{t} as (select draw_weight, y, x from fetched where t = {t}), {_update(t, f'f{t}', 2, 4, 'draw_weight', 0.1, 0.5)}"
    return text


def chain(s: SparkSession, d: str, sampler: str, config: DescentConfig = _SGD) -> DataFrame:
    save = saver(s)
    ex = save(view(s, d, "f1"))  # read once for strata, counts and positions
    if sampler == "stratified":
        assigned, _, plan = descent.prepare(ex, 4, 2, config.b, StrataConfig("by_class"), AllocationConfig(), save)
        indexed = index.dense_position(assigned, index.buckets_for(plan.n))
    else:
        b = 1 if sampler == "single" else config.b
        plan, indexed = StratumPlan.single(cluster.train_rows(ex).count(), b), one_stratum(ex)
    return descent.run_chains([descent.Run("run", indexed, plan, config, np.zeros((2, 4)))], keep_all=True)


for _s in ("uniform", "stratified", "single"):
    add(f"sgd_{_s}_5_steps", lambda s, d, sampler=_s: _out(_long(chain(s, d, sampler))), f"{_sgd_sql(_s)} select t, cls, component, {O.r6('w')} as w from ({_iterates_sql(5, 2, 4)})")
_IT = f"{_sgd_sql('stratified')}, it as ({_iterates_sql(5, 2, 4)})"
_AVERAGES = {
    "last": (averaging.last, "arg_max(w, t)", "it"),
    "mean": (averaging.mean, "avg(w)", "it"),
    "suffix": (lambda it: averaging.suffix(it, 0.4, 5), "avg(w)", "(select * from it where t > 3)"),
}
for _k, (_f, _agg, _src) in _AVERAGES.items():
    add(f"{_k}_average", lambda s, d, f=_f: f(_long(chain(s, d, "stratified"))).select("cls", "component", r6("w").alias("w")), f"{_IT} select cls, component, {O.r6(_agg)} as w from {_src} group by cls, component")
_RHO = [(3 + 1) / (t + 3) for t in range(1, 6)]
_POLY = [r * float(np.prod([1 - q for q in _RHO[i + 1 :]])) for i, r in enumerate(_RHO)]
add("polynomial_average", lambda s, d: averaging.polynomial(_long(chain(s, d, "stratified")), 3).select("cls", "component", r6("w").alias("w")), f"{_IT} select cls, component, {O.r6('sum(w * case t ' + ' '.join(f'when {t} then {v!r}::double' for t, v in enumerate(_POLY, 1)) + ' end)')} as w from it group by cls, component")
_F7D = f"with {O.view('f7')}, {O.train()}, {O.built(2, 'euclid', 2, 6, name='k0')}, w0 as (select {O.literal(zeros(2, 6))} as w)"


def _dynamic_sql(refresh: str, every: int, steps: int, b: int = 8) -> str:
    """Strata and counts of each refresh, then its steps."""
    text, strata = _F7D, "k0"
    for first in range(1, steps + 1, every):
        w = f"(select w from w{first - 1})"
        if refresh == "both":
            text += f", {O.moved(strata, w, 2, 6, f'k{first}')}"
            strata = f"k{first}"
        last = min(first + every - 1, steps)
        text += f", {O.gradient_counts(strata, w, 2, 6, b, f'c{first}')}, {O.positions(strata, f'i{first}')}, {O.draws(f'c{first}', 1, first, last, f'd{first}')}"
        for t in range(first, last + 1):
            text += f", f{t} as (select d.draw_weight, i.y, i.x from d{first} d join i{first} i using (stratum, pos) where t = {t}), {_update(t, f'f{t}', 2, 6, 'draw_weight', 0.1, 0.5)}"
    return f"{text} select t, cls, component, {O.r6('w')} as w from ({_iterates_sql(steps, 2, 6)})"


def _dynamic(refresh: str, every: int, steps: int):
    config = DescentConfig(0.1, 8, steps, "constant", 0.5)
    return lambda s, d: _out(_weights(s, descent.dynamic(view(s, d, "f7"), 6, 2, config, StrataConfig("kmeans", 4, iters=2), DynamicConfig(every, refresh, iters=1), saver(s))))


add("dynamic_2_steps", _dynamic("both", 1, 2), _dynamic_sql("both", 1, 2))
add("dynamic_counts_only", _dynamic("counts", 2, 4), _dynamic_sql("counts", 2, 4))


def _inverse(s: SparkSession, d: str) -> DataFrame:
    """The published step 1 / (lam t) over k-means strata."""
    assigned, _, plan = descent.prepare(view(s, d, "f7"), 6, 2, 8, StrataConfig("kmeans", 4, iters=2), AllocationConfig(), saver(s))
    run = descent.Run("run", saver(s)(index.dense_position(assigned)), plan, DescentConfig(0.1, 8, 5, "inverse", eval_every=1), np.zeros((2, 6)))
    return _out(_long(descent.run_chains([run], keep_all=True)))


_INVERSE = f"{_F7D}, {O.stats('k0', 6)}, {O.greedy('strata', 8)}, {O.positions('k0')}, {O.draws('counted', 1, 1, 5)}, fetched as materialized (select d.t, d.draw_weight, i.y, i.x from draws d join indexed i using (stratum, pos))"
for _t in range(1, 6):
    _INVERSE += f", f{_t} as (select draw_weight, y, x from fetched where t = {_t}), {_update(_t, f'f{_t}', 2, 6, 'draw_weight', 0.1, 1 / (0.1 * _t))}"
add("sgd_inverse_kmeans_5_steps", _inverse, f"{_INVERSE} select t, cls, component, {O.r6('w')} as w from ({_iterates_sql(5, 2, 6)})")


def _snapshot(s: SparkSession, d: str) -> DataFrame:
    ex = saver(s)(view(s, d, "f7"))
    assigned, _, plan = descent.prepare(ex, 6, 2, 8, StrataConfig("by_class"), AllocationConfig())
    return _out(_weights(s, extras.snapshot(ex, index.dense_position(assigned), plan, DescentConfig(0.1, 8, 2, "constant", 0.5), 2, 2, 6)))


_F7C = f"with {O.view('f7')}, {O.train()}, assigned as (select *, y as stratum from train), {O.stats('assigned', 6)}, {O.greedy('strata', 8)}"


def _snapshot_sql() -> str:
    """Two outer epochs of two steps: each adds the mean gradient at the anchor to the difference of the minibatch's."""
    text = f"{_F7C}, {O.positions('assigned')}, {O.draws('counted', 1, 1, 4)}, fetched as materialized (select d.t, d.draw_weight, i.y, i.x from draws d join indexed i using (stratum, pos)), w0 as (select {O.literal(zeros(2, 6))} as w)"
    for t in range(1, 5):
        anchor = (t - 1) // 2 * 2
        if t % 2:
            text += f", {O.residuals('train', f'(select w from w{anchor})', 2, f'full{t}')}, fg{anchor} as ({O.cells(f'full{t}', 2, 6, '1.0::double / (select count(*) from train)')})"
        w = f"(select w from w{t - 1})"
        text += f""", f{t} as (select draw_weight, y, x from fetched where t = {t}), {O.residuals(f'f{t}', w, 2, f'now{t}')}, {O.residuals(f'f{t}', f'(select w from w{anchor})', 2, f'then{t}')},
          gn{t} as ({O.cells(f'now{t}', 2, 6, 'draw_weight')}), gt{t} as ({O.cells(f'then{t}', 2, 6, 'draw_weight')}),
          w{t} as (select list(row order by cls) as w from (select cls, list(v order by component) as row from (select cls, component,
            {w}[cls + 1][component + 1] - 0.5::double * (a.g - b.g + c.g + 0.1::double * {w}[cls + 1][component + 1]) as v from gn{t} a join gt{t} b using (cls, component) join fg{anchor} c using (cls, component)) group by cls))"""
    return f"{text} select t, cls, component, {O.r6('w')} as w from ({_iterates_sql(4, 2, 6)})"


add("snapshot_step", _snapshot, _snapshot_sql())


def _importance(s: SparkSession, d: str, by_class: bool) -> DataFrame:
    rows = cluster.train_rows(view(s, d, "f7"))
    assigned = cluster.by_class(rows) if by_class else rows.withColumn("stratum", F.lit(0))
    plan = StratumPlan.from_frame(allocate.round_greedy(cluster.stats(assigned, 6), 8), 8, 2) if by_class else StratumPlan.single(rows.count(), 8)
    drawn = extras.importance_draws(saver(s)(extras.importance_index(assigned)), plan, 1, 3)
    return drawn.select("t", "stratum", "r", "row_id", r6("draw_weight").alias("draw_weight"))


_SIZED = f"""sized as (select row_id, stratum, round(sqrt(list_inner_product(x, x)) + 1e-6, 9) as size, {O.hashed("'bucket'", 'row_id')} % 64 as bucket from assigned),
    summed as (select *, sum(size) over (partition by stratum order by bucket, row_id rows between unbounded preceding and current row) as upto, sum(size) over (partition by stratum) as total from sized)"""
_IMPORTANCE = f"""{_SIZED}, draws as (select t, stratum, b_i, unnest(range(1, b_i + 1)) as r from counted cross join (select unnest(range(1, 4)) as t)),
    points as (select *, {O.hashed('1', 't', chr(39) + 'importance' + chr(39), 'stratum', 'r')} / 4503599627370496.0::double as u from draws)
    select t::int as t, p.stratum::int as stratum, r::int as r, row_id, {O.r6('1.0::double / ((select count(*) from train) * (size / total) * b_i)')} as draw_weight
    from points p join summed s on s.stratum = p.stratum and u >= (upto - size) / total and u < upto / total"""
_F7U = f"with {O.view('f7')}, {O.train()}, assigned as (select *, 0 as stratum from train)"
add("importance_step", lambda s, d: _importance(s, d, False), f"{_F7U}, counted as (select 0 as stratum, 8 as b_i), {_IMPORTANCE}")
add("stratified_importance_step", lambda s, d: _importance(s, d, True), f"{_F7C}, {_IMPORTANCE}")
add(
    "range_lookup",
    lambda s, d: saver(s)(extras.importance_index(cluster.train_rows(view(s, d, "f7")).withColumn("stratum", F.lit(0)))).select("row_id", r6("p").alias("p"), r6("lo").alias("lo"), r6("hi").alias("hi")),
    f"{_F7U}, {_SIZED} select row_id, {O.r6('size / total')} as p, {O.r6('(upto - size) / total')} as lo, {O.r6('upto / total')} as hi from summed",
)


def _moment_control(s: SparkSession, d: str) -> DataFrame:
    ex = saver(s)(view(s, d, "f7"))
    first, gram = extras.moments(ex, 6, 2)
    mean = np.array(cluster.train_rows(ex).agg(F.array(*(F.avg(F.col("x")[j]) for j in range(6)))).first()[0])
    plan = StratumPlan.single(cluster.train_rows(ex).count(), 8)
    drawn = sampling.fetch(sampling.plan_chunk(s, plan, 1, 1, 1), one_stratum(ex), "broadcast")  # one step
    w = np.array(fixed_w(2, 6))
    return _weights(s, [extras.moment_control(descent.by_step(drawn, 6)[1], w, DescentConfig(0.1, 8, 1), first, gram, mean)]).select("t", "cls", "component", r6("w").alias("g"))


def _moment_sql() -> str:
    """The minibatch gradient less the linearised one, plus that one's mean over all rows."""
    w = np.array(fixed_w(2, 6))
    centred = ((w - w.mean(axis=0)) / 2).tolist()
    linear = "[" + ", ".join(f"0.5::double + list_inner_product(x, {O.literal([centred[c]])}[1]) - case when y = {c} then 1 else 0 end" for c in range(2)) + "]"
    ridge = "case " + " ".join(f"when cls = {c} and component = {j} then {float(0.1 * w[c][j])!r}::double" for c in range(2) for j in range(6)) + " end"
    return f"""{_F7U}, {O.positions('assigned')}, {O.single('train', 8)}, {O.draws('counted', 1, 1, 1)}, f as (select d.draw_weight, i.y, i.x from draws d join indexed i using (stratum, pos)), {O.residuals('f', O.literal(fixed_w(2, 6)), 2, 'now')},
      lessened as (select draw_weight, x, [r[1] - l2[1], r[2] - l2[2]] as r from (select *, {linear} as l2 from now)), a as ({O.cells('lessened', 2, 6, 'draw_weight')}),
      every as (select x, {linear} as r from train), b as ({O.cells('every', 2, 6, '1.0::double / (select count(*) from train)')})
      select 1 as t, cls, component, {O.r6(f'a.g + b.g + {ridge}')} as g from a join b using (cls, component)"""


add("moment_control_step", _moment_control, _moment_sql())

# ---- theory ---------------------------------------------------------------------------------------

_V = [(t, round(0.5 / t, 6)) for t in range(1, 31)]
_V_SQL = "v(t, variance) as (values " + ", ".join(f"({t}, {x}::double)" for t, x in _V) + ")"


def v_literal(s: SparkSession) -> DataFrame:
    return s.createDataFrame(_V, "t int, variance double")


_ALPHA = bounds.contraction(0.8, 0.05, 0.55)
add("theorem1_rhs", lambda s, d: bounds.theorem1(v_literal(s), 0.5, 0.05, 2.0).select(r6("bound").alias("bound")), f"with {_V_SQL} select {O.r6('(0.5::double * 2.0 / 2 + sum(variance / (0.5::double + 0.05::double * t))) / count(*)')} as bound from v")
add("theorem2_rhs", lambda s, d: bounds.theorem2(v_literal(s), 0.8, 0.05, 0.55, 2.0).select(r6("bound").alias("bound")), f"with {_V_SQL}, m as (select max(t) as n from v) select {O.r6(f'pow({_ALPHA!r}::double, any_value(n)) * 2.0 * 0.55::double / 2 + 0.8::double * 0.8::double * 0.55::double / 2 * sum(pow({_ALPHA!r}::double, n - t) * variance)')} as bound from v cross join m")


def _one_step(s: SparkSession, d: str) -> DataFrame:
    """The bound by event type: mean value as objective, mean square as squared gradient norm, and their variance."""
    value = F.col("value")
    cases = load(s, d, "events").groupBy(F.col("event_type").alias("sampler")).agg(F.avg(value).alias("objective"), F.avg(value * value).alias("gradient_norm2"), F.var_pop(value).alias("variance"))
    return bounds.one_step_frame(cases.withColumns({"eta": F.lit(0.1), "smoothness": F.lit(0.55)})).select("sampler", r6("bound").alias("bound"))


add("one_step_bound", _one_step, f"with c as (select event_type as sampler, avg(value) as p, avg(value * value) as g, var_pop(value) as v, 0.1::double as e, 0.55::double as h from events group by event_type) select sampler, {O.r6('p - e * (1 - e * h / 2) * g + e * e * h / 2 * v')} as bound from c")
add("smoothness_constants", lambda s, d: bounds.constants(cluster.train_rows(view(s, d, "f1")), 0.05).select(r6("smoothness").alias("smoothness"), r6("convexity").alias("convexity")), f"{_F1} select {O.r6('0.5::double * max(list_inner_product(x, x)) + 0.05::double')} as smoothness, {O.r6('0.05::double')} as convexity from train")


def _lemma2(s: SparkSession, d: str) -> DataFrame:
    rows = saver(s)(cluster.train_rows(view(s, d, "f7")))
    u, v = np.array(fixed_w(2, 6)), np.zeros((2, 6))
    c = bounds.constants(rows, 0.05).first()
    left, right = bounds.lemma2_sides(extras.gradient_matrix(rows, u, 0.05), extras.gradient_matrix(rows, v, 0.05), u, v, 0.05, c.smoothness)
    return s.createDataFrame([(round(left, 6), round(right, 6), left >= right - 1e-12)], "left_side double, right_side double, holds boolean")


def _lemma2_sql() -> str:
    w = fixed_w(2, 6)
    diff = " + ".join(f"sum(case when cls = {c} and component = {j} then dg * ({w[c][j]!r}::double) end)" for c in range(2) for j in range(6))
    w2 = sum(v * v for row in w for v in row)
    lam = "case " + " ".join(f"when a.cls = {c} and a.component = {j} then {0.05 * w[c][j]!r}::double" for c in range(2) for j in range(6)) + " end"
    return f"""with {O.view('f7')}, {O.train()}, {O.residuals('train', O.literal(w), 2, 'ru')}, {O.residuals('train', O.literal(zeros(2, 6)), 2, 'rv')}, gu as ({O.cells('ru', 2, 6)}), gv as ({O.cells('rv', 2, 6)}),
    dg as (select a.cls, a.component, (a.g - b.g) / (select count(*) from train) + {lam} as dg from gu a join gv b using (cls, component)), c as (select 0.5::double * max(list_inner_product(x, x)) + 0.05::double as sm from train),
    sides as (select {diff} as l, 0.05::double * any_value(sm) / (0.05::double + any_value(sm)) * {w2!r}::double + sum(dg * dg) / (0.05::double + any_value(sm)) as r from dg cross join c)
    select round(l, 6) as left_side, round(r, 6) as right_side, l >= r - 1e-12 as holds from sides"""


add("lemma2_check", _lemma2, _lemma2_sql())
_PAIRS = ((0, 1), (1, 0), (0, 2))
_MODELS = [fixed_w(2, 6), zeros(2, 6), [[-v for v in row] for row in fixed_w(2, 6)]]


def _definitions(s: SparkSession, d: str) -> DataFrame:
    models = [np.array(w) for w in _MODELS]
    return bounds.check_definitions(saver(s)(cluster.train_rows(view(s, d, "f7"))), [(models[a], models[b]) for a, b in _PAIRS], 0.05)


def _definitions_sql() -> str:
    text = f"with {O.view('f7')}, {O.train()}, c as (select 0.5::double * max(list_inner_product(x, x)) + 0.05::double as sm from train)"
    for i, w in enumerate(_MODELS):
        ridge = 0.025 * sum(v * v for row in w for v in row)
        lam = "case " + " ".join(f"when cls = {c} and component = {j} then {0.05 * w[c][j]!r}::double" for c in range(2) for j in range(6)) + " end"
        text += f", {O.residuals('train', O.literal(w), 2, f'r{i}')}, p{i} as (select avg(list_max(l) + ln(list_sum(e)) - l[y + 1]) + {ridge!r}::double as p from r{i}), h{i} as ({O.cells(f'r{i}', 2, 6)}), g{i} as (select cls, component, g / (select count(*) from train) + {lam} as g from h{i})"
    rows = []
    for k, (a, b) in enumerate(_PAIRS):
        gap = "case " + " ".join(f"when cls = {c} and component = {j} then {_MODELS[a][c][j] - _MODELS[b][c][j]!r}::double" for c in range(2) for j in range(6)) + " end"
        text += f", q{k} as (select (select p from p{a}) as pu, (select p from p{b}) as pv, any_value(sm) as sm, sum(v.g * ({gap})) as i, sum(({gap}) * ({gap})) as d2, sum((u.g - v.g) * (u.g - v.g)) as b2, sum((u.g - v.g) * ({gap})) as t from g{a} u join g{b} v using (cls, component) cross join c)"
        sides = {"convex": ("pu", "pv + i"), "strongly_convex": ("pu", "pv + i + 0.025::double * d2"), "smooth": ("pv + i + sm / 2 * d2", "pu"), "lipschitz_gradient": ("sm * sqrt(d2)", "sqrt(b2)"), "co_coercive": ("t", "b2 / sm"), "strongly_convex_and_smooth": ("t", "0.05::double * sm / (0.05::double + sm) * d2 + b2 / (0.05::double + sm)")}
        rows += [f"select {k} as pair, '{name}' as \"check\", round({x}, 6) as left_side, round({y}, 6) as right_side, {x} >= {y} - 1e-9 as holds from q{k}" for name, (x, y) in sides.items()]
    return f"{text} " + " union all ".join(rows)


add("definition_checks", _definitions, _definitions_sql())


def _bounds_on_run(s: SparkSession, d: str) -> DataFrame:
    """Both samplers' mean gap over five seeds and 60 steps 1 / (a + lam t), against the bound with their exact variances."""
    save, lam, steps = saver(s), 0.1, 60
    ex = save(view(s, d, "f7"))
    rows = save(cluster.train_rows(ex))
    smooth, best = bounds.constants(rows, lam).first().smoothness, bounds.reference_optimum(s, ex, lam, 2)
    least = measures.objective(rows, best.tolist(), lam).first()[0]
    assigned, _, plan = descent.prepare(ex, 6, 2, 8, StrataConfig("dispersion", 4, iters=4), AllocationConfig(), save)
    single = StratumPlan.single(rows.count(), 8)
    places = {"uniform": (rows.withColumn("stratum", F.lit(0)), single), "stratified": (assigned, plan)}
    config = DescentConfig(lam, 8, steps, "shifted", shift=smooth - lam, eval_every=1)
    indexed = {k: save(index.dense_position(v[0])) for k, v in places.items()}
    runs = [descent.Run(f"{k}|{seed}", indexed[k], places[k][1], replace(config, seed=seed), np.zeros((2, 6))) for k in places for seed in experiments.SEEDS]
    models = descent.run_chains(runs, keep_all=True)
    zero = s.createDataFrame([(r.name, 0, c, [0.0] * 6) for r in runs for c in range(2)], descent.MODELS)
    models = save(models.unionByName(zero))
    spread = _union(*(descent.variances(models.where(F.col("run_id").startswith(k)), *places[k]) for k in places)).withColumn("t", F.col("t") + 1)
    trace = descent.evaluate(models, ex, lam).join(spread, ["run_id", "t"]).withColumn("sampler", F.split("run_id", "[|]")[0])
    means = trace.groupBy("sampler", "t").agg((F.avg("objective") - least).alias("gap"), F.avg("est_variance").alias("variance"))
    return bounds.on_run(means, smooth - lam, lam, float((best**2).sum())).select("sampler", r6("mean_gap").alias("mean_gap"), r6("bound").alias("bound"), "holds")


add("theorem1_on_run", _bounds_on_run)


def _lemma1(s: SparkSession, d: str) -> DataFrame:
    """The bound of each step of an event type, an hour of the day: distances are the hour's mean square and the next one's."""
    steps = load(s, d, "events").groupBy("event_type", (F.hour("ts") + 1).cast("int").alias("t")).agg(F.avg(F.col("value") * F.col("value")).alias("before"), F.var_pop("value").alias("variance"))
    after = F.coalesce(F.lead("before").over(Window.partitionBy("event_type").orderBy("t")), F.lit(0.0))
    return steps.select("event_type", "t", r6(bounds.lemma1(0.5 / F.col("t"), F.col("before"), after, 0.05, F.col("variance"))).alias("bound"))


add(
    "lemma1_rhs",
    _lemma1,
    f"""with steps as (select event_type, (hour(ts) + 1)::int as t, avg(value * value) as before, var_pop(value) as variance from events group by 1, 2),
    sides as (select *, coalesce(lead(before) over (partition by event_type order by t), 0) as after, 0.5::double / t as eta from steps)
    select event_type, t, {O.r6('(before - after) / (2 * eta) - 0.05::double / 2 * before + eta * variance')} as bound from sides""",
)

# ---- workloads ------------------------------------------------------------------------------------

_TRACES: dict[tuple[str, str, str], DataFrame] = {}


def workload(s: SparkSession, d: str, name: str) -> DataFrame:
    """The trace of a workload as it is defined, five seeds and all its epochs; kept as a table for the queries of a session."""
    key = (s.sparkContext.applicationId, d, name)
    if key not in _TRACES:
        _TRACES[key] = saver(s)(experiments.curves(s, d, name, save=saver(s)))
    return _TRACES[key]


for _w in experiments.WORKLOADS:
    add(f"{_w}_curve", lambda s, d, w=_w: workload(s, d, w))
    add(f"{_w}_summary", lambda s, d, w=_w: experiments.summary(workload(s, d, w)))
    add(f"{_w}_ratios", lambda s, d, w=_w: experiments.ratios(workload(s, d, w)))
for _w in ("w6", "w7"):
    add(f"{_w}_gaps", lambda s, d, w=_w: experiments.gaps(s, d, w, workload(s, d, w)))
add("w8_scale", lambda s, d: experiments.scale_run(s, d, saver(s)))


def _ablation_sql(name: str, classes: int, d: int, b: int, per_class: int) -> str:
    """A SELECT for each builder, kind and rounding."""
    build = {rule: O.built(per_class, how, 5, d) for rule, how in (("kmeans", "euclid"), ("dispersion", "dispersion"), ("frozen", "frozen"))}
    build["by_class"] = "assigned as (select *, y as stratum from train)"
    build["random"] = f"assigned as (select *, (y * {per_class} + {O.hashed(chr(39) + 'strata' + chr(39), '1', 'row_id')} % {per_class})::int as stratum from train)"
    build["quantile"] = O.starts(per_class, 0, name="assigned")
    out = []
    for builder, sql in build.items():
        each = [(kind, rounding) for kind in ("dispersion", "proportional", "equal") for rounding in ("greedy", "remainder", "systematic")]
        counted = ", ".join(O.allocated("strata", b, kind, rounding, f"n_{kind}_{rounding}") for kind, rounding in each)
        bound = "sum(n_i::double * n_i * v_i / b_i) / (sum(n_i) * sum(n_i))"
        rows = " union all ".join(f"select '{builder}' as builder, '{k}' as kind, '{r}' as rounding, {O.r6(bound)} as bound, {O.r6(f'{1 - 1 / classes!r}::double * {bound}')} as variance from n_{k}_{r}" for k, r in each)
        out.append(f"select * from (with {O.view(name)}, {O.train()}, {sql}, {O.stats('assigned', d)}, {counted} {rows})")
    return " union all ".join(out)


for _v, _m, _b, _k in (("f7", 2, 12, 6), ("f8", 5, 20, 10)):
    _query = lambda s, d, v=_v, m=_m, b=_b, k=_k: experiments.ablation(s, d, v, m, b, k, saver(s)).select("builder", "kind", "rounding", r6("bound").alias("bound"), r6("variance").alias("variance"))
    add(f"ablation_{_v}", _query, _ablation_sql(_v, _m, VIEWS[_v].d, _b, _k // _m))


def _blocks(s: SparkSession, d: str) -> DataFrame:
    """Draws from the index as it is written, by stratum and block of positions."""
    path = shared_path(s, "index")
    index.write(f4_indexed(s, d), path)
    return sampling.fetch(sampling.plan_chunk(s, f4_plan(s, d), 1, 1, 3), index.read(s, path), "broadcast").select("t", "stratum", "r", "row_id")


add("drawn_rows_from_blocks", _blocks, ORACLES["drawn_rows_merge"])

# ---- sources, streams -----------------------------------------------------------------------------


def _libsvm(s: SparkSession, d: str) -> DataFrame:
    path = shared_path(s, "libsvm")
    write_libsvm(view(s, d, "f5"), path)
    return read_libsvm(s, path, 16).groupBy("y").agg(F.count("*").alias("n_rows"), r6(F.sum(F.col("x")[0])).alias("total"))


add("libsvm_roundtrip", _libsvm, f"with {O.view('f5')} select y, count(*) as n_rows, {O.r6('sum(x[1])')} as total from ex group by y")
for _fmt in ("csv", "json", "orc", "parquet"):
    add(f"{_fmt}_roundtrip", lambda s, d, fmt=_fmt: roundtrip(strata_f8(s, d).select("stratum", "y", "n_i", r6("v_i").alias("v_i")), fmt, shared_path(s, fmt)), f"{_A8} select stratum, y, n_i, {O.r6('v_i')} as v_i from strata")
_WINDOWS = {
    "tumbling": (lambda: F.window("ts", "1 hour"), "1 hour", 1),
    "sliding": (lambda: F.window("ts", "2 hours", "1 hour"), "2 hour", 2),
}
for _k, (_w, _len, _n) in _WINDOWS.items():
    add(
        "stream_window_moments" if _k == "tumbling" else "sliding_window_moments",
        lambda s, d, w=_w: stream.class_stats(load(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp")), w()).select(F.date_format("start", "yyyy-MM-dd HH:mm:ss").alias("start"), "event_type", "n_rows", r6("sum_value").alias("sum_value"), r6("sum_squares").alias("sum_squares")),
        f"select strftime(date_trunc('hour', ts) - to_hours(k), '%Y-%m-%d %H:%M:%S') as start, event_type, count(*) as n_rows, {O.r6('sum(value)')} as sum_value, {O.r6('sum(value * value)')} as sum_squares from events cross join (select unnest(range(0, {_n})) as k) group by 1, 2",
    )
add(
    "session_counts",
    lambda s, d: load(s, d, "events").withColumn("ts", F.col("ts").cast("timestamp")).groupBy(F.session_window("ts", "30 minutes"), "user_id").agg(F.count("*").alias("n_rows")).groupBy("user_id").agg(F.count("*").alias("sessions"), F.max("n_rows").alias("longest")),
    """with e as (select user_id, ts, case when ts - lag(ts) over (partition by user_id order by ts) <= interval 30 minutes then 0 else 1 end as fresh from events),
    n as (select user_id, sum(fresh) over (partition by user_id order by ts rows between unbounded preceding and current row) as session from e),
    c as (select user_id, session, count(*) as n_rows from n group by 1, 2) select user_id, count(*) as sessions, max(n_rows) as longest from c group by user_id""",
)
add("interval_join", lambda s, d: stream.nearby(load(s, d, "events")).groupBy("user_id").agg(F.count("*").alias("pairs")), "select a.user_id, count(*) as pairs from events a join events b on a.user_id = b.user_id and (b.ts > a.ts or (b.ts = a.ts and b.event_id > a.event_id)) and b.ts <= a.ts + interval 1 hour group by a.user_id")


def _sql_scores(s: SparkSession, d: str) -> DataFrame:
    """The confusion of a fixed model, by the functions registered for SQL users."""
    sql_functions.register(s)
    view(s, d, "f1").createOrReplaceTempView("descent_examples")
    w = ", ".join("array(" + ", ".join(f"{v!r}D" for v in row) + ")" for row in fixed_w(2, 4))
    return s.sql(f"select y, descent_class(descent_scores(x, array({w}))) as cls, count(*) as n_rows, round(avg(descent_loss(descent_scores(x, array({w})), y)), 6) + 0D as loss from descent_examples where split = 'test' group by 1, 2")


def _sql_draws(s: SparkSession, d: str) -> DataFrame:
    """Five steps' positions in every class of the events, by the table function."""
    sql_functions.register(s)
    cluster.train_rows(view(s, d, "f8")).groupBy(F.col("y").alias("stratum")).agg(F.count("*").alias("n_i")).createOrReplaceTempView("descent_strata")
    return s.sql("select t.id as step, c.stratum, r, pos from descent_strata c, range(1, 6) t, lateral descent_draws(7, cast(t.id as int), c.stratum, c.n_i, 4)")


def _catalog(s: SparkSession, d: str) -> DataFrame:
    register(s, d)
    return s.sql("select n_name, count(*) as customers from nation join customer on c_nationkey = n_nationkey group by n_name")


def _bucketed(s: SparkSession, d: str) -> DataFrame:
    """Class counts from a table that is bucketed by class: no shuffle."""
    name = f"descent_{uuid.uuid4().hex}"
    return write_bucketed(view(s, d, "f8").select("row_id", "y"), name, ["y"], 8).groupBy("y").agg(F.count("*").alias("n_rows"))


def _exported(s: SparkSession, d: str) -> DataFrame:
    path = shared_path(s, "trace")
    export_trace(trace_of(s, d), path)
    schema = "seed int, t int, objective double, workload string, sampler string"
    return s.read.schema(schema).option("header", "true").csv(path).groupBy("workload", "sampler").agg(F.count("*").alias("n_rows"), r6(F.sum("objective")).alias("objective"))


add("sql_scores", _sql_scores, f"{_TEST1} select y, (list_position(l, list_max(l)) - 1)::int as cls, count(*) as n_rows, {O.r6('avg(list_max(l) + ln(list_sum(e)) - l[y + 1])')} as loss from res group by 1, 2")
add("sql_draws", _sql_draws, f"with {O.view('f8')}, {O.train()}, c as (select y as stratum, count(*) as n_i from train group by y) select t::bigint as step, stratum, r::int as r, {O.hashed('7', 't', 'stratum', 'r')} % n_i as pos from c cross join (select unnest(range(1, 6)) as t) cross join (select unnest(range(1, 5)) as r)")
add("catalog_views", _catalog, "select n_name, count(*) as customers from nation join customer on c_nationkey = n_nationkey group by n_name")
add("bucketed_counts", _bucketed, f"with {O.view('f8')} select y, count(*) as n_rows from ex group by y")
add("exported_trace", _exported, f"with {_TRACE_SQL} select workload, sampler, count(*) as n_rows, {O.r6('sum(objective)')} as objective from trace group by 1, 2")
add("lead_events", lambda s, d: load(s, d, "events").select("event_id", F.lead("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias("next_value")), "select event_id, lead(value) over (partition by user_id order by ts, event_id) as next_value from events")
add("percentiles", lambda s, d: load(s, d, "lineitem").groupBy("l_returnflag").agg(*(r6(F.percentile("l_extendedprice", p)).alias(f"p{round(100 * p)}") for p in (0.25, 0.5, 0.9))), "select l_returnflag, " + ", ".join(f"{O.r6(f'quantile_cont(l_extendedprice, {p})')} as p{round(100 * p)}" for p in (0.25, 0.5, 0.9)) + " from lineitem group by 1")
add(
    "approximate_distinct",
    lambda s, d: load(s, d, "lineitem").groupBy("l_returnflag").agg(F.countDistinct("l_partkey").alias("parts"), F.approx_count_distinct("l_partkey", 0.02).alias("about")).select("l_returnflag", "parts", (F.abs(F.col("about") - F.col("parts")) <= 0.1 * F.col("parts")).alias("close")),
    "select l_returnflag, count(distinct l_partkey) as parts, true as close from lineitem group by 1",
)
add("hash_stream", lambda s, d: load(s, d, "events").select(F.col("event_id").alias("id"), rng.hash52(7, F.col("event_id"), "x").alias("h")), f"select event_id as id, {O.hashed('7', 'event_id', chr(39) + 'x' + chr(39))} as h from events")


def flagship(s: SparkSession, sf_dir: str) -> DataFrame:
    """Uniform against stratified descent on the embeddings: the trace of both."""
    return experiments.curves(s, sf_dir, "w3", seeds=(1,), save=saver(s), epochs=0.5, points=2)
