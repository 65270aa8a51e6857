"""Feature views: each maps a table to examples (row_id, y, x, split).

A view's label, id and features are SQL expressions; where Spark and other engines spell one
differently the view holds both.  Labels become 0-based codes in sorted order.  Scaled views are
standardised with the training split's means and population deviations.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.load import load
from .rng import hash52

Expr = str | tuple[str, str]  # one text, or (Spark's, ANSI)
SPLIT_GRAIN = 10_000


@dataclass(frozen=True)
class View:
    table: str
    id_text: str  # SQL of a text that names the row; its hash is row_id, unless id_is_key
    label: Expr
    features: tuple[Expr, ...]
    fraction: float = 0.8
    scaled: bool = True
    id_is_key: bool = False
    label_is_code: bool = False
    array: Expr | None = None  # features as one array expression
    width: int = 0
    trigrams: bool = False  # features are shares of hashed character trigrams of text
    join: str | None = None  # a second table, joined on doc_id

    @property
    def d(self) -> int:
        return self.width or len(self.features)


def spark_text(e: Expr) -> str:
    return e if isinstance(e, str) else e[0]


def ansi_text(e: Expr) -> str:
    return e if isinstance(e, str) else e[1]


_LINE_ID = (
    "concat_ws('|', l_orderkey, l_linenumber, l_partkey, l_suppkey, cast(round(l_quantity * 100) as bigint), cast(round(l_extendedprice * 100) as bigint), "
    "cast(round(l_discount * 10000) as bigint), cast(round(l_tax * 10000) as bigint), l_returnflag, l_linestatus)"
)
_LINE = ("cast(l_quantity as double)", "cast(l_extendedprice as double)", "cast(l_discount as double)", "cast(l_tax as double)")
_NET = "case when l_extendedprice * (1 - l_discount) >= 50000 then 1 else 0 end"
#: Letters of the 16-letter view.
LETTERS = "eniratsdhulocmgb"
#: Part types of the brand view, in sorted order.
PART_TYPES = ("ECONOMY", "LARGE", "MEDIUM", "PROMO", "SMALL", "STANDARD")
_WORDS = (r"filter(split(text, '[\\x20\\t\\n\\r]+'), w -> w != '')", r"list_filter(regexp_split_to_array(text, '[\x20\t\n\r]+'), lambda w: w <> '')")
_LINES = (r"filter(split(text, '\\n'), w -> w != '')", r"list_filter(regexp_split_to_array(text, '\n'), lambda w: w <> '')")


def _letter(c: str) -> str:
    return f"cast(length(lower(text)) - length(replace(lower(text), '{c}', '')) as double) / greatest(length(text), 1)"


def _ratio(top: Expr, bottom: Expr) -> Expr:
    return tuple(f"cast({t} as double) / greatest({b}, 1)" for t, b in zip((spark_text(top), ansi_text(top)), (spark_text(bottom), ansi_text(bottom)), strict=True))


_N_WORDS = (f"size({_WORDS[0]})", f"len({_WORDS[1]})")
_TEXT_SHAPE = (
    "cast(length(text) as double)",
    (f"cast({_N_WORDS[0]} as double)", f"cast({_N_WORDS[1]} as double)"),
    _ratio((f"size(array_distinct({_WORDS[0]}))", f"len(list_distinct({_WORDS[1]}))"), _N_WORDS),
    _ratio((r"length(regexp_replace(text, '[^0-9]', ''))", r"length(regexp_replace(text, '[^0-9]', '', 'g'))"), "length(text)"),
    _ratio((r"length(regexp_replace(text, '[^.,;:!?#*$%&|<>]', ''))", r"length(regexp_replace(text, '[^.,;:!?#*$%&|<>]', '', 'g'))"), "length(text)"),
    _ratio((f"size(array_distinct({_LINES[0]}))", f"len(list_distinct({_LINES[1]}))"), (f"size({_LINES[0]})", f"len({_LINES[1]})")),
)
TRIGRAM_BUCKETS = 256

VIEWS: dict[str, View] = {
    "f1": View("lineitem", _LINE_ID, _NET, _LINE, fraction=0.9004, label_is_code=True),
    "f1wide": View("lineitem", _LINE_ID, _NET, (*_LINE, "cast(l_linenumber as double)", *(f"case when month(l_shipdate) = {m} then 1e0 else 0e0 end" for m in range(1, 13))), fraction=0.9004, label_is_code=True),
    "f2": View("lineitem", _LINE_ID, "l_linestatus", _LINE, fraction=0.9004),
    "f2flag": View("lineitem", _LINE_ID, "l_returnflag", _LINE, fraction=0.9004),
    "f3": View(
        "part", "p_partkey", "p_brand",
        ("cast(p_size as double)", "cast(p_retailprice as double)", *(f"case when p_type = '{t}' then 1e0 else 0e0 end" for t in PART_TYPES), *(f"case when p_size > {lo} and p_size <= {lo + 7} then 1e0 else 0e0 end" for lo in range(0, 56, 7))),
        fraction=0.75, id_is_key=True,
    ),
    "f4": View("embeddings", "vec_id", "label", (), fraction=0.857, scaled=False, id_is_key=True, label_is_code=True, array=("cast(embedding as array<double>)", "embedding::double[]"), width=64),
    "f5": View("documents", "doc_id", "lang", tuple(map(_letter, LETTERS)), fraction=0.682, id_is_key=True),
    "f6": View("documents", "doc_id", "lang", (), fraction=0.784, scaled=False, id_is_key=True, trigrams=True, width=TRIGRAM_BUCKETS),
    "f7": View("documents", "doc_id", "quality", _TEXT_SHAPE, id_is_key=True, label_is_code=True, join="labels"),
    "f7toxic": View("documents", "doc_id", "toxic", _TEXT_SHAPE, id_is_key=True, label_is_code=True, join="labels"),
    "f8": View("events", "event_id", "event_type", ("cast(value as double)", "cast(hour(ts) as double)", ("cast(get_json_object(props, '$.k') as double)", "cast(json_extract_string(props, '$.k') as double)")), id_is_key=True),
    "f9order": View("orders", "o_orderkey", "o_orderpriority", ("cast(o_totalprice as double)", "cast(month(o_orderdate) as double)", "cast(year(o_orderdate) as double)"), id_is_key=True),
    "f9customer": View("customer", "c_custkey", "c_mktsegment", ("cast(c_acctbal as double)", "cast(c_nationkey as double)"), id_is_key=True),
    "f9turn": View("conversations", "concat_ws('|', conv_id, turn)", "role", ("cast(length(text) as double)", "cast(turn as double)"),),
}


def split_column(row_id: F.Column, fraction: float, seed: int = 0) -> F.Column:
    return F.when(hash52("split", seed, row_id) % SPLIT_GRAIN < round(fraction * SPLIT_GRAIN), "train").otherwise("test")


def encode_labels(df: DataFrame, column: str) -> DataFrame:
    """column as a 0-based code y in sorted order of its distinct values; rows without a label go."""
    from pyspark.sql import Window

    codes = df.where(F.col(column).isNotNull()).select(column).distinct()
    codes = codes.select(F.col(column).alias("label_key"), (F.dense_rank().over(Window.orderBy(column)) - 1).cast("int").alias("y"))  # a row per class
    return df.join(F.broadcast(codes), F.col(column) == F.col("label_key")).drop("label_key")


def trigram_shares(texts: list[str | None], buckets: int) -> np.ndarray:
    """For each text and bucket the share of the text's characters at which a trigram of that bucket starts."""
    out = np.zeros((len(texts), buckets))
    bucket_of: dict[int, int] = {}
    for i, text in enumerate(texts):
        at = np.frombuffer((text or "").encode("utf-32-le"), dtype=np.uint32).astype(np.int64)
        if len(at) < 3:
            continue
        codes, n = np.unique(at[:-2] << 42 | at[1:-1] << 21 | at[2:], return_counts=True)
        for code in codes.tolist():
            if code not in bucket_of:
                run = "".join(chr(code >> shift & 0x1FFFFF) for shift in (42, 21, 0))
                bucket_of[code] = int(hashlib.md5(run.encode(), usedforsecurity=False).hexdigest()[:13], 16) % buckets  # as hash52 does
        np.add.at(out[i], [bucket_of[c] for c in codes.tolist()], n / len(at))
    return out


def hashed_trigrams(docs: DataFrame, buckets: int = TRIGRAM_BUCKETS) -> DataFrame:
    """doc_id, lang and x: for each bucket its trigrams' share of the text's characters, counted inside the row."""

    def shares(batches):
        for batch in batches:
            x = trigram_shares(batch.column(2).to_pylist(), buckets)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * buckets), pa.array(x.ravel()))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), lists], ["doc_id", "lang", "x"])

    return docs.select("doc_id", "lang", "text").mapInArrow(shares, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, lang string, x array<double>")


def raw_view(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """row_id, y, x before scaling, split."""
    v = VIEWS[name]
    df = load(spark, sf_dir, v.table)
    if v.join:
        df = df.join(load(spark, sf_dir, v.join), "doc_id")
    row_id = F.expr(v.id_text).cast("bigint") if v.id_is_key else hash52(F.expr(v.id_text))
    if v.trigrams:
        df = hashed_trigrams(df)
    x = F.col("x") if v.trigrams else F.expr(spark_text(v.array)) if v.array else F.array(*(F.expr(spark_text(e)) for e in v.features))
    df = df.select(row_id.alias("row_id"), F.expr(spark_text(v.label)).alias("label"), x.alias("x"))
    df = df.where("label is not null").withColumn("y", F.col("label").cast("int")) if v.label_is_code else encode_labels(df, "label")
    return df.select("row_id", "y", "x", split_column(F.col("row_id"), v.fraction).alias("split"))


def fit_scaler(ex: DataFrame, d: int) -> DataFrame:
    """One row: mean and sd arrays of the training split."""
    train = ex.where("split = 'train'")
    return train.agg(F.array(*(F.avg(F.col("x")[j]) for j in range(d))).alias("mean"), F.array(*(F.stddev_pop(F.col("x")[j]) for j in range(d))).alias("sd"))


def apply_scaler(ex: DataFrame, scaler: DataFrame) -> DataFrame:
    """x standardised; a feature without spread becomes 0."""
    wide = ex.crossJoin(F.broadcast(scaler))  # one row
    z = F.expr("transform(x, (v, j) -> if(sd[j] = 0, 0D, (v - mean[j]) / sd[j]))")
    return wide.select("row_id", "y", z.alias("x"), "split")


def view(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    ex = raw_view(spark, sf_dir, name)
    return apply_scaler(ex, fit_scaler(ex, VIEWS[name].d)) if VIEWS[name].scaled else ex


def null_policy(df: DataFrame, columns: list[str], mode: str) -> DataFrame:
    """Rows with a NULL or NaN in columns: rejected with an error, dropped, or filled with the column's mean."""
    bad = F.lit(False)
    for c in columns:
        bad = bad | F.col(c).isNull() | F.isnan(c)
    if mode == "drop":
        return df.where(~bad)
    if mode == "reject":
        if df.where(bad).limit(1).count():
            raise ValueError(f"missing values in {columns}")
        return df
    if mode != "impute_mean":
        raise ValueError(mode)
    clean = {c: F.when(~F.isnan(c), F.col(c)) for c in columns}
    means = df.agg(*(F.avg(e).alias(f"mean_{c}") for c, e in clean.items()))
    return df.crossJoin(F.broadcast(means)).withColumns({c: F.coalesce(e, F.col(f"mean_{c}")) for c, e in clean.items()}).drop(*(f"mean_{c}" for c in columns))
