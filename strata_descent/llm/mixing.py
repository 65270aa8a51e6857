"""Mixing sources to target weights by a low-discrepancy schedule of equal-token blocks.

Each source's documents stand in a seeded shuffled order, one after the other; that stream is cut into
blocks of B words.  Slot i of the mix looks at the i-th point of a low-discrepancy sequence (golden
ratio or van der Corput): the source whose interval of cumulative target weight holds the point gets the
slot, and the mix has as many slots as the targets have blocks.  A slot's rank among its source's slots
picks the block: laps over the stream one after the other, each an affine shuffle of the whole blocks that
starts where the point of the lap's first slot stands in the source's interval; a shorter last block ends
the lap.  So the points decide which blocks of an unfinished lap are taken.  Blocks that the points miss
follow after the last slot, and a source's last block is cut at its target, so every source gives exactly
its target, rounded to words, and no document is taken more than MAX_EPOCHS times.

Nothing that grows is collected or kept in one task: documents are split into hash buckets and slots into
chunks, with prefix sums over their totals; sources are numbered by ranges; points meet the sources'
intervals by a sort within ranges of points.  The driver gets totals only.

Null texts have size 0 and are taken 0 times; a null source is a source of its own, last in order.  Rows
are told apart by all their columns; repeated rows, with an id or without, each have their own place.  An
empty table gives an empty mix.
"""

from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import words as kernel
from .common import at_most, checked, documents, saved, table

WEIGHTS = (3.0, 1.0, 2.0)
SHARE = 1.5
MAX_EPOCHS = 2
BLOCK_WORDS = 1024
CHUNK_BITS = 16  # of slots, and of points in a range
ROWS_PER_BUCKET = 2_000
ROWS_PER_RANGE = 100_000
SEED = 20_240_607
POINT_BITS = 53
_GOLDEN = 0x9E3779B97F4A7C15  # frac of the golden ratio times 2**64


def _hashable(docs: DataFrame) -> list[str]:
    return [f"`{f.name}`" for f in docs.schema if "map<" not in f.dataType.simpleString() and "variant" not in f.dataType.simpleString()]


def with_size(docs: DataFrame) -> DataFrame:
    """doc_id, source, size (words of the text), key (hash of the row) for every row of docs."""

    def count(batches):
        for batch in batches:
            sizes = [w.counts() for _, _, w in kernel.steps(batch)]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(np.concatenate(sizes) if sizes else np.zeros(0), pa.int64()), batch.column(3)], ["doc_id", "source", "size", "key"])

    kept = documents(docs, F.col("source").cast("string").alias("source"), F.xxhash64(*_hashable(docs)).alias("key"))
    return kept.mapInArrow(count, f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, source string, size bigint, key bigint")


def totals_before(df: DataFrame, order: list[Column], **sums: str) -> DataFrame:
    """df with, for each name, the total of an expression over the rows before it in an order.

    Rows are dealt by ranges of the order; only the ranges' totals, a row for ROWS_PER_RANGE rows, meet in one task.
    """
    ranges = -(-df.count() // ROWS_PER_RANGE)
    if ranges <= 1:
        before = Window.orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
        return df.withColumns({name: F.coalesce(F.sum(F.expr(e)).over(before), F.lit(0)) for name, e in sums.items()})
    dealt = saved(df.repartitionByRange(ranges, *order).withColumn("part", F.spark_partition_id()))
    above = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    starts = dealt.groupBy("part").agg(*(F.sum(F.expr(e)).alias(name) for name, e in sums.items()))
    starts = starts.select("part", *(F.coalesce(F.sum(name).over(above), F.lit(0)).alias(f"{name} start") for name in sums))
    inside = Window.partitionBy("part").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    out = dealt.join(F.broadcast(starts), "part")
    return out.select(*df.columns, *((F.col(f"{name} start") + F.coalesce(F.sum(F.expr(e)).over(inside), F.lit(0))).alias(name) for name, e in sums.items()))


def _stride(n: int) -> int:
    """A step near n over the golden ratio that has no factor in common with n."""
    step = max(1, round(n * 0.6180339887498949))
    while math.gcd(step, n) != 1:
        step += 1
    return step % n if n > 1 else 0


def _strides(column: str) -> Column:
    @F.pandas_udf("bigint")
    def strides(n: pd.Series) -> pd.Series:
        return n.map(lambda x: _stride(max(1, int(x)))).astype("int64")

    return strides(column)


def with_targets(sources: DataFrame, share: float = SHARE, cap: float = MAX_EPOCHS) -> DataFrame:
    """sources (source, number, size) with weight and target: by weight, share of all sizes in all, none above cap times its size.

    Handing back the excess by weight until none is above ends where all sources below their cap have one
    common ratio of target to weight.  In the order of the ratios at which sources reach their cap, it is
    what is left for the first one that stays below and those after it.
    """
    weights = F.array(*(F.lit(w) for w in WEIGHTS))
    rows = sources.withColumn("weight", F.get(weights, (F.col("number") % len(WEIGHTS)).cast("int"))).withColumn("most", F.col("size") * F.lit(float(cap)))
    whole = rows.agg(F.sum("size").alias("size"), F.sum("weight").alias("weight")).first()
    if not whole["size"]:
        return rows.withColumn("target", F.lit(0.0)).drop("most")
    ordered = totals_before(rows.withColumn("reach", F.col("most") / F.col("weight")), [F.col("reach"), F.col("number")], given="most", weighed="weight")
    left, weight = F.lit(share * whole["size"]) - F.col("given"), F.lit(whole["weight"]) - F.col("weighed")
    ratio = ordered.where(F.col("most") * weight >= left * F.col("weight")).agg(F.min_by(left / weight, F.struct("reach", "number"))).first()[0]
    target = F.col("most") if ratio is None else F.least("most", F.col("weight") * F.lit(ratio))
    return rows.withColumn("target", target).drop("most")


def sources_of(sized: DataFrame, block: int = BLOCK_WORDS) -> DataFrame:
    """A row for each source: source, number, size, weight, target; words (target, rounded), whole (blocks of a lap of full size), lap (all its blocks), slots, slots_before, stride."""
    rows = saved(sized.groupBy("source").agg(F.sum("size").alias("size")))
    rows = totals_before(rows, [F.col("source").asc_nulls_last()], number="1")  # strings are ordered by code point
    rows = with_targets(saved(rows)).withColumns({"words": F.expr("cast(round(target) as bigint)"), "whole": F.expr(f"size div {block}"), "lap": F.expr(f"(size + {block - 1}) div {block}")})
    slots = f"if(size = 0, 0, (words div size) * lap + (words % size + {block - 1}) div {block})"
    rows = saved(rows.withColumns({"slots": F.expr(slots), "stride": _strides("whole")}))
    return saved(totals_before(rows, [F.col("number")], slots_before="slots"))


def points(first: np.ndarray, sequence: str = "golden") -> np.ndarray:
    """The points of slots, as integers of POINT_BITS bits."""
    i = first.astype(np.uint64)
    if sequence == "golden":
        with np.errstate(over="ignore"):
            i = i * np.uint64(_GOLDEN)
    elif sequence == "van_der_corput":
        for shift, mask in ((1, 0x5555555555555555), (2, 0x3333333333333333), (4, 0x0F0F0F0F0F0F0F0F), (8, 0x00FF00FF00FF00FF), (16, 0x0000FFFF0000FFFF)):
            i = (i >> np.uint64(shift) & np.uint64(mask)) | (i & np.uint64(mask)) << np.uint64(shift)
        i = i >> np.uint64(32) | i << np.uint64(32)
    else:
        raise ValueError(f"unknown sequence {sequence!r}")
    return (i >> np.uint64(64 - POINT_BITS)).astype(np.int64)


def slots_of(sources: DataFrame, sequence: str = "golden", start: int = 0) -> DataFrame:
    """slot, number, at: the source that each slot's point falls on, and where in the source's interval, from 0 to 1."""
    spark = sources.sparkSession
    total = int(sources.agg(F.sum("slots")).first()[0] or 0)
    bits = max(0, (total >> CHUNK_BITS).bit_length())
    ranges = F.shiftright("point", POINT_BITS - bits) if bits else F.lit(0).cast("bigint")

    def pointed(batches):
        for batch in batches:
            slot = batch.column(0).to_numpy()
            yield pa.RecordBatch.from_arrays([pa.array(slot), pa.array(points(slot + start, sequence))], ["slot", "point"])

    drawn = spark.range(0, total, 1, max(1, min(10_000, -(-total >> CHUNK_BITS)))).mapInArrow(pointed, "slot bigint, point bigint")
    scale = 2.0**POINT_BITS / max(total, 1)
    edges = sources.where("slots > 0").select((F.col("slots_before") * F.lit(scale)).cast("bigint").alias("point"), F.col("number").alias("edge"), (F.col("slots") * F.lit(scale)).alias("width"))
    # the source whose interval a range of points begins in; a row for each range
    last = edges.groupBy(ranges.alias("range")).agg(F.max_by(F.struct("edge", "point", "width"), "edge").alias("last"))
    carried = spark.range(0, 1 << bits).withColumnRenamed("id", "range").join(last, "range", "left")
    carried = carried.select("range", F.last("last", ignorenulls=True).over(Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)).alias("carried"))
    both = drawn.select("slot", "point", F.lit(None).cast("struct<edge:bigint,point:bigint,width:double>").alias("interval")).unionByName(
        edges.select(F.lit(None).cast("bigint").alias("slot"), "point", F.struct("edge", "point", "width").alias("interval"))
    )
    over = Window.partitionBy("range").orderBy("point", F.col("slot").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    found = both.withColumn("range", ranges).withColumn("interval", F.last("interval", ignorenulls=True).over(over)).where("slot is not null")
    found = found.join(F.broadcast(carried), "range").withColumn("of", F.coalesce("interval", "carried"))
    at = F.least(F.greatest((F.col("point") - F.col("of.point")) / F.col("of.width"), F.lit(0.0)), F.lit(1.0))
    return found.select("slot", F.col("of.edge").alias("number"), at.alias("at"))


def schedule(sources: DataFrame, block: int = BLOCK_WORDS, sequence: str = "golden", start: int = 0) -> DataFrame:
    """slot, number, rank, lap, block, take: the blocks that the mix serves, in the order of slots, and how many words of each."""
    total = int(sources.agg(F.sum("slots")).first()[0] or 0)
    drawn = saved(slots_of(sources, sequence, start).withColumn("chunk", F.shiftright("slot", CHUNK_BITS)))
    counts = drawn.groupBy("chunk", "number").agg(F.count("*").alias("n"))
    earlier = Window.partitionBy("number").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    counts = saved(counts.withColumn("before", F.coalesce(F.sum("n").over(earlier), F.lit(0))))
    inside = Window.partitionBy("chunk", "number").orderBy("slot")
    ranked = drawn.join(counts, ["chunk", "number"]).select("slot", "number", "at", (F.col("before") + F.row_number().over(inside) - 1).alias("rank"))
    needs = sources.where("slots > 0").select("number", "size", "words", "whole", F.col("lap").alias("in_lap"), "slots", "slots_before", "stride")
    # blocks that the points have missed
    short = needs.join(counts.groupBy("number").agg(F.sum("n").alias("given")), "number", "left").withColumn("given", F.coalesce("given", F.lit(0))).where("given < slots")
    rest = short.withColumn("rank", F.explode(F.expr("sequence(given, slots - 1)"))).select((F.lit(total) + F.col("slots_before") + F.col("rank")).alias("slot"), "number", F.lit(0.0).alias("at"), "rank")
    rows = ranked.unionByName(rest).join(checked(needs), "number").where("rank < slots").withColumns({"lap": F.expr("rank div in_lap"), "place": F.expr("rank % in_lap")})
    begin = rows.where("place = 0").select("number", "lap", F.expr("cast(least(floor(at * whole), whole - 1) as bigint)").alias("begin"))  # a row for each lap of a source
    rows = rows.join(checked(saved(begin)), ["number", "lap"])
    # products of large numbers need decimals
    shuffled = "cast((cast(place as decimal(19, 0)) * cast(stride as decimal(19, 0)) + begin) % whole as bigint)"
    rows = rows.withColumn("block", F.expr(f"if(place < whole, {shuffled}, whole)"))
    take = f"least(least({block}, size - block * {block}), words - lap * size - place * {block})"
    return rows.select("slot", "number", "rank", "lap", "block", F.expr(take).alias("take"))


def placed(sized: DataFrame, sources: DataFrame, seed: int = SEED) -> DataFrame:
    """sized with number (of the source), place (unique in it) and first (word of the source's stream)."""
    buckets = 1 << max(0, (sized.count() // ROWS_PER_BUCKET).bit_length())
    numbers = sources.select(F.col("source").alias("named"), "number")
    docs = sized.join(checked(numbers), F.col("source").eqNullSafe(F.col("named"))).drop("named")
    docs = docs.withColumn("h", F.xxhash64("doc_id", "size", "key", F.lit(seed))).withColumn("bucket", F.pmod(F.shiftrightunsigned("h", 20), F.lit(buckets)))
    totals = docs.groupBy("number", "bucket").agg(F.sum("size").alias("words"), F.count("*").alias("rows"))
    before = Window.partitionBy("number").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    totals = totals.select("number", "bucket", F.coalesce(F.sum("words").over(before), F.lit(0)).alias("w0"), F.coalesce(F.sum("rows").over(before), F.lit(0)).alias("r0"))
    inside = Window.partitionBy("number", "bucket").orderBy("h", "doc_id", "size", "key")
    docs = docs.withColumns({"w": F.coalesce(F.sum("size").over(inside.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)), "r": F.row_number().over(inside)})
    docs = docs.join(totals, ["number", "bucket"])
    return docs.select("doc_id", "source", "size", "key", "number", (F.col("r0") + F.col("r")).alias("place"), (F.col("w0") + F.col("w")).alias("first"))


def mix_documents(docs: DataFrame, block: int = BLOCK_WORDS, seed: int = SEED, sequence: str = "golden", start: int = 0) -> tuple[DataFrame, DataFrame, DataFrame]:
    """(documents with their place, pieces of the mix, sources).

    A piece is a run of words of one document in one slot: slot, lap, number, place, key, doc_id, from_word, n.
    """
    sized = saved(with_size(docs))
    sources = sources_of(sized, block)
    at = saved(placed(sized, sources, seed))
    spans = at.where("size > 0").withColumn("block", F.explode(F.expr(f"sequence(first div {block}, (first + size - 1) div {block})")))
    served = schedule(sources, block, sequence, start).select("slot", "number", "lap", "block", "take")
    pieces = spans.join(served, ["number", "block"])
    pieces = pieces.withColumns({"a": F.greatest("first", F.col("block") * block), "z": F.least(F.col("first") + F.col("size"), F.col("block") * block + F.col("take"))}).where("a < z")
    return at, pieces.select("slot", "lap", "number", "place", "key", "doc_id", (F.col("a") - F.col("first")).alias("from_word"), (F.col("z") - F.col("a")).alias("n")), sources


def taken_words(docs: DataFrame, **options) -> DataFrame:
    """doc_id, source, size, source_size, target, taken, first_slot (null if nothing is taken), n_slots for every row of docs."""
    at, pieces, sources = mix_documents(docs, **options)
    ends = sources.select("number", F.col("size").alias("source_size"), "target")
    taken = pieces.groupBy("number", "place").agg(F.sum("n").alias("taken"), F.min("slot").alias("first_slot"), F.count("*").alias("n_slots"))
    out = at.join(taken, ["number", "place"], "left").join(checked(ends), "number", "left")
    zero = lambda name: F.coalesce(name, F.lit(0)).cast("bigint").alias(name)
    return out.select("doc_id", "source", "size", "source_size", "target", zero("taken"), "first_slot", zero("n_slots"))


def _runs(parts: list[dict]) -> list[tuple[int, int]]:
    """(first word, word after the last) of what is taken, by lap and then place, with neighbours joined."""
    out: list[tuple[int, int, int]] = []
    for p in sorted(parts, key=lambda p: (p["lap"], p["from_word"])):
        if out and out[-1][0] == p["lap"] and out[-1][2] == p["from_word"]:
            out[-1] = (p["lap"], out[-1][1], p["from_word"] + p["n"])
        else:
            out.append((p["lap"], p["from_word"], p["from_word"] + p["n"]))
    return [(a, z) for _, a, z in out]


def mixed_texts(docs: DataFrame) -> DataFrame:
    """docs as the mix takes them: of each text the words taken, all other columns as they were.

    A text taken whole once stays as it is; else its runs of words that the mix takes, lap by lap, stand on
    a line each, a run of all words as the whole text.  Documents of which nothing is taken go, empty ones
    included.  Rows that are alike in all columns each give what their own place gives.  n_chars, where
    there is one, follows the text.
    """
    name, runs = "mix key", "mix runs"
    _, pieces, _ = mix_documents(docs)
    # as many runs as the text has blocks in MAX_EPOCHS laps
    given = saved(pieces.groupBy("number", "place", F.col("key").alias(name)).agg(F.collect_list(F.struct("lap", "from_word", "n")).alias(runs)).select(name, runs))
    repeated = saved(given.groupBy(name).agg(F.count("*").alias("n")).where("n > 1").select(name))
    named = docs.withColumn(name, F.xxhash64(*_hashable(docs)))
    if not at_most(repeated, 0):  # one row stands for those that are alike, and meets what each of them gives
        named = named.join(checked(repeated), name, "left_anti").unionByName(named.join(checked(repeated), name, "left_semi").dropDuplicates([name]))
    joined = named.join(given, name).select(*docs.columns, runs)
    text, count = joined.columns.index("text"), joined.columns.index(runs)

    def cut(batches):
        for batch in batches:
            texts: list[str] = []
            wanted = batch.column(count)
            for a, _, w in kernel.steps(batch):
                raw = w.data.tobytes()
                for i in range(w.rows):
                    lo, n = int(w.row_words[i]), int(w.row_words[i + 1] - w.row_words[i])
                    whole = raw[int(w.row_bytes[i]) : int(w.row_bytes[i + 1])]
                    texts.append(b"\n".join([whole if (x, z) == (0, n) else raw[int(w.starts[lo + x]) : int(w.ends[lo + z - 1])] for x, z in _runs(wanted[a + i].as_py())]).decode())
            columns = [pa.array(texts, pa.string()) if i == text else batch.column(i) for i in range(batch.num_columns)]
            yield pa.RecordBatch.from_arrays(columns[:count] + columns[count + 1 :], batch.schema.names[:count] + batch.schema.names[count + 1 :])

    out = joined.mapInArrow(cut, joined.drop(runs).schema)
    return out.withColumn("n_chars", F.length("text").cast("bigint")) if "n_chars" in docs.columns else out


def op5_mixing(spark, sf_dir: str) -> DataFrame:
    return taken_words(table(spark, sf_dir, "documents")).drop("source")


QUERIES = {"op5_mixing": op5_mixing}
ORACLES: dict[str, str] = {}
