"""Document fingerprints from closed syncmers, by DataFrame functions only.

A text of any size is a sequence of words.  A run of K of them is a closed syncmer if the least hash
among its inner runs of S stands at its first or last place.  Whether a run is chosen depends on that
run alone, so an edit elsewhere never moves an anchor.  The fingerprint keeps the ``ANCHORS`` distinct
anchors of least hash, each with its least place, so its size is bounded whatever the text and copies
of a passage take no room; a sequence shorter than K is one anchor, an empty text has none.  Likeness
compares two fingerprints place by place: anchors of equal hash vote for a shift, and only those within
``SLACK`` places of the median shift count, over the anchors of the merged sketch.

Texts are dealt once, by ranges of ids, and a text meets the next one as its neighbour in the order of
its range; the first text of a range goes to the end of the range before it too.  The ranges' bounds are
approximate quantiles of the ids, so no task sees more than some ranges, and nothing is broadcast.

Null texts are empty.  Two empty fingerprints have likeness 1, one empty fingerprint 0.  Rows that
repeat a doc_id each get a result; as someone's next document such an id stands for its row of least text.
Rows without a doc_id have no next document and are nobody's.  Equal texts have equal fingerprints.
Columns other than doc_id and text are not looked at.  An empty table gives an empty result.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import at_most, checked, documents, saved, table, words_column

K, S, ANCHORS, SLACK = 8, 2, 48, 64
RANGES = 4  # of ids, for each shuffle partition


def anchors(text: str) -> str:
    """SQL for the array of struct(h, i), by hash, of the chosen anchors of a text column."""
    inner = f"transform(sequence(0, size(t) - {S}), i -> xxhash64({', '.join(f't[i + {j}]' for j in range(S))}))"
    last = K - S
    middle = ", ".join(f"s[i + {j}]" for j in range(1, last))
    chosen = f"""filter(sequence(0, size(s) - {last + 1}), i -> least(s[i], s[i + {last}]) <= least({middle}))"""
    hashed = f"""transform({chosen}, i -> struct(xxhash64({', '.join(f's[i + {j}]' for j in range(0, last + 1, S))}) as h, i as i))"""
    long = f"transform(array({inner}), s -> array_sort({hashed}))[0]"
    whole = "array(struct(xxhash64(concat_ws(' ', t)) as h, 0 as i))"
    some = f"case when {text} = '' then array() when size(t) < {K} then {whole} else {long} end"
    firsts = f"transform(array({some}), a -> filter(a, (x, k) -> k = 0 or a[k - 1].h != x.h))[0]"
    return f"transform(array({words_column(text)}), t -> slice({firsts}, 1, {ANCHORS}))[0]"


def likeness(a: str, b: str) -> str:
    """SQL for the likeness, 0 to 1, of two arrays of anchors."""
    shared = f"filter(transform({a}, x -> struct(x.h as h, x.i as i, element_at(bm, x.h) as j)), x -> x.j is not null)"
    shifts = "transform(m, x -> x.i - x.j)"
    voted = f"""transform(array(sort_array({shifts})), d -> size(filter(d, x -> abs(x - d[cast(floor(size(d) / 2) as int)]) <= {SLACK})))[0]"""
    # of the merged sketch only the least min(|a|, |b|) hashes are known on both sides
    bound = f"least(if(size({a}) < {ANCHORS}, 9223372036854775807L, {a}[{ANCHORS - 1}].h), if(size({b}) < {ANCHORS}, 9223372036854775807L, {b}[{ANCHORS - 1}].h))"
    size = f"size(array_union(transform(filter({a}, x -> x.h <= lim), x -> x.h), transform(filter({b}, x -> x.h <= lim), x -> x.h)))"
    score = f"""transform(array({bound}), lim -> transform(array(map_from_arrays(transform({b}, x -> x.h), transform({b}, x -> x.i))), bm ->
        transform(array(filter({shared}, x -> x.h <= lim)), m -> if(size(m) = 0, 0D, cast({voted} as double) / {size}))[0])[0])[0]"""
    return f"case when size({a}) = 0 and size({b}) = 0 then 1D when size({a}) = 0 or size({b}) = 0 then 0D else {score} end"


def as_text(a: str) -> str:
    return f"concat_ws(',', transform({a}, x -> concat(lower(hex(x.h)), ':', x.i)))"


def fingerprint_documents(docs: DataFrame) -> DataFrame:
    """doc_id, text, n_chars, marks: one row per row of docs."""
    return documents(docs).withColumns({"n_chars": F.length("text").cast("bigint"), "marks": F.expr(anchors("text"))})


def in_ranges(chain: DataFrame) -> DataFrame:
    """chain (distinct doc_id, text, more) dealt by part, a range of ids; rows with ghost repeat the first row of the next range, after all others."""
    spark = chain.sparkSession
    n = RANGES * max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))
    least, cuts = chain.agg(F.min("doc_id"), F.percentile_approx("doc_id", [i / n for i in range(1, n)] or [0.5], max(10_000, 10 * n))).first()
    cuts = sorted({c for c in cuts or () if c > least})  # quantiles are ids themselves, so each is the first of its range
    group = max(1, math.isqrt(len(cuts)))
    bounds = F.split(F.lit(",".join(map(str, cuts))), ",").cast("array<bigint>") if cuts else F.array().cast("array<bigint>")
    tops = F.split(F.lit(",".join(map(str, cuts[::group]))), ",").cast("array<bigint>") if cuts else bounds
    below = lambda array: F.size(F.filter(array, lambda c: c <= F.col("doc_id")))
    placed = chain.withColumn("top", below(tops))
    placed = placed.withColumn("part", F.when(F.col("top") == 0, 0).otherwise((F.col("top") - 1) * group + below(F.slice(bounds, (F.col("top") - 1) * group + 1, group)))).drop("top")
    first = (F.col("doc_id") == F.lit(least)) | F.coalesce(F.get(bounds, F.col("part") - 1) == F.col("doc_id"), F.lit(False))
    before = F.pmod(F.col("part") - 1, F.lit(len(cuts) + 1))
    home = F.struct(F.col("part").alias("part"), F.lit(False).alias("ghost"))
    there = F.when(first, F.array(home, F.struct(before.alias("part"), F.lit(True).alias("ghost")))).otherwise(F.array(home))
    return placed.withColumn("there", F.explode(there)).drop("part").select("*", "there.part", "there.ghost").drop("there").repartition("part")


def with_next(chain: DataFrame) -> DataFrame:
    """chain with marks, next_text and next_marks: those of the row of the next greater id, round to the first."""
    order = Window.partitionBy("part").orderBy("ghost", "doc_id")
    rows = in_ranges(chain).withColumn("marks", F.expr(anchors("text")))
    return rows.withColumns({"next_text": F.lead("text").over(order), "next_marks": F.lead("marks").over(order)}).where("not ghost").drop("part", "ghost")


def against_edits(docs: DataFrame) -> DataFrame:
    """Fingerprints of every text and of its edited text, and their likeness, per row of docs."""
    rows = documents(docs)
    named, unnamed = rows.where("doc_id is not null"), rows.where("doc_id is null")
    repeated = saved(named.groupBy("doc_id").count().where("count > 1").select("doc_id"))
    columns = ["doc_id", "text", "marks", "next_text", "next_marks"]
    alone = unnamed.withColumn("marks", F.expr(anchors("text"))).select("doc_id", "text", "marks", F.lit(None).cast("string").alias("next_text"), F.expr("if(false, marks, null)").alias("next_marks"))
    if at_most(repeated, 0):
        out = with_next(named).select(*columns)
    else:  # such an id has one place in the order, and its rows get what follows that
        several = named.join(checked(repeated), "doc_id", "left_semi")
        stand_in = several.groupBy("doc_id").agg(F.min("text").alias("text"), F.lit(True).alias("several"))
        chain = with_next(named.join(checked(repeated), "doc_id", "left_anti").withColumn("several", F.lit(False)).unionByName(stand_in))
        follows = chain.where("several").select("doc_id", "next_text", "next_marks")
        out = chain.where("not several").select(*columns).unionByName(several.join(follows, "doc_id").withColumn("marks", F.expr(anchors("text"))).select(*columns))
    out = out.unionByName(alone).withColumn("n_chars", F.length("text").cast("bigint"))
    edited = F.expr("concat(left(text, cast(n_chars - floor(n_chars / 4) as int)), left(coalesce(next_text, ''), cast(floor(n_chars / 4) as int)))")
    out = out.withColumn("edited", edited).withColumn("edited_marks", F.expr(anchors("edited")))
    return out.select(
        "doc_id",
        "n_chars",
        F.sha2(F.col("edited").cast("binary"), 256).alias("edited_sha256"),
        F.expr(as_text("marks")).alias("fingerprint"),
        F.expr(as_text("edited_marks")).alias("edited_fingerprint"),
        F.expr(likeness("marks", "edited_marks")).alias("near_edited"),
        F.coalesce(F.expr(f"if(next_marks is null, null, {likeness('marks', 'next_marks')})"), F.lit(0.0)).alias("near_next"),
    )


def op4_fingerprints(spark, sf_dir: str) -> DataFrame:
    return against_edits(table(spark, sf_dir, "documents"))


QUERIES = {"op4_fingerprints": op4_fingerprints}
ORACLES: dict[str, str] = {}
