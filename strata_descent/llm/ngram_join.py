"""N-gram Jaccard join: blocked sparse matrix product of the document by shingle incidence.

Documents with equal shingle sets form a class, and only classes are joined.  Two sets of sizes x and
y can be that similar only if they share at least T / (1 + T) * (x + y) shingles.  Candidates come from
an extended prefix filter: a set posts its 1 + (1 - T) * n + d least shingles by hash, so two similar
sets share at least 1 + d of them; each set may then leave out its d most frequent postings, by one
order for all, and still shares one.  That removes the passages that many documents hold in common,
whatever their number, without losing a pair.  Only shingles that two classes post are candidates.

Classes that postings tie together, directly or through others, are gathered into blocks; a block holds
many small such sets, and a large one is split by size and hash, so blocks are bounded in rows and
shingles.  A pair of blocks is a tile if the two share a posting.  A tile multiplies its two incidence matrices, accumulates overlap counts,
drops pairs below the bound, and reports each class's links and a spanning forest.  Every pair is in
one tile, so links are counted once.  Copies are never expanded, and no tile is larger than two blocks.

A shingle that very many classes post is dealt over several tasks by class; which ones are, a sample of
the rows tells, and that changes no result.

Shingles are 64-bit hashes of lower-cased words.  Null and empty texts have no shingles and link with
nothing.  Rows are told apart by a hash of id and text: rows that repeat a document are copies of it, and
so are rows without an id, which link like others; component_id is the least id that a component has, null
if none of its rows has one.  Columns other than doc_id and text are not looked at.  An empty table gives
an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import words as kernel
from .common import at_most, checked, documents, marks, row_key, saved, table, where_marked
from .components import components

N = 5
PERCENT = 75
SPARE = 0.15
BLOCK_ROWS = 256
BLOCK_SHINGLES = 1 << 17
#: Classes whose postings a task has just sent are not sent again while they are among so many.
REMEMBERED = 100_000
#: A shingle that has more than one in HOT_SHARE of a sample's postings, and more than HOT_LEAST of them, is dealt over SALTS tasks.
SAMPLE, HOT_SHARE, HOT_LEAST, SALTS = 1 / 64, 100_000, 64, 64
U64 = np.uint64


def shingle_sets(w: kernel.Words) -> tuple[np.ndarray, np.ndarray]:
    """(row, shingle) of the distinct shingles, ascending in each row."""
    h = w.hashes(lower=True)
    grams, first = w.grams(N, h)
    row = w.row_of_word()
    counts = w.counts()
    short = np.flatnonzero((counts > 0) & (counts < N))
    if len(short):
        whole = np.zeros(len(short), dtype=U64)
        with np.errstate(over="ignore"):
            for j in range(N - 1):
                has = counts[short] > j
                whole[has] = kernel.mix(whole[has] + h[w.row_words[:-1][short[has]] + j], 31 + j)
        return kernel.row_sets(np.concatenate([row[first], short]), np.concatenate([grams, whole]))
    return kernel.row_sets(row[first], grams)


def _class_keys(rows: int, row: np.ndarray, shingle: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(set sizes, class keys): a key hashes a whole set."""
    n = np.bincount(row, minlength=rows)
    key = np.zeros(rows, dtype=U64)
    np.add.at(key, row, kernel.mix(shingle, 77))
    return n, kernel.mix(key + n.astype(U64), 13)


def heads(docs: DataFrame) -> DataFrame:
    """doc_id, rid, n, key for every row of docs."""

    def found(batches):
        for batch in batches:
            parts = [_class_keys(w.rows, *shingle_sets(w)) for _, _, w in kernel.steps(batch)]
            n = np.concatenate([p[0] for p in parts]) if parts else np.zeros(0, dtype=np.int64)
            key = np.concatenate([p[1] for p in parts]) if parts else np.zeros(0, dtype=U64)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(n.astype(np.int64)), pa.array(key.view(np.int64))], ["doc_id", "rid", "n", "key"])

    kept = documents(docs).select("doc_id", row_key().alias("rid"), "text")
    return kept.mapInArrow(found, f"doc_id {kept.schema['doc_id'].dataType.simpleString()}, rid bigint, n bigint, key bigint")


def spare(n: np.ndarray | F.Column):
    """Postings beyond the prefix, as many as may be left out again."""
    return np.floor(SPARE * n).astype(np.int64) if isinstance(n, np.ndarray) else F.floor(F.lit(SPARE) * n)


def postings(docs: DataFrame) -> DataFrame:
    """(shingle, key): the extended prefixes of all classes, each from at least one of its copies."""

    def found(batches):
        sent: set[int] = set()
        for batch in batches:
            for _, _, w in kernel.steps(batch):
                row, shingle = shingle_sets(w)
                n, key = _class_keys(w.rows, row, shingle)
                length = np.minimum(n, n - (n * PERCENT + 99) // 100 + 1 + spare(n))
                fresh = np.zeros(w.rows, dtype=bool)
                for i, k in enumerate(key.tolist()):
                    if n[i] and k not in sent:
                        fresh[i] = True
                        sent.add(k)
                if len(sent) > REMEMBERED:
                    sent.clear()
                begin = np.cumsum(n) - n
                keep = (np.arange(len(row)) - begin[row] < length[row]) & fresh[row]
                yield pa.RecordBatch.from_arrays([pa.array(shingle[keep].view(np.int64)), pa.array(key[row[keep]].view(np.int64))], ["shingle", "key"])

    return documents(docs).mapInArrow(found, "shingle bigint, key bigint")


def hot_shingles(docs: DataFrame) -> DataFrame:
    """(shingle, hot): at most HOT_SHARE shingles that far more postings have than others, by a sample of the rows."""
    counts = saved(postings(docs.sample(SAMPLE, seed=7)).groupBy("shingle").count())
    total = counts.agg(F.sum("count")).first()[0] or 0
    return counts.where(F.col("count") > max(HOT_LEAST, total // HOT_SHARE)).select("shingle", F.lit(True).alias("hot"))


def candidates(docs: DataFrame, classes: DataFrame) -> DataFrame:
    """(shingle, key, salt, pivot) of the postings that are left: those that classes share, less what each may leave out.

    salt: null but for the parts of a hot shingle; pivot: the least class of the shingle, or of the part.
    The order by which postings are left out is the same for all: hot shingles first, then by frequency.
    """
    salt = F.when(F.col("hot"), F.pmod("key", F.lit(SALTS))).alias("salt")
    posted = postings(docs).join(F.broadcast(saved(hot_shingles(docs))), "shingle", "left").select("shingle", "key", salt)
    of_shingle = Window.partitionBy("shingle", "salt")
    posted = posted.withColumns({"df": F.count("*").over(of_shingle), "least": F.min("key").over(of_shingle), "most": F.max("key").over(of_shingle)})
    shared = saved(posted.where("salt is not null or least != most").select("shingle", "key", "salt", F.when(F.col("salt").isNull(), F.col("df")).otherwise(1 << 62).alias("df")))
    shared = shared.groupBy("shingle", "key", "salt").agg(F.max("df").alias("df")).join(classes.select("key", "n"), "key")
    by_frequency = Window.partitionBy("key").orderBy(F.desc("df"), "shingle")
    left = shared.withColumn("place", F.row_number().over(by_frequency)).where(F.col("place") > spare(F.col("n"))).select("shingle", "key", "salt")
    left = left.withColumns({"m": F.count("*").over(of_shingle), "pivot": F.min("key").over(of_shingle)})
    return saved(left.where("salt is not null or m > 1").select("shingle", "key", "salt", "pivot"))


def blocks(left: DataFrame, classes: DataFrame) -> DataFrame:
    """(key, n, copies, block, band): band is a class's size step within a split label, else -1.

    A label is a component of the graph that ties each class to the pivots of its postings, and the
    pivots of a hot shingle's parts to each other.
    """
    parts = left.where("salt is not null").select("shingle", "pivot").distinct()
    ties = parts.select(F.col("pivot").alias("a"), F.min("pivot").over(Window.partitionBy("shingle")).alias("b"))  # SALTS rows of a shingle
    roots = components(left.select(F.col("key").alias("a"), F.col("pivot").alias("b")).unionByName(ties))
    label = roots.select(F.col("node").alias("key"), F.col("root").alias("label"))
    sized = saved(label.join(classes, "key").withColumn("step", F.floor(F.log("n") / F.log(F.lit(100 / PERCENT)))))
    need = lambda rows, shingles: F.ceil(F.greatest(rows / F.lit(BLOCK_ROWS), shingles / F.lit(BLOCK_SHINGLES)))
    banded = sized.groupBy("label", "step").agg(F.count("*").alias("rows"), F.sum("n").alias("shingles"))
    whole = banded.groupBy("label").agg(need(F.sum("rows"), F.sum("shingles")).alias("parts")).where("parts > 1").select("label")
    banded = saved(banded.join(whole, "label").select("label", "step", need(F.col("rows"), F.col("shingles")).alias("band_parts")))
    total = sized.agg(need(F.count("*"), F.sum("n"))).first()[0] or 1
    # a label that fits into a block shares one with others; a larger one is split by size and then by hash
    sized = sized.join(checked(banded), ["label", "step"], "left")
    alone = F.col("band_parts").isNotNull()
    block = F.when(alone, F.xxhash64("label", "step", F.pmod(F.xxhash64("key"), "band_parts"))).otherwise(F.pmod(F.xxhash64("label"), F.lit(total)))
    return sized.select("key", "n", "copies", block.alias("block"), F.when(alone, F.col("step")).otherwise(-1).alias("band"))


def tiles(left: DataFrame, placed: DataFrame) -> DataFrame:
    """(a, b): pairs of blocks, a <= b, of which members share a posting and sizes allow a link.

    A label that was not split shares postings with no other.
    """
    split = placed.where("band >= 0").select("key", "block", "band")
    at = left.join(split, "key").select("shingle", "block", "band").distinct()
    other = at.select("shingle", F.col("block").alias("b"), F.col("band").alias("band_b"))
    pairs = at.withColumnRenamed("block", "a").join(other, "shingle").where("a <= b and abs(band - band_b) <= 1")
    whole = placed.where("band < 0").select(F.col("block").alias("a"), F.col("block").alias("b"))
    return pairs.select("a", "b").unionByName(whole).distinct()


def overlaps(one: tuple[np.ndarray, np.ndarray], two: tuple[np.ndarray, np.ndarray] | None, rows: tuple[int, int]) -> np.ndarray:
    """Counts of shared shingles of each row of one with each row of two (None: with one itself).

    one, two: (row, shingle).  A shingle of few rows adds to its pairs; columns of many are multiplied.
    """
    n = rows[0] + (rows[1] if two is not None else 0)
    row = one[0] if two is None else np.concatenate([one[0], two[0] + rows[0]])
    value = one[1] if two is None else np.concatenate([one[1], two[1]])
    order = np.argsort(value, kind="stable")
    row, value = row[order], value[order]
    edge = np.flatnonzero(np.concatenate([[True], value[1:] != value[:-1]])) if len(value) else np.zeros(0, dtype=np.int64)
    count = np.diff(np.append(edge, len(value)))
    out = np.zeros(n * n, dtype=np.float32)
    few = np.repeat(count <= 12, count)
    r, v = row[few], value[few]
    for step in range(1, 12):
        same = np.flatnonzero(v[:-step] == v[step:]) if len(v) > step else np.zeros(0, dtype=np.int64)
        if not len(same):
            break
        out += np.bincount(r[same] * n + r[same + step], minlength=n * n)
        out += np.bincount(r[same + step] * n + r[same], minlength=n * n)
    out = out.reshape(n, n)
    many = np.repeat(count > 12, count)
    r, column = row[many], np.repeat(np.arange((count > 12).sum()), count[count > 12])
    for first in range(0, int(column[-1]) + 1 if len(column) else 0, 2048):
        a, z = np.searchsorted(column, [first, first + 2048])
        part = np.zeros((n, 2048), dtype=np.float32)
        part[r[a:z], column[a:z] - first] = 1
        out += part @ part.T
    return out if two is None else out[: rows[0], rows[0] :]


def _linked(counts: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    shared = counts.astype(np.int64)
    return (100 * shared >= PERCENT * (x[:, None] + y[None, :] - shared)) & (shared > 0)


def _tile(rows: pa.Table) -> pa.Table:
    """(key, root, links) of every class of the tile that has a link there."""
    _, first = np.unique(np.stack([rows["side"].to_numpy(), rows["key"].to_numpy()]), axis=1, return_index=True)
    rows = rows.take(np.sort(first))  # a class sent by two rows of one id counts once
    side, name, n, copies = (rows[c].to_numpy() for c in ("side", "key", "n", "copies"))
    lists = rows["shingles"].combine_chunks()
    value, length = lists.flatten().to_numpy().view(U64), lists.value_lengths().to_numpy()
    order = np.argsort(side, kind="stable")
    m = int((side == 0).sum())
    row = np.empty(len(side), dtype=np.int64)
    row[order] = np.arange(len(side))
    each = np.repeat(row, length)
    first_side = each < m
    size, copy, names = n[order], copies[order], name[order]
    if m == len(side):
        link = _linked(overlaps((each, value), None, (m, 0)), size, size)
        np.fill_diagonal(link, False)
    else:
        across = _linked(overlaps((each[first_side], value[first_side]), (each[~first_side] - m, value[~first_side]), (m, len(side) - m)), size[:m], size[m:])
        link = np.zeros((len(side), len(side)), dtype=bool)
        link[:m, m:] = across
        link[m:, :m] = across.T
    links = link @ copy
    root = np.full(len(side), -1)
    for i in np.argsort(names):
        if root[i] < 0 and links[i]:
            reached = np.zeros(len(side), dtype=bool)
            reached[i] = True
            edge = reached
            while edge.any():
                edge = link[edge].any(axis=0) & ~reached
                reached |= edge
            root[reached] = i
    has = links > 0
    return pa.table({"key": pa.array(names[has]), "root": pa.array(names[root[has]]), "links": pa.array(links[has].astype(np.int64))})


def class_links(docs: DataFrame, classes: DataFrame, repeated: bool = True) -> DataFrame:
    """(key, root, links), a row for each tile in which a class has links; repeated: whether rows may repeat id and text."""
    left = candidates(docs, classes)
    placed = saved(blocks(left, classes))
    pairs = saved(tiles(left, placed))
    tile = F.xxhash64("a", "b").alias("tile")
    sides = pairs.select(tile, F.col("a").alias("block"), F.lit(0).alias("side")).unionByName(pairs.where("a != b").select(tile, F.col("b").alias("block"), F.lit(1).alias("side")))

    def sets(batches):
        for batch in batches:
            for a, z, w in kernel.steps(batch):
                row, shingle = shingle_sets(w)
                n, key = _class_keys(w.rows, row, shingle)
                at = np.concatenate([[0], np.cumsum(n)]).astype(np.int32)
                yield pa.RecordBatch.from_arrays([batch.column(0).slice(a, z - a), pa.array(key.view(np.int64)), pa.ListArray.from_arrays(pa.array(at), pa.array(shingle.view(np.int64)))], ["rid", "key", "shingles"])

    into = saved(placed.join(classes.select("key", "rid"), "key").select("key", "rid", "n", "copies", "block").join(sides, "block").drop("block"))
    # only the row that stands for its class sends the set; what the bitmap lets through beyond that, the join drops
    rows = where_marked(documents(docs).select(row_key().alias("rid"), "text"), marks(into)).mapInArrow(sets, "rid bigint, key bigint, shingles array<bigint>")
    rows = (rows.dropDuplicates(["rid", "key"]) if repeated else rows).join(checked(into), ["rid", "key"])
    return rows.select("tile", "side", "key", "n", "copies", "shingles").groupBy("tile").applyInArrow(_tile, "key bigint, root bigint, links bigint")


def classes_of(head: DataFrame) -> DataFrame:
    """(key, n, copies, doc_id, rid): the classes of equal sets, with the row of least id that stands for each."""
    first = F.min(F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id", "rid"))
    found = head.where("n > 0").groupBy("key").agg(F.max("n").alias("n"), F.count("*").alias("copies"), first.alias("first"))
    return found.select("key", "n", "copies", "first.doc_id", "first.rid")


def components_of(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(heads, classes): a head for every row; for each class its component's least doc_id and the rid of that row, and n_links."""
    head = saved(heads(docs))
    classes = saved(classes_of(head))
    repeated = not at_most(head.where("n > 0").groupBy("rid").count().where("count > 1"), 0)
    found = saved(class_links(docs, classes, repeated))
    links = found.groupBy("key").agg(F.sum("links").alias("links"))
    roots = components(found.select(F.col("key").alias("a"), F.col("root").alias("b")))
    member = classes.join(roots.withColumnRenamed("node", "key"), "key", "left").withColumn("root", F.coalesce("root", "key"))
    least = member.groupBy("root").agg(F.min(F.struct(F.col("doc_id").isNull().alias("unnamed"), "doc_id", "rid")).alias("first"))
    of_class = member.join(least, "root").join(links, "key", "left")
    return head, of_class.select("key", F.col("first.doc_id").alias("component_id"), F.col("first.rid").alias("first_rid"), (F.col("copies") - 1 + F.coalesce("links", F.lit(0))).alias("n_links"))


def join_documents(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, component_id, n_links (other rows that the row links with) for every row of docs."""
    head, of_class = components_of(docs)
    out = head.join(of_class, (head.key == of_class.key) & (head.n > 0), "left")
    component = F.when(of_class.key.isNull(), head.doc_id).otherwise(F.col("component_id"))
    return out.select(head.doc_id, head.n.alias("n_shingles"), component.alias("component_id"), F.coalesce("n_links", F.lit(0)).cast("bigint").alias("n_links"))


def keep_one(docs: DataFrame) -> DataFrame:
    """One row of each component, the one of least id (rows without one come last), and all rows without words.

    A bitmap of the rows that have to be looked up keeps the texts of the others from moving.
    """
    head, of_class = components_of(docs)
    name, first = "row key", "row first"  # no operator's and hardly a table's column names
    rows = head.where("n > 0").join(of_class, "key").groupBy(F.col("rid").alias(name)).agg(F.count("*").alias("times"), F.max(F.col("rid") == F.col("first_rid")).alias(first))
    looked = saved(rows.where(f"times > 1 or not `{first}`").select(name, first))
    named, bitmap = docs.withColumn(name, row_key()), marks(looked, name)
    found = where_marked(named, bitmap, name).join(looked, name, "left")
    out = where_marked(named, bitmap, name, marked=False).unionByName(found.where(F.col(first).isNull()).drop(first))
    if not at_most(looked.where(f"`{first}`"), 0):  # rows that repeat id and text
        out = out.unionByName(found.where(F.col(first)).drop(first).dropDuplicates([name]))
    return out.drop(name)


def op1_ngram_join(spark, sf_dir: str) -> DataFrame:
    return join_documents(table(spark, sf_dir, "documents"))


QUERIES = {"op1_ngram_join": op1_ngram_join}
ORACLES = {
    "op1_ngram_join": r"""
    with recursive words as (
      select doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') as w
      from documents),
    shingles as (
      select doc_id, unnest(case when len(w) = 0 then [] when len(w) < 5 then [array_to_string(w, ' ')]
        else list_distinct(list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' '))) end) as s
      from words),
    sizes as (select doc_id, count(*) as n from shingles group by doc_id),
    ids as (select s, row_number() over () as i from (select s from shingles group by s having count(*) > 1)),
    short as (select doc_id, i from shingles join ids using (s)),
    overlap as (
      select a.doc_id as a, b.doc_id as b, count(*) as shared
      from short a join short b on a.i = b.i and a.doc_id <> b.doc_id group by 1, 2),
    links as (
      select a, b from overlap join sizes x on x.doc_id = a join sizes y on y.doc_id = b
      where 100 * shared >= 75 * (x.n + y.n - shared)),
    reached as (
      select doc_id as a, doc_id as b from documents
      union
      select r.a, l.b from reached r join links l on r.b = l.a),
    least as (select a, min(b) as component_id from reached group by a),
    counts as (select a, count(*) as n_links from links group by a)
    select d.doc_id, coalesce(z.n, 0) as n_shingles, m.component_id, coalesce(c.n_links, 0) as n_links
    from documents d join least m on m.a = d.doc_id left join sizes z on z.doc_id = d.doc_id left join counts c on c.a = d.doc_id"""
}
