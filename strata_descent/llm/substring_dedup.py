"""Substring dedup: prefix-partitioned suffix trees find and remove passages that occur twice.

A window of ``WINDOW`` words belongs to the run of ``PREFIX`` words of least hash inside it, its
anchor; equal windows have equal anchors at equal places, so windows can only repeat where an anchor
does.  Occurrences of repeated anchors carry their surroundings (the words of all their windows) to
the partition of the anchor, which is a prefix of the suffix that starts there.  In a partition, equal
surroundings are merged, and a suffix tree is built over the suffixes of the rest: sorted by prefix
doubling on word numbers (of 64-bit word hashes), with longest common prefixes of neighbours.  Leaves below an internal
node of depth WINDOW or more are windows that start elsewhere too.

Prefixes are of variable length, so partitions have a bounded size: the occurrences of an anchor that
stands more than ``GROUP_ROWS`` times become one suffix for each of their windows, partitioned by the
first ``LONGER[0]`` words of the window, those groups that are still too large by more words, and so on;
where a prefix is a whole window its suffix tree is one node, and counting its leaves replaces the tree.
So no group is collected whole.

Rows are told apart by a hash of id and text, so that those without an id count like others and equal
rows share their result; a bitmap of fixed size keeps most texts without repeats from moving.  Windows
are judged on the input.  Null texts have no words; texts of fewer than WINDOW words lose none.  Rows
that repeat a document, with its id or without any, repeat its windows.  Columns other than doc_id and
text are not looked at.  An empty table gives an empty result.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import words as kernel
from .common import at_most, documents, marks, row_key, saved, table, where_marked

WINDOW = 35
PREFIX = 6
GROUP_ROWS = 100_000
#: Words of the prefixes of the windows of an anchor that is too frequent, one after the other.
LONGER = (12, 20, 28)
#: Surroundings of one tree: a task's memory is bounded by this many, and by words.
TREE_ROWS = 10_000
TREE_WORDS = 1 << 19
U64 = np.uint64


def row_keys(w: kernel.Words, hashes: np.ndarray) -> np.ndarray:
    """A hash of each row's whole word sequence; with the id it tells rows apart, and equal rows share it."""
    key = np.zeros(w.rows, dtype=U64)
    place = np.arange(len(hashes)) - np.repeat(w.row_words[:-1], w.counts())
    with np.errstate(over="ignore"):
        np.add.at(key, w.row_of_word(), kernel.mix(hashes + kernel.mix(place.astype(U64), 3)))
    return kernel.mix(key + w.counts().astype(U64), 5)


def anchor_places(w: kernel.Words, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(first word, hash, first window, last window) of the anchors, each with the windows that are its own."""
    empty = np.zeros(0, dtype=np.int64)
    grams, first = w.grams(PREFIX, hashes)
    inner = WINDOW - PREFIX + 1
    counts = np.maximum(w.counts() - WINDOW + 1, 0)
    if not counts.any():
        return empty, np.zeros(0, dtype=U64), empty, empty
    start = np.repeat(w.row_words[:-1] - np.cumsum(counts) + counts, counts) + np.arange(counts.sum())
    at = np.searchsorted(first, start)
    # sliding minimum by blocks: the least of a block's tail and the next block's head
    n = len(grams)
    padded = np.full(-(-(n + inner) // inner) * inner, np.iinfo(np.uint64).max, dtype=U64)
    padded[:n] = grams
    by_block = padded.reshape(-1, inner)
    head = np.minimum.accumulate(by_block, axis=1).ravel()
    tail = np.minimum.accumulate(by_block[:, ::-1], axis=1)[:, ::-1].ravel()
    least = np.minimum(tail[at], head[at + inner - 1])
    # the first place in the window that has the least hash: walk back from the last equal gram
    order = np.zeros(len(at), dtype=np.int64)
    open_ = np.arange(len(at))
    for j in range(inner):
        hit = grams[at[open_] + j] == least[open_]
        order[open_[hit]] = at[open_[hit]] + j
        open_ = open_[~hit]
        if not len(open_):
            break
    new = np.ones(len(at), dtype=bool)
    new[1:] = (order[1:] != order[:-1]) | (start[1:] != start[:-1] + 1)
    begin = np.flatnonzero(new)
    end = np.append(begin[1:], len(at)) - 1
    return first[order[begin]], least[begin], start[begin], start[end]


def keyed(docs: DataFrame) -> DataFrame:
    """doc_id, text, rid (hash of both) for every row of docs."""
    return documents(docs).withColumn("rid", row_key())


def anchors(rows: DataFrame) -> DataFrame:
    """(anchor, rid, m): the distinct anchors of every text of rows (rid, text), with their occurrences in it."""

    def found(batches):
        for batch in batches:
            for a, z, w in kernel.steps(batch):
                place, anchor, _, _ = anchor_places(w, w.hashes())
                row = np.searchsorted(w.row_words, place, side="right") - 1
                order = np.lexsort((anchor, row))
                row, anchor = row[order], anchor[order]
                first = np.flatnonzero(np.concatenate([[True], (row[1:] != row[:-1]) | (anchor[1:] != anchor[:-1])])) if len(row) else np.zeros(0, dtype=np.int64)
                m = np.diff(np.append(first, len(row)))
                yield pa.RecordBatch.from_arrays([pa.array(anchor[first].view(np.int64)), batch.column(0).slice(a, z - a).take(pa.array(row[first])), pa.array(m.astype(np.int32))], ["anchor", "rid", "m"])

    return rows.select("rid", "text").mapInArrow(found, "anchor bigint, rid bigint, m int")


def surroundings(rows: DataFrame, chosen: DataFrame) -> DataFrame:
    """(anchor, hot, rid, row, firsts, windows, words) of the chosen anchors.

    chosen: rid and picks, an array of (anchor, hot).  words: those of all windows of the anchor,
    joined by spaces; firsts: where in the text they start, as a text that repeats them sends them once.
    A hot anchor has a row for each window.
    """

    def found(batches):
        for batch in batches:
            picks_of = batch.column(2)
            for a, z, w in kernel.steps(batch):
                h = w.hashes()
                place, anchor, begin, end = anchor_places(w, h)
                row = np.searchsorted(w.row_words, place, side="right") - 1
                bound = np.searchsorted(row, np.arange(w.rows + 1))
                key = row_keys(w, h).view(np.int64)
                lists = picks_of.slice(a, z - a)
                out: list[list] = [[], [], [], [], [], [], []]
                raw = w.data.tobytes()
                for i in range(w.rows):
                    hot = {p["anchor"]: p["hot"] for p in lists[i].as_py() or ()}
                    same: dict[tuple[int, int, bytes], list[int]] = {}
                    for g in range(bound[i], bound[i + 1]):
                        name = int(anchor[g].view(np.int64))
                        if name not in hot:
                            continue
                        for lo, hi in [(begin[g], end[g])] if not hot[name] else [(s, s) for s in range(begin[g], end[g] + 1)]:
                            s, e = w.starts[lo : hi + WINDOW], w.ends[lo : hi + WINDOW]
                            text = b" ".join([raw[x:y] for x, y in zip(s.tolist(), e.tolist(), strict=True)])
                            same.setdefault((name, int(hi - lo + 1), text), []).append(int(lo - w.row_words[i]))
                    for (name, n, text), firsts in same.items():
                        for column, value in zip(out, (name, hot[name], a + i, int(key[i]), firsts, n, text), strict=True):
                            column.append(value)
                ids = batch.column(0).take(pa.array(out[2], pa.int64()))
                yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.bool_()), ids, pa.array(out[3], pa.int64()), pa.array(out[4], pa.list_(pa.int32())), pa.array(out[5], pa.int32()), pa.array(out[6], pa.binary()).cast(pa.string())], ["anchor", "hot", "rid", "row", "firsts", "windows", "words"])

    some = where_marked(rows.select("rid", "text"), marks(chosen))
    joined = some.join(chosen, "rid").select("rid", "text", "picks")
    return joined.mapInArrow(found, "anchor bigint, hot boolean, rid bigint, row bigint, firsts array<int>, windows int, words string")


def suffix_tree(names: np.ndarray, last: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(suffixes in order, longest common prefix of each with the one before) up to 64 words.

    names: word numbers of texts one after the other; last: bound of the text each word is in.
    Prefix doubling: the name of 2m words is the pair of names of m words; a text's end is a name of
    its own, less than all others.
    """
    n = len(names)
    levels = [names.astype(np.int64) + 1]
    at = np.arange(n)
    for k in range(6):
        ahead = at + (1 << k)
        inside = ahead < last
        behind = np.where(inside, levels[-1][np.minimum(ahead, n - 1)], 0)
        pair = levels[-1] * (n + 2) + behind
        levels.append(np.unique(pair, return_inverse=True)[1].astype(np.int64) + 1)
    order = np.argsort(levels[-1], kind="stable")
    common = np.zeros(n, dtype=np.int64)
    if n > 1:
        x, y = order[:-1].copy(), order[1:].copy()
        end_x, end_y = last[x], last[y]
        for k in range(6, -1, -1):
            ok = (x < end_x) & (y < end_y) & (x + (1 << k) <= end_x) & (y + (1 << k) <= end_y)
            ok &= levels[k][np.minimum(x, n - 1)] == levels[k][np.minimum(y, n - 1)]
            step = np.where(ok, 1 << k, 0)
            common[1:] += step
            x += step
            y += step
    return order, common


def repeated_windows(words: pa.Array, windows: np.ndarray, weight: np.ndarray) -> np.ndarray:
    """For the windows of the surroundings one after the other: whether a second occurrence is in the tree.

    weight: occurrences that have the very same surroundings.  Groups may stand together: a deep node
    holds equal windows, which are of one group.
    """
    w = kernel.split(*kernel._bytes_of(words))
    h = w.hashes()
    _, names = np.unique(h, return_inverse=True)
    owner = w.row_of_word()
    place = np.arange(len(h)) - w.row_words[:-1][owner]
    last = w.row_words[1:][owner]
    order, common = suffix_tree(names, last)
    starts = place < windows[owner]
    deep = common >= WINDOW
    node = np.cumsum(~deep)  # leaves below one deep node stand together
    leaves = np.zeros(node[-1] + 1 if len(node) else 1)
    inside = starts[order]
    np.add.at(leaves, node[inside], weight[owner[order[inside]]])
    out = np.zeros(len(h), dtype=bool)
    out[order[inside]] = leaves[node[inside]] > 1
    return out[starts]


def _tree_rows(batch: pa.Table):
    """Repeated windows of whole groups: (row of the table, first word of the run, windows) runs."""
    words = batch["words"].combine_chunks()
    anchor = batch["anchor"].to_numpy()
    windows = batch["windows"].to_numpy()
    w = kernel.split(*kernel._bytes_of(words))
    text_key = row_keys(w, w.hashes())
    _, kind, back = np.unique(np.stack([anchor.view(U64), text_key]), axis=1, return_index=True, return_inverse=True)
    back = back.ravel()
    starts = batch["firsts"].combine_chunks().to_pylist()
    weight = np.bincount(back, weights=[len(x) for x in starts], minlength=len(kind))
    flags = repeated_windows(words.take(pa.array(kind)), windows[kind], weight)
    bound = np.concatenate([[0], np.cumsum(windows[kind])])
    change = np.flatnonzero(np.diff(np.concatenate([[0], flags.astype(np.int8), [0]])))
    runs: list[tuple[int, int, int]] = []
    for a, z in zip(change[::2].tolist(), change[1::2].tolist(), strict=True):
        i = int(np.searchsorted(bound, a, side="right")) - 1
        while a < z:  # a run of flags may go on into the next surroundings
            stop = min(z, int(bound[i + 1]))
            runs.append((i, a - int(bound[i]), stop - a))
            a, i = stop, i + 1
    by_kind: dict[int, list[tuple[int, int]]] = {}
    for i, first, n in runs:
        by_kind.setdefault(i, []).append((first, n))
    rows, first, length = [], [], []
    for r, i in enumerate(back.tolist()):
        for f, n in by_kind.get(i, ()):
            for start in starts[r]:
                rows.append(r)
                first.append(start + f)
                length.append(n)
    return np.array(rows, dtype=np.int64), np.array(first, dtype=np.int64), np.array(length, dtype=np.int64)


def repeats_of_partitions(around: DataFrame) -> DataFrame:
    """(rid, row, first, windows): runs of repeated windows, from the trees of the partitions of around, by anchor."""
    names = ["rid", "row", "first", "windows"]

    def found(batches):
        held: list[pa.RecordBatch] = []

        def emit(rows: pa.Table):
            at, first, n = _tree_rows(rows)
            part = rows.take(pa.array(at))
            return pa.Table.from_arrays([part["rid"], part["row"], pa.array(first.astype(np.int32)), pa.array(n.astype(np.int32))], names).combine_chunks().to_batches()

        for batch in batches:
            for piece in (batch.slice(i, TREE_ROWS) for i in range(0, batch.num_rows, TREE_ROWS)):
                held.append(piece)
                rows = pa.Table.from_batches(held)
                if len(rows) < TREE_ROWS and rows.nbytes < 6 * TREE_WORDS:
                    continue
                anchor = rows["anchor"].to_numpy()
                # all but the last group are whole
                cut = int(np.searchsorted(anchor, anchor[-1])) if anchor[0] != anchor[-1] else 0
                if cut:
                    yield from emit(rows.slice(0, cut))
                    held = rows.slice(cut).combine_chunks().to_batches()
        if held:
            rows = pa.Table.from_batches(held)
            if len(rows):
                yield from emit(rows)

    ordered = around.select("anchor", "rid", "row", "firsts", "windows", "words").repartition(F.col("anchor")).sortWithinPartitions("anchor")
    return ordered.mapInArrow(found, "rid bigint, row bigint, first int, windows int")


def repeats_of_split_groups(left: DataFrame, group_rows: int) -> DataFrame:
    """(rid, row, first, windows) of the windows of left, rows of one window each, that start elsewhere too.

    Windows are partitioned by ever longer prefixes; a prefix that stands once is no repeat's.
    """
    found = []
    for length in LONGER:
        named = left.withColumn("anchor", F.xxhash64(F.substring_index("words", " ", length)))
        counts = named.groupBy("anchor").agg(F.sum(F.size("firsts")).alias("n")).where("n > 1")
        named = saved(named.join(counts, "anchor"))
        found.append(repeats_of_partitions(named.where(F.col("n") <= group_rows)))
        left = named.where(F.col("n") > group_rows).drop("n")
        if at_most(left, 0):
            break
    else:
        nodes = left.select("rid", "row", "firsts", "windows", F.sha2("words", 256).alias("node"))
        leaves = nodes.groupBy("node").agg(F.sum(F.size("firsts")).alias("n")).where("n > 1").select("node")
        found.append(nodes.join(leaves, "node").select("rid", "row", F.explode("firsts").alias("first"), "windows"))
    out = found[0]
    for more in found[1:]:
        out = out.unionByName(more)
    return out


def repeated_ranges(rows: DataFrame, group_rows: int = GROUP_ROWS) -> DataFrame:
    """(rid, row, ranges): for each text of rows (rid, text) with repeated windows, (first word, word after the last) of the runs of them."""
    every = saved(anchors(rows))
    counts = every.groupBy("anchor").agg(F.sum("m").alias("n")).where("n > 1").select("anchor", (F.col("n") > group_rows).alias("hot"))
    chosen = every.join(counts, "anchor").select("rid", F.struct("anchor", "hot").alias("pick"))
    # no more picks than the text has anchors: equal rows share them
    chosen = saved(chosen.groupBy("rid").agg(F.collect_set("pick").alias("picks")))
    around = surroundings(rows, chosen)
    if not at_most(counts.where("hot"), 0):
        around = saved(around)
        runs = repeats_of_partitions(around.where("not hot")).unionByName(repeats_of_split_groups(around.where("hot"), group_rows))
    else:
        runs = repeats_of_partitions(around)
    ranges = runs.select("rid", "row", F.struct(F.col("first").alias("a"), (F.col("first") + F.col("windows") + F.lit(WINDOW - 1)).alias("z")).alias("range"))
    return ranges.groupBy("rid", "row").agg(F.collect_set("range").alias("ranges"))


def _covered(n: int, ranges: list[dict]) -> np.ndarray:
    cover = np.zeros(n + 1, dtype=np.int32)
    for r in ranges:
        cover[r["a"]] += 1
        cover[r["z"]] -= 1
    return np.cumsum(cover[:-1]) > 0


def with_ranges(docs: DataFrame) -> DataFrame:
    """doc_id, text, found (ranges of texts of the row's key) for every row of docs."""
    rows = keyed(docs)
    ranges = saved(repeated_ranges(rows))
    by_row = ranges.groupBy("rid").agg(F.collect_list(F.struct("row", "ranges")).alias("found"))
    bitmap = marks(ranges)
    moved = where_marked(rows, bitmap).join(by_row, "rid", "left").select("doc_id", "text", "found")
    return moved.unionByName(where_marked(rows, bitmap, marked=False).select("doc_id", "text", F.lit(None).cast(by_row.schema["found"].dataType).alias("found")))


def kept_texts(batch: pa.RecordBatch, text: int, found: int):
    """For each row: (words, words removed, kept words joined by one space)."""
    lists = batch.column(found)
    named = batch.schema.names[text]
    for a, z, w in kernel.steps(batch, named):
        key = row_keys(w, w.hashes()).view(np.int64)
        raw = w.data.tobytes()
        for i in range(w.rows):
            lo, hi = int(w.row_words[i]), int(w.row_words[i + 1])
            gone = np.zeros(hi - lo, dtype=bool)
            for entry in lists[a + i].as_py() or ():
                if entry["row"] == key[i]:
                    gone = _covered(hi - lo, entry["ranges"])
            s, e = w.starts[lo:hi][~gone].tolist(), w.ends[lo:hi][~gone].tolist()
            yield hi - lo, int(gone.sum()), b" ".join([raw[x:y] for x, y in zip(s, e, strict=True)])


def remove_repeats(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, n_removed, kept (text) for every row of docs."""

    def cut(batches):
        for batch in batches:
            rows = list(kept_texts(batch, 1, 2))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.int64()), pa.array([r[2] for r in rows], pa.binary()).cast(pa.string())], ["doc_id", "n_words", "n_removed", "kept"])

    joined = with_ranges(docs)
    return joined.mapInArrow(cut, f"doc_id {joined.schema['doc_id'].dataType.simpleString()}, n_words bigint, n_removed bigint, kept string")


def op2_substring_dedup(spark, sf_dir: str) -> DataFrame:
    out = remove_repeats(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "n_removed", F.sha2(F.col("kept").cast("binary"), 256).alias("kept_sha256"))


QUERIES = {"op2_substring_dedup": op2_substring_dedup}
ORACLES = {
    "op2_substring_dedup": r"""
    with words as (select doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') as w from documents),
    windows as (
      select doc_id, p, md5(array_to_string(w[p:p + 34], ' ')) as h
      from (select doc_id, w, unnest(range(1, len(w) - 33)) as p from words where len(w) >= 35)),
    repeated as (select h from windows group by h having count(*) > 1),
    gone as (select distinct doc_id, unnest(range(p, p + 35)) as p from windows join repeated using (h)),
    lost as (select doc_id, list(p) as ps, count(*) as n from gone group by doc_id)
    select d.doc_id, cast(len(w) as bigint) as n_words, cast(coalesce(n, 0) as bigint) as n_removed,
      sha256(coalesce(array_to_string(case when ps is null then w else
        list_transform(list_filter(list_zip(w, range(1, len(w) + 1)), lambda x: not list_contains(ps, x[2])), lambda x: x[1]) end, ' '), '')) as kept_sha256
    from words d left join lost using (doc_id)"""
}
