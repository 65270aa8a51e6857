"""Every operator against a plain version, with null, empty, long, tied and repeated rows, and empty tables."""

from __future__ import annotations

import hashlib
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from strata_descent.llm import fingerprints, importance, mixing, ngram_join, personal_data, pieces, quality_rules, substring_dedup, toxicity, url_filters
from strata_descent.llm import words as kernel

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id bigint, text string, lang string, source string, n_chars bigint, words string, score double"


def text_of(seed: int, n: int) -> str:
    rng = np.random.default_rng(seed)
    return " ".join("".join(chr(97 + c) for c in rng.integers(0, 26, rng.integers(2, 7))) for _ in range(n))


def make(spark, rows):
    """rows of (doc_id, text, source), with columns whose names the operators use themselves."""
    return spark.createDataFrame([(i, t, "en", s, None if t is None else len(t), "x", 1.0) for i, t, s in rows], SCHEMA)


@pytest.fixture(scope="module")
def corpus():
    base = text_of(1, 120)
    words = base.split()
    near = " ".join([*words[:60], "changed", *words[61:]])
    passage = text_of(2, 50)
    rows = [
        (1, base, "a"), (2, base.upper(), "a"), (3, near, "b"), (4, None, "b"), (5, "", None), (6, " \t\n ", None), (7, "one two three", "c"), (8, "one  two\nthree", "c"),
        (9, text_of(3, 80) + " " + passage + " " + text_of(4, 30), "a"), (10, passage + "\n" + text_of(5, 60), "a"), (11, text_of(6, 5000), "a"), (12, "the " * 90, "b"),
        (13, base, "a"), (13, base, "a"), (14, "ÄÖ 日本語 " * 30 + "mail x.y@example.com now", "d"),
        (None, near + " more", "a"), (None, text_of(7, 70), "b"), (None, text_of(7, 70), "b"), (None, text_of(6, 5000)[:9000], "c"), (None, None, None), (15, "x" * 30_000 + " " + "7" * 9_000, "d"),
    ]
    return rows


@pytest.fixture(scope="module")
def docs(spark, corpus):
    return make(spark, corpus).repartition(3).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return make(spark, [(1, "x", "a")]).where("doc_id < 0")


def lower(t):
    return "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t)


def sets_of(text):
    w = WORD.findall(lower(text or ""))
    return {tuple(w)} if 0 < len(w) < 5 else {tuple(w[i : i + 5]) for i in range(len(w) - 4)}


def join_by_hand(rows):
    sets = [sets_of(t) for _, t, _ in rows]
    link = [[i != j and bool(a & b) and 100 * len(a & b) >= 75 * len(a | b) for j, b in enumerate(sets)] for i, a in enumerate(sets)]
    out = []
    for i, (doc, _, _) in enumerate(rows):
        seen, todo = {i}, [i]
        while todo:
            at = todo.pop()
            new = [j for j in range(len(rows)) if link[at][j] and j not in seen]
            seen |= set(new)
            todo += new
        out.append((doc, len(sets[i]), min((rows[j][0] for j in seen if rows[j][0] is not None), default=None), sum(link[i])))
    return sorted(out, key=repr)


def test_word_kernel(corpus):
    import pyarrow as pa

    texts = [t for _, t, _ in corpus]
    batch = pa.RecordBatch.from_arrays([pa.array(texts)], ["text"])
    found = []
    for _, _, w in kernel.steps(batch):
        raw = w.data.tobytes()
        found += [[raw[a:z].decode() for a, z in zip(w.starts[lo:hi], w.ends[lo:hi], strict=True)] for lo, hi in zip(w.row_words, w.row_words[1:], strict=False)]
    assert found == [WORD.findall(t or "") for t in texts]


def test_ngram_join(docs, corpus):
    assert sorted((tuple(r) for r in ngram_join.join_documents(docs).collect()), key=repr) == join_by_hand(corpus)


def test_ngram_join_keeps_one_row_of_each_group(docs, corpus):
    wanted = []
    sets = [sets_of(t) for _, t, _ in corpus]
    for doc, text, source in corpus:
        near = [r for r, s in zip(corpus, sets, strict=True) if s and len(s & sets_of(text)) * 100 >= 75 * len(s | sets_of(text))]
        if not near or (doc, text) == min(((r[0], r[1]) for r in near), key=lambda r: (r[0] is None, r[0] or 0)):
            wanted.append((doc, text, source))
    wanted = [r for i, r in enumerate(wanted) if not sets_of(r[1]) or r not in wanted[:i]]
    got = ngram_join.keep_one(docs)
    assert got.columns == docs.columns
    assert sorted(((r.doc_id, r.text, r.source) for r in got.collect()), key=repr) == sorted(wanted, key=repr)


def test_ngram_join_deals_hot_shingles(spark, monkeypatch):
    """Every shared shingle taken for a hot one: the parts are tied together again."""
    rng = np.random.default_rng(12)
    common = text_of(11, 40).split()
    rows = [(i, " ".join([*common, *text_of(50 + i % 30, 8 + i % 9).split()[: int(rng.integers(6, 12))]]), "a") for i in range(60)]
    monkeypatch.setattr(ngram_join, "SAMPLE", 1.0)
    monkeypatch.setattr(ngram_join, "HOT_LEAST", 1)
    assert sorted((tuple(r) for r in ngram_join.join_documents(make(spark, rows)).collect()), key=repr) == join_by_hand(rows)


def test_ngram_join_of_many_near_copies(spark, monkeypatch):
    """A group that is split into blocks, with sizes at the bound, common passages and small blocks."""
    monkeypatch.setattr(ngram_join, "BLOCK_ROWS", 8)
    rng = np.random.default_rng(0)
    base, common = text_of(10, 60).split(), text_of(11, 40).split()
    rows = []
    for i in range(50):
        w = list(base)
        for at in rng.integers(0, 60, rng.integers(0, 3)):
            w[at] = f"edit{rng.integers(0, 9)}"
        rows.append((i, " ".join(w[: rng.integers(50, 61)]), "a"))
    rows += [(100 + i, " ".join([*common, *text_of(50 + i, rng.integers(4, 60)).split()]), "a") for i in range(40)]
    assert sorted((tuple(r) for r in ngram_join.join_documents(make(spark, rows)).collect()), key=repr) == join_by_hand(rows)


def test_overlap_product():
    rng = np.random.default_rng(4)
    one = np.unique(np.stack([rng.integers(0, 30, 900), rng.integers(0, 60, 900)]), axis=1)
    two = np.unique(np.stack([rng.integers(0, 9, 300), rng.integers(0, 60, 300)]), axis=1)
    a, b = np.zeros((30, 60)), np.zeros((9, 60))
    a[one[0], one[1]] = 1
    b[two[0], two[1]] = 1
    whole = ngram_join.overlaps((one[0], one[1]), None, (30, 0))
    off = ~np.eye(30, dtype=bool)
    assert (whole[off] == (a @ a.T)[off]).all()
    assert (ngram_join.overlaps((one[0], one[1]), (two[0], two[1]), (30, 9)) == a @ b.T).all()


def dedup_by_hand(rows):
    windows = Counter()
    for _, t, _ in rows:
        w = WORD.findall(t or "")
        windows.update(tuple(w[i : i + 35]) for i in range(len(w) - 34))
    out = []
    for doc, t, _ in rows:
        w = WORD.findall(t or "")
        gone = {j for i in range(len(w) - 34) if windows[tuple(w[i : i + 35])] > 1 for j in range(i, i + 35)}
        out.append((doc, len(w), len(gone), " ".join(x for i, x in enumerate(w) if i not in gone)))
    return sorted(out, key=repr)


def test_substring_dedup(docs, corpus, monkeypatch):
    wanted = dedup_by_hand(corpus)
    assert sorted((tuple(r) for r in substring_dedup.remove_repeats(docs).collect()), key=repr) == wanted
    # every group split by longer prefixes, some of them down to whole windows
    ranges = substring_dedup.repeated_ranges
    for most in (1, 3):
        monkeypatch.setattr(substring_dedup, "repeated_ranges", lambda d, most=most: ranges(d, group_rows=most))
        assert sorted((tuple(r) for r in substring_dedup.remove_repeats(docs).collect()), key=repr) == wanted


def test_suffix_tree_is_a_sorted_array_with_its_prefixes():
    rng = np.random.default_rng(2)
    names = rng.integers(0, 3, 120)
    last = np.repeat([50, 120], [50, 70])
    order, common = substring_dedup.suffix_tree(names, last)
    suffix = [tuple(names[i : min(last[i], i + 64)]) for i in order]
    assert suffix == sorted(suffix)
    for a, b, n in zip(suffix, suffix[1:], common[1:], strict=False):
        assert n == next((k for k, (x, y) in enumerate(zip(a, b, strict=False)) if x != y), min(len(a), len(b)))


def test_quality_counts(docs, corpus):
    wanted = []
    for doc, t, _ in corpus:
        w = WORD.findall(t or "")
        grams = [tuple(w[i : i + 3]) for i in range(len(w) - 2)]
        n = Counter(grams)
        cover = {j for i, g in enumerate(grams) if n[g] > 1 for j in range(i, i + 3)}
        lines = [x for x in (t or "").split("\n") if WORD.search(x)]
        wanted.append((doc, len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t or ""), len(lines) - len(set(lines)), len(cover), len(w) < 50 or 100 * len(cover) > 50 * len(w)))
    got = quality_rules.base_counts(docs).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed")
    assert sorted((tuple(r) for r in got.collect()), key=repr) == sorted(wanted, key=repr)


def test_quality_verdicts(spark):
    rng, known = np.random.default_rng(5), text_of(1, 300).split()
    some = lambda n: " ".join(rng.choice(known, n, replace=False))
    good = [(i, some(80), "a") for i in range(60)]
    junk = [(100 + i, " ".join(w + "$%&#"[k % 4] * 3 for k, w in enumerate(some(80).split())), "a") for i in range(10)]
    labels = spark.createDataFrame([(i, 1) for i in range(40)], "doc_id bigint, quality int")
    judged = quality_rules.judge_quality(make(spark, good + junk), labels).select("doc_id", "kept", "base_failed").collect()
    assert all(r.kept == (r.doc_id < 100) for r in judged if not r.base_failed)
    none = quality_rules.judge_quality(make(spark, good), labels.where("doc_id < 0"))
    assert none.where("kept = base_failed").count() == 0


def test_quality_ratio_by_hand(spark, docs, corpus):
    """Buckets, ratios, threshold, scores and verdicts against plain counts; hashes by Spark's own function."""
    import math

    labels = spark.createDataFrame([(1, 1), (3, 1), (9, 1), (11, 0), (13, 1), (13, 0), (None, 1), (99, 1), (12, None)], "doc_id bigint, quality int")
    trusted = {1, 3, 9, 13}
    words = [WORD.findall(t or "") for _, t, _ in corpus]
    listed = sorted({w for ws in words for w in ws})
    rows = spark.createDataFrame([(i, w, w[:3], w[-3:]) for i, w in enumerate(listed)], "i int, w string, a string, z string")
    of = {listed[r.i]: r for r in rows.select("i", F.xxhash64("a").alias("a"), F.expr("xxhash64(z, 1)").alias("z"), F.expr("xxhash64(w, 2)").alias("w")).collect()}
    pairs = sorted({(a, b) for ws in words for a, b in zip(ws, ws[1:], strict=False)})
    joint = spark.createDataFrame([(i, of[a].w, of[b].w) for i, (a, b) in enumerate(pairs)], "i int, a long, b long").select("i", F.xxhash64("a", "b").alias("h")).collect()
    of_pair = {pairs[r.i]: r.h for r in joint}
    grams = [[of[w][k] % quality_rules.BUCKETS for w in ws for k in ("a", "z", "w")] + [of_pair[p] % quality_rules.BUCKETS for p in zip(ws, ws[1:], strict=False)] for ws in words]
    raw, good = Counter(), Counter()
    for (d, _, _), g in zip(corpus, grams, strict=True):
        raw.update(g)
        good.update(g if d in trusted else [])
    scale = sum(good.values()) / sum(raw.values())
    ratio = [math.log((good[b] + quality_rules.PRIOR) / (raw[b] * scale + quality_rules.PRIOR)) for b in range(quality_rules.BUCKETS)]
    score = [sum(ratio[b] for b in g) / len(g) if g else 0.0 for g in grams]
    known = [s for (d, _, _), s, ws in zip(corpus, score, words, strict=True) if d in trusted and len(ws) >= 50]
    for spread in (10.0, 0.5):
        ratios, least = quality_rules.fitted(docs, labels, spread)
        assert ratios == pytest.approx(ratio, abs=1e-8) and least == pytest.approx(np.mean(known) - spread * np.std(known), abs=1e-5)
        got = sorted(((r.doc_id, r.n_words, round(r.score, 6), r.kept) for r in quality_rules.judge_quality(docs, labels, spread).collect()), key=repr)
        failed = {(r.doc_id, r.n_words): r.base_failed for r in quality_rules.base_counts(docs).collect()}
        assert got == sorted(((d, len(ws), round(s, 6), not failed[d, len(ws)] and s >= least) for (d, _, _), s, ws in zip(corpus, score, words, strict=True)), key=repr)
    kept = quality_rules.keep_quality(docs.withColumn("words", F.lit(1)), labels)
    assert kept.columns == docs.columns
    verdicts = quality_rules.judge_quality(docs, labels).where("kept").collect()
    assert sorted((r.doc_id or -1 for r in kept.collect())) == sorted(r.doc_id or -1 for r in verdicts) and -1 in {r.doc_id or -1 for r in verdicts}


def test_quality_scores_words_and_pairs(spark):
    """Words garbled between clean edges, and good words in another order, score lower than the text they come from."""
    words = [f"abc{a}{b}xyz" for a in "defgh" for b in "klmno"]
    good = " ".join(words * 4)
    garbled = " ".join(w[:3] + "qj" + w[5:] for w in words * 4)
    order = np.random.default_rng(5).permutation(len(words))
    salad = " ".join([words[i] for i in order] * 4)
    docs = make(spark, [(i, good, "a") for i in range(5)] + [(10, garbled, "a"), (11, salad, "a")] + [(20 + i, text_of(700 + i, 100), "a") for i in range(5)])
    labels = spark.createDataFrame([(i, 1, 0) for i in range(5)], "doc_id bigint, quality int, toxic int")
    score = {r.doc_id: r.score for r in quality_rules.judge_quality(docs, labels).collect()}
    assert score[10] < score[0] - 0.01 and score[11] < score[0] - 0.01


def test_quality_rejects_texts_garbled_in_part(spark):
    """Good texts with every fifth word garbled go; good texts stay, whether the counts of the trusted have them or not."""
    rng = np.random.default_rng(11)
    known = ["".join(rng.choice(list("abcdefghij"), 5)) for _ in range(150)]
    some = lambda: list(rng.choice(known, 120))
    good = [(i, " ".join(some()), "a") for i in range(80)]
    garbled = [(100 + i, " ".join(w + "$%&#"[k % 4] * 3 if k % 5 == 0 else w for k, w in enumerate(some())), "a") for i in range(10)]
    labels = spark.createDataFrame([(i, 1) for i in range(40)], "doc_id bigint, quality int")
    judged = quality_rules.judge_quality(make(spark, good + garbled), labels).collect()
    assert not any(r.base_failed for r in judged) and not any(r.kept for r in judged if r.doc_id >= 100)
    assert sum(r.kept for r in judged if r.doc_id < 100) >= 78
    kept = quality_rules.keep_quality(make(spark, good + garbled), labels).collect()
    assert sorted(r.doc_id for r in kept) == sorted(r.doc_id for r in judged if r.kept)


def sketches(spark, texts):
    """Anchors (hash, place) of each text by a plain scan, hashes by Spark's own function."""
    k, s, rows = fingerprints.K, fingerprints.S, []
    words = [WORD.findall(t or "") for t in texts]
    for i, w in enumerate(words):
        rows += [(i, j, w[j], w[j + 1]) for j in range(len(w) - 1)]
    got = spark.createDataFrame(rows or [(-1, 0, "", "")], "i int, j int, a string, b string").select("i", "j", F.xxhash64("a", "b").alias("h")).collect()
    inner = {(r.i, r.j): r.h for r in got}
    runs = []
    for i, w in enumerate(words):
        for j in range(len(w) - k + 1):
            own = [inner[i, j + x] for x in range(k - s + 1)]
            if min(own) in (own[0], own[-1]):
                runs.append((i, j, own))
    hashed = spark.createDataFrame([(i, j, *own[::s]) for i, j, own in runs] or [(-1, 0, 0, 0, 0, 0)], "i int, j int, a long, b long, c long, d long").select("i", "j", F.xxhash64("a", "b", "c", "d").alias("h")).collect()
    whole = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(words)], "i int, t string").select("i", F.xxhash64("t").alias("h")).collect()
    out = [{} for _ in texts]
    for r in hashed:
        if r.i >= 0:
            out[r.i][r.h] = min(r.j, out[r.i].get(r.h, r.j))
    for r in whole:
        if texts[r.i] and len(words[r.i]) < k:
            out[r.i] = {r.h: 0}
    return [sorted(o.items())[: fingerprints.ANCHORS] for o in out]


def likeness_by_hand(a, b):
    if not a or not b:
        return float(not a and not b)
    n = fingerprints.ANCHORS
    most = min([x[-1][0] for x in (a, b) if len(x) == n], default=2**63 - 1)
    one, two = ({h: i for h, i in x if h <= most} for x in (a, b))
    shifts = sorted(one[h] - two[h] for h in one if h in two)
    return sum(abs(x - shifts[len(shifts) // 2]) <= fingerprints.SLACK for x in shifts) / len(one.keys() | two.keys()) if shifts else 0.0


def test_fingerprints(spark, docs, corpus):
    """Edited texts, sketches and likeness of every row are those of a plain version, whatever the ranges."""
    texts = {}
    for d, t, _ in corpus:
        texts[d] = min(texts.get(d, t or ""), t or "")
    ids = sorted(d for d in texts if d is not None)
    after = dict(zip(ids, ids[1:] + ids[:1], strict=True))
    own = [t or "" for _, t, _ in corpus]
    follow = [texts[after[d]] if d is not None else None for d, _, _ in corpus]
    edited = [t[: len(t) - len(t) // 4] + (f or "")[: len(t) // 4] for t, f in zip(own, follow, strict=True)]
    of_own, of_edited, of_follow = (sketches(spark, x) for x in (own, edited, [f or "" for f in follow]))
    show = lambda a: ",".join(f"{h & 2**64 - 1:x}:{i}" for h, i in a)
    wanted = [
        (d, len(t), hashlib.sha256(e.encode()).hexdigest(), show(a), show(b), likeness_by_hand(a, b), likeness_by_hand(a, c) if f is not None else 0.0)
        for (d, _, _), t, e, f, a, b, c in zip(corpus, own, edited, follow, of_own, of_edited, of_follow, strict=True)
    ]
    assert sorted((tuple(r) for r in fingerprints.against_edits(docs).collect()), key=repr) == sorted(wanted, key=repr)
    rows = {r.doc_id: r for r in fingerprints.against_edits(docs.where("doc_id = 11 or doc_id = 14")).collect()}
    assert rows[11].near_edited > 0.3 > rows[11].near_next
    one = fingerprints.against_edits(docs.where("doc_id = 11")).first()  # its own next document
    assert one.near_next == 1.0


def test_repeats_take_no_anchors(spark):
    """A repeated passage neither crowds out distinct anchors nor counts twice, and size changes no text's kind."""
    plain, passage = text_of(78, 400), text_of(79, 24)
    mixed = plain + " " + " ".join([passage] * 300)
    short = text_of(80, 60)
    assert len(short) < 512
    rows = spark.createDataFrame([(1, plain), (2, plain + " " + passage + " " + passage), (3, mixed), (4, short), (5, short + " " + text_of(81, 120))], "i int, text string")
    got = {r.i: r.a for r in rows.select("i", F.expr(fingerprints.anchors("text")).alias("a")).collect()}
    assert len(got[3]) == len({x.h for x in got[3]}) == fingerprints.ANCHORS and got[3] == got[2]
    assert len({x.h for x in got[4]} & {x.h for x in got[5]}) > 0


def mix_by_hand(rows, source_rows, start, block):
    """Words taken of each source's stream: {(number, lap, word)}, by walking the slots one after the other."""
    live = [r for r in source_rows if r.slots]
    total = sum(r.slots for r in live)
    edges = [int(r.slots_before * 2.0**53 / total) for r in live]
    ranks, begins, taken = Counter(), {}, set()

    def serve(r, at):
        rank = ranks[r.number]
        ranks[r.number] += 1
        if rank >= r.slots:
            return
        lap, place = divmod(rank, r.lap)
        if place == 0:
            begins[r.number, lap] = min(int(at * r.whole), r.whole - 1)
        which = (place * mixing._stride(r.whole) + begins[r.number, lap]) % r.whole if place < r.whole else r.whole
        before = lap * r.size + place * block
        for word in range(which * block, min((which + 1) * block, r.size, which * block + r.words - before)):
            assert (r.number, lap, word) not in taken
            taken.add((r.number, lap, word))

    for slot in range(total):
        point = ((slot + start) * mixing._GOLDEN % 2**64) >> 11
        which = max(i for i, e in enumerate(edges) if e <= point)
        serve(live[which], (point - edges[which]) / (live[which].slots * 2.0**53 / total))
    for r in live:
        while ranks[r.number] < r.slots:
            serve(r, 0.0)
    return taken


def test_mixing(spark, docs, corpus):
    rows = mixing.taken_words(docs).collect()
    again = mixing.taken_words(docs.repartition(5)).collect()
    key = lambda r: repr((r.doc_id, r["size"], r.taken, r.first_slot))
    assert sorted(map(key, rows)) == sorted(map(key, again)) and len(rows) == len(corpus)
    sizes, size_of = Counter(), Counter()
    for d, t, s in corpus:
        sizes[s] += len(WORD.findall(t or ""))
        size_of[d, len(WORD.findall(t or ""))] += 1
    assert size_of == Counter((r.doc_id, r["size"]) for r in rows)
    taken = Counter()
    for r in rows:
        assert r.taken <= 2 * r["size"] and (r.taken > 0) == (r.n_slots > 0) == (r.first_slot is not None)
        taken[r.source] += r.taken
    for r in rows:
        assert r.source_size == sizes[r.source] and abs(taken[r.source] - r.target) <= 1
    assert sum({r.source: r.target for r in rows}.values()) == pytest.approx(1.5 * sum(sizes.values()))


def test_mixing_takes_what_the_slots_say(spark):
    """Against a walk over the slots; another schedule takes other documents, and targets are met all the same."""
    rows = [(i, text_of(i, 3 + i % 40), "abc"[i % 3] if i % 11 else None) for i in range(200)] + [(5, text_of(5, 8), "c")] * 3
    docs, got = make(spark, rows), {}
    for start, sequence in ((0, "golden"), (1000, "golden"), (0, "van_der_corput")):
        at, pieces, sources = mixing.mix_documents(docs, block=16, start=start, sequence=sequence)
        first = {(r.number, r.place): r["first"] for r in at.collect()}
        words = Counter((r.number, r.lap, first[r.number, r.place] + r.from_word + k) for r in pieces.collect() for k in range(r.n))
        listed = sorted(sources.collect(), key=lambda r: r.number)
        assert max(words.values()) == 1
        for r in listed:
            assert sum(n for (s, _, _), n in words.items() if s == r.number) == r.words == round(r.target)
        got[start, sequence] = set(words)
        if sequence == "golden":
            assert set(words) == mix_by_hand(rows, listed, start, 16)
    assert len(set(map(frozenset, got.values()))) == 3


def test_targets_are_capped(spark, monkeypatch):
    sizes, weights = [100, 10, 50, 0, 7, 400, 3], [3.0, 1.0, 2.0, 3.0, 1.0, 2.0, 3.0]
    wanted, open_, left = [0.0] * 7, set(range(7)), 1.5 * sum(sizes)
    while open_:
        total = sum(weights[i] for i in open_)
        over = {i for i in open_ if left * weights[i] / total > 2 * sizes[i]}
        for i in over or open_:
            wanted[i] = 2.0 * sizes[i] if over else left * weights[i] / total
        if not over:
            break
        left, open_ = left - sum(wanted[i] for i in over), open_ - over
    rows = spark.createDataFrame(list(enumerate(sizes)), "number bigint, size bigint")
    for per in (100_000, 2):  # in one range, and in several
        monkeypatch.setattr(mixing, "ROWS_PER_RANGE", per)
        assert [r.target for r in mixing.with_targets(rows).orderBy("number").collect()] == pytest.approx(wanted)


def listed_sources(spark, blocks):
    at = [0, *np.cumsum(blocks).tolist()]
    return spark.createDataFrame([(str(i), i, n * 10, n * 10, n, n, n, at[i], mixing._stride(max(1, n))) for i, n in enumerate(blocks)], "source string, number bigint, size bigint, words bigint, whole bigint, lap bigint, slots bigint, slots_before bigint, stride bigint")


def test_schedule_serves_sources_evenly(spark):
    for sequence in ("golden", "van_der_corput"):
        rows = mixing.schedule(listed_sources(spark, [500, 1500, 0]), 10, sequence).orderBy("slot").collect()
        assert sorted((r.number, r.block) for r in rows) == [(0, i) for i in range(500)] + [(1, i) for i in range(1500)]
        at = np.cumsum([r.number == 0 for r in rows])
        assert np.abs(at - np.arange(1, len(rows) + 1) / 4).max() < 8


def test_schedule_serves_small_sources_in_full(spark):
    """Every block of every source has one slot, also where the points miss a small source or come in many ranges."""
    for blocks in ([2, 185184, 3, 1, 2, 1, 192620, 73101, 5], [112127, 5, 5, 2, 5, 1, 24960], [1, 1, 1]):
        plan = mixing.schedule(listed_sources(spark, blocks), 10)
        per = {r.number: (r.rows, r.blocks, r.least, r.most, r.words) for r in plan.groupBy("number").agg(F.count("*").alias("rows"), F.count_distinct("block").alias("blocks"), F.min("block").alias("least"), F.max("block").alias("most"), F.sum("take").alias("words")).collect()}
        assert per == {i: (n, n, 0, n - 1, 10 * n) for i, n in enumerate(blocks)}
        assert plan.select("slot").distinct().count() == sum(blocks)


def test_mixed_texts(spark, docs, corpus):
    taken = Counter((r.doc_id, r.taken) for r in mixing.taken_words(docs).where("taken > 0").collect())
    out = mixing.mixed_texts(docs)
    assert out.columns == docs.columns
    rows = out.collect()
    assert Counter((r.doc_id, len(WORD.findall(r.text))) for r in rows) == taken
    texts = {d: Counter(WORD.findall(t or "")) for d, t, _ in corpus if d is not None}
    for r in rows:
        assert r.n_chars == len(r.text)
        if r.doc_id is not None:
            assert all(n <= 2 * texts[r.doc_id][w] for w, n in Counter(WORD.findall(r.text)).items())


def test_personal_data(docs, corpus):
    text = "write a.b@mail.example.com or 10.0.0.255 and 999.1.1.1, card 4111 1111 1111 1111 5500-0000-0000-0004, tel +1 (555) 010-9999 x@y z@@q.w 1.2.3.4.5"
    spans = personal_data.base_spans(text)
    email = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
    ip = re.compile(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)")
    card = re.compile(r"[0-9]([\x20-]?[0-9])+")
    phone = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
    digits = lambda s: re.sub("[^0-9]", "", s)
    for t in [text, *(t or "" for _, t, _ in corpus), "1" * 30 + ".2.3.4", "a@b.c@d.e-f.g", "++1 2 3 456789 0", "0000.1.2.3"]:
        wanted = [(0, m.start(), m.end()) for m in email.finditer(t)]
        wanted += [(1, m.start(), m.end()) for m in ip.finditer(t) if all(int(p) <= 255 for p in m[0].split("."))]
        wanted += [(2, m.start(), m.end()) for m in card.finditer(t) if 13 <= len(digits(m[0])) <= 19 and personal_data.luhn(digits(m[0]))]
        wanted += [(3, m.start(), m.end()) for m in phone.finditer(t) if 9 <= len(digits(m[0])) <= 15]
        assert personal_data.base_spans(t) == wanted
    every = personal_data.all_spans(text, personal_data.prior_weights())[1]
    assert set(spans) <= set(every)
    joined = "ids 4111111111111111 5500000000000004 end"  # one base match of 32 digits, which fails
    assert not personal_data.base_spans(joined)
    assert [joined[a:z] for _, a, z in personal_data.all_spans(joined, personal_data.prior_weights())[1]] == ["4111111111111111", "5500000000000004"]
    rows = personal_data.find_personal_data(docs).collect()
    assert len(rows) == len(corpus) and sum(r.n_email for r in rows) == 1
    clean = personal_data.redact(docs).where("doc_id = 14").first()
    assert clean.text.endswith("mail <email> now") and clean.n_chars == len(clean.text)


def test_best_spans_is_the_best_segmentation():
    texts = ["call +1 (555) 010-9999 now", "card 4111111111111111 ok", "at 10.1.2.3 here", "a.b@c.example.org"]
    weights = personal_data.fit_weights([e for t in texts for e in personal_data.examples(t)])
    island = "4111111111111111 10.1.2.3"
    bounds, cut, _, scores, n = personal_data._scored(island, "", "", weights)

    def best(i):
        if i >= n:
            return 0.0
        return max([best(i + 1), *(scores[k].max() + best(cut[k][1]) for k in range(len(cut)) if cut[k][0] == i)])

    found = personal_data.best_spans(island, "", "", weights)
    at = {(bounds[i], bounds[j]): k for k, (i, j) in enumerate(cut)}
    assert sum(scores[at[a, z], kind] for kind, a, z in found) == pytest.approx(best(0))


def test_fit_follows_the_likelihood():
    """The fit's first step is the gradient of the base spans' log likelihood, sums taken over every segmentation."""
    seen = list(personal_data.examples("call tel +1 (555) 010-9999 at 10.1.2.3 now"))
    prior = personal_data.prior_weights()

    def likelihood(weights):
        total = 0.0
        for island, before, after, gold in seen:
            bounds, cut, _, scores, n = personal_data._scored(island, before, after, weights)

            def every(i, cut=cut, scores=scores, n=n):
                if i >= n:
                    return 0.0
                return np.logaddexp.reduce([every(i + 1), *(s + every(cut[k][1]) for k in range(len(cut)) if cut[k][0] == i for s in scores[k])])

            at = {(bounds[i], bounds[j]): k for k, (i, j) in enumerate(cut)}
            total += sum(scores[at[i, j], kind] for kind, i, j in gold) - every(0)
        return total

    step = (personal_data.fit_weights(seen, rounds=1, rate=1e-3) - prior) * 1000 * len(seen)
    for kind in range(4):
        for f in (0, 1, 4, 7, 10, 16):
            moved = prior.copy()
            moved[kind, f] += 1e-5
            assert step[kind, f] == pytest.approx((likelihood(moved) - likelihood(prior)) / 1e-5, abs=2e-3)
    assert np.abs(step[:, personal_data.FEATURES.index("told_phone")]).max() > 0


def test_personal_data_end_to_end(spark):
    """Fitted on all islands of the documents, the field alone finds nearly all base spans of others, and adds what the patterns miss."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    weights = personal_data.train(docs.where("doc_id % 2 = 0"))
    assert (weights == personal_data.train(docs.where("doc_id % 2 = 0").repartition(3))).all()
    base, found, hit = 0, 0, 0
    for r in docs.where("doc_id % 2 = 1").collect():
        own, by_field = set(personal_data.base_spans(r.text or "")), set(personal_data.field_spans(r.text or "", weights))
        base, found, hit = base + len(own), found + len(by_field), hit + len(own & by_field)
    assert base > 20 and hit / base > 0.9 and hit / found > 0.7
    missed = {"phone (555) 010-9999 or": "phone", "card no 4111.1111.1111.1111": None, "ids 4111111111111111 5500000000000004 end": "card"}
    for text, kind in missed.items():
        added = [personal_data.KINDS[k] for k, _, _ in personal_data.all_spans(text, weights)[1]]
        assert not personal_data.base_spans(text) and (kind is None or kind in added)


def test_personal_data_is_linear():
    import time

    for text in ("7" * 400_000, "a@b.c +1 234 567 8901 " * 8_000, "x" * 400_000 + "@", "1." * 200_000, "@" * 200_000):
        began = time.time()
        base, every = personal_data.all_spans(text, personal_data.prior_weights())
        assert set(base) <= set(every) and time.time() - began < 20


def test_pieces_are_lossless_and_repeatable(docs, corpus):
    rows = pieces.sample_pieces(docs, "source").collect()
    texts = {d: t or "" for d, t, _ in corpus}
    assert all(r.decoded_sha256 == hashlib.sha256(texts[r.doc_id].encode()).hexdigest() for r in rows if r.doc_id is not None)
    assert Counter(r.decoded_sha256 for r in rows) == Counter(hashlib.sha256((t or "").encode()).hexdigest() for _, t, _ in corpus)
    again = {(r.doc_id, r.decoded_sha256): r.pieces for r in pieces.sample_pieces(docs.repartition(5), "source").collect()}
    assert all(again[r.doc_id, r.decoded_sha256] == r.pieces for r in rows)


def test_piece_shares_follow_the_lattice():
    """Sampled segmentations of one word come as often as their weights say."""
    vocabulary = pieces.Vocabulary.read(temperature=0.001)
    word, n = b"international", 4000
    data = np.frombuffer(word * n, dtype=np.uint8)
    ids, rows = pieces.encode_rows(vocabulary, data, np.arange(n + 1) * len(word), np.arange(n).astype(np.uint64))
    seen = Counter(tuple(ids[a:z].tolist()) for a, z in zip(rows[:-1], rows[1:], strict=True))
    by_bytes = {p: i for i, p in enumerate(vocabulary.pieces) if p}

    def paths(at):
        if at == len(word):
            return [((), 0.0)]
        out = []
        for z in range(at + 1, len(word) + 1):
            if word[at:z] in by_bytes:
                i = by_bytes[word[at:z]]
                out += [((i, *rest), s + 0.001 * vocabulary.scores[i]) for rest, s in paths(z)]
        return out

    every = paths(0)
    total = np.logaddexp.reduce([s for _, s in every])
    for path, s in sorted(every, key=lambda p: -p[1])[:3]:
        p = np.exp(s - total)
        assert abs(seen[path] / n - p) < 5 * np.sqrt(p * (1 - p) / n) + 0.01


def test_pieces_of_every_length_are_sampled():
    """Shares of all segmentations of a chunk, pieces of more than DENSE bytes and the longest included, are those of the lattice."""
    whole = pieces.Vocabulary.read()
    long = [p for p in whole.pieces if p is not None and len(p) > 12]
    assert len(long) > 300 and whole.longest == max(map(len, long))
    for seed, chunk in enumerate((b" internationalisation", max(long, key=len))):
        parts = sorted({chunk[a:z] for a in range(len(chunk)) for z in (a + 1, a + 5, a + 13, a + 14, len(chunk)) if z <= len(chunk)})
        vocabulary = pieces.Vocabulary(tuple(parts), np.array([8.0 * (len(p) > 12) + 0.1 * (i % 7) for i, p in enumerate(parts)]), np.arange(256, dtype=np.int32), 0.7)
        into = [1.0] + [0.0] * len(chunk)
        for z in range(1, len(chunk) + 1):
            into[z] = sum(into[z - len(p)] * np.exp(0.7 * vocabulary.scores[i]) for i, p in enumerate(parts) if chunk[:z].endswith(p))
        last = {p: into[len(chunk) - len(p)] * np.exp(0.7 * vocabulary.scores[i]) / into[-1] for i, p in enumerate(parts) if chunk.endswith(p)}
        n = 20_000
        data = np.frombuffer(chunk * n, dtype=np.uint8)
        ids, rows = pieces.encode_rows(vocabulary, data, np.arange(n + 1) * len(chunk), np.arange(n, dtype=np.uint64), seed)
        assert b"".join(parts[i] for i in ids) == chunk * n
        found = Counter(parts[i] for i in ids[rows[1:] - 1])
        assert sum(share for p, share in last.items() if len(p) > 12) > 0.1
        for p, share in last.items():
            assert found[p] / n == pytest.approx(share, abs=0.015)
    for p in long[:40]:
        alone = pieces.Vocabulary(whole.pieces, np.where([q == p for q in whole.pieces], 9e3, whole.scores), whole.byte_ids, whole.temperature)
        ids, _ = pieces.encode_rows(alone, np.frombuffer(p, dtype=np.uint8), np.array([0, len(p)]), np.zeros(1, dtype=np.uint64))
        assert [whole.pieces[i] for i in ids] == [p]


def test_chunks_of_every_length_are_whole():
    """No place of a long chunk is a forced cut: its pieces are those of the whole lattice, sampled shares included."""
    vocabulary = pieces.Vocabulary((b"x", b"x" * 7), np.array([0.0, 90.0]), np.arange(256, dtype=np.int32), 5.0)
    ids, rows = pieces.encode_rows(vocabulary, np.frombuffer(b"x" * 70_000, dtype=np.uint8), np.array([0, 70_000]), np.zeros(1, dtype=np.uint64))
    assert rows.tolist() == [0, 10_000] and (ids == 1).all()
    even = pieces.Vocabulary((b"x", b"xx"), np.array([0.0, 0.0]), np.arange(256, dtype=np.int32), 1.0)
    ids, _ = pieces.encode_rows(even, np.frombuffer(b"x" * 60_000, dtype=np.uint8), np.array([0, 60_000]), np.zeros(1, dtype=np.uint64))
    golden = (1 + 5**0.5) / 2  # a step of two has the share golden**-2 of all continuations
    assert (ids == 1).mean() == pytest.approx(golden**-2, abs=0.01) and (ids + 1).sum() == 60_000


def test_toxicity_learns_stems(spark):
    rng = np.random.default_rng(8)
    rows, labels = [], []
    for i in range(400):
        toxic = i % 4 == 0
        w = text_of(1000 + i, 60).split()
        if toxic:
            for at in rng.integers(0, 60, 3):
                w[at] = "grumblo" + "abcdefgh"[rng.integers(0, 8)]
        rows.append((i, " ".join(w), "a"))
        labels.append((i, int(toxic)))
    rows += [(1000, None, "a"), (1001, "", "a")]
    found = toxicity.score_toxicity(make(spark, rows), spark.createDataFrame(labels, "doc_id bigint, toxic int")).collect()
    held = [r for r in found if r.held_out and r.doc_id < 400]
    assert len(held) > 50 and np.mean([r.predicted == int(r.doc_id % 4 == 0) for r in held]) > 0.95
    assert all(0 <= r.score <= 1 and r.predicted == int(r.score >= 0.5) for r in found)
    none = toxicity.score_toxicity(make(spark, rows), spark.createDataFrame([], "doc_id bigint, toxic int")).collect()
    assert all(r.score == 0 for r in none)
    odd = toxicity.score_toxicity(make(spark, [(None, "grumbloa", "a"), (None, None, "a"), *rows]), spark.createDataFrame([*labels, (None, 1), (3, None), (3, 0)], "doc_id bigint, toxic int"))
    assert odd.count() == len(rows) + 2 and odd.where("doc_id is null and held_out").count() in (0, 2)


def plain_models(train):
    """p(class, run of six): Kneser-Ney probabilities of a run's last byte after the five before it, from plain dictionaries."""
    fold = lambda t: b"     " + re.sub(rb"[\x09-\x0D]", b" ", t.encode().lower())
    six = [Counter(), Counter()]
    for t, c in train:
        b = fold(t)
        six[c].update(b[i - 6 : i] for i in range(6, len(b) + 1))
    four = [Counter(r[-4:] for r in six[c]) for c in (0, 1)]
    three = Counter(r[-3:] for r in set(four[0]) | set(four[1]))
    two = Counter(r[-2:] for r in three)

    def scaled(counts):
        n = [sum(c.values()) for c in counts]
        return [{r: k * min(n) / n[c] for r, k in counts[c].items()} for c in (0, 1)]

    def order(counts, discount):
        whole, freed = Counter(), Counter()
        for r, k in counts.items():
            whole[r[:-1]] += k
            freed[r[:-1]] += min(k, discount)
        return lambda r, lower: max(counts.get(r, 0) - discount, 0) / whole[r[:-1]] + freed[r[:-1]] / whole[r[:-1]] * lower if whole[r[:-1]] else lower

    by_two, by_three = order(two, toxicity.BACKOFF), order(three, toxicity.BACKOFF)
    by_four, by_six = ([order(c, toxicity.DISCOUNT) for c in scaled(x)] for x in (four, six))
    return fold, lambda c, r: by_six[c](r, by_four[c](r[-4:], by_three(r[-3:], by_two(r[-2:], 1 / 256))))


@pytest.fixture(scope="module")
def toxic_texts():
    rng = np.random.default_rng(9)
    words = text_of(900, 60).split()
    return [(" ".join(rng.choice(words, 200)) + (" Grumblo\tx" * 3 if i % 3 == 0 else ""), int(i % 3 == 0)) for i in range(30)]


def test_toxicity_is_a_normalised_model(spark, toxic_texts):
    """Every byte's ratio is that of plain Kneser-Ney models, whose probabilities add up to one after every history."""
    fold, p = plain_models(toxic_texts)
    model = toxicity.fit(spark.createDataFrame(toxic_texts, "text string, toxic int"))
    text = toxic_texts[0][0] + " never seen: zq9 " + toxic_texts[1][0].split()[3]
    b = fold(text)
    runs = [b[i - 6 : i] for i in range(6, len(b) + 1)]
    got = model.ratios(toxicity.Runs.of(kernel.Words(np.frombuffer(text.encode(), dtype=np.uint8), np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.int64), np.zeros(2, dtype=np.int64), np.array([0, len(text)]))))
    assert got == pytest.approx([np.log(p(1, r) / p(0, r)) for r in runs], abs=1e-5)
    for r in runs[::40] + [b"zzzzzz", b"rumblo"]:
        for c in (0, 1):
            assert sum(p(c, r[:-1] + bytes([x])) for x in range(256)) == pytest.approx(1)


def test_toxicity_evidence_by_hand(spark, toxic_texts):
    """The mean log ratio of a text and the largest of its windows; the curve's score of both."""
    fold, p = plain_models(toxic_texts)
    model = toxicity.fit(spark.createDataFrame(toxic_texts, "text string, toxic int"))
    texts = [toxic_texts[0][0][-60:], "grumblo", "ab", "", None, "日本 grumblo"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    got = {r.doc_id: (r.evidence, r.peak) for r in toxicity.with_evidence(docs, model).collect()}
    for i, t in enumerate(texts):
        b = fold(t or "")
        logs = [np.log(p(1, b[k - 6 : k]) / p(0, b[k - 6 : k])) for k in range(6, len(b) + 1)]
        size = min(len(logs), toxicity.WINDOW)
        wanted = (np.mean(logs), max(np.mean(logs[k : k + size]) for k in range(len(logs) - size + 1))) if logs else (0.0, 0.0)
        assert got[i] == pytest.approx(wanted, abs=1e-5)


def test_importance_sample(spark, docs, corpus):
    rng = np.random.default_rng(3)
    good = [(i, text_of(i, 60), "a") for i in range(60)]
    junk = [(100 + i, "$$ %% " * int(rng.integers(20, 40)), "a") for i in range(20)]
    labels = spark.createDataFrame([(i, 1) for i in range(45)] + [(100 + i, 0) for i in range(15)], "doc_id bigint, quality int")
    found = importance.resample(make(spark, good + junk), labels).collect()
    assert sum(r.kept for r in found) == 60 and all(r.kept == (r.doc_id < 100) for r in found)
    keys = spark.createDataFrame([(int(k),) for k in [*rng.integers(-(2**62), 2**62, 300), 5, 5, -7, 0]], "key bigint")
    ordered = sorted((r.key for r in keys.collect()), reverse=True)
    assert [importance.kth_largest(keys, k) for k in (1, 2, 150, 304)] == [ordered[0], ordered[1], ordered[149], ordered[303]]
    assert importance.kth_largest(keys, 305) is None


def test_importance_by_hand(spark, docs, corpus):
    """Models, importance, keys and the sample against plain counts of n-grams; buckets by the kernel, one n-gram at a time."""
    import pyarrow as pa
    from strata_descent.llm.common import row_key

    labels = spark.createDataFrame([(1, 1), (3, 1), (9, 1), (11, 0), (2, 0), (13, 1), (13, 0), (None, 1)], "doc_id bigint, quality int")
    target, known = {1, 3, 9, 13}, {}

    def bucket(gram):
        if gram not in known:
            batch = pa.RecordBatch.from_arrays([pa.array([" ".join(gram)])], ["text"])
            found = [importance._features(w)[1].tolist() for _, _, w in kernel.steps(batch)][0]
            known[gram] = [found[0], *found[2:]] if len(gram) == 1 else found[2:3]
            if len(gram) == 1:
                known[gram] = found  # the word, and its two edges
        return known[gram]

    def grams(text):
        w = WORD.findall(text or "")
        return [b for x in w for b in bucket((x,))] + [b for p in zip(w, w[1:], strict=False) for b in bucket(p)]

    every = [grams(t) for _, t, _ in corpus]
    raw, good = Counter(b for g in every for b in g), Counter(b for (d, _, _), g in zip(corpus, every, strict=True) if d in target for b in g)
    n = importance.BUCKETS
    ratio = lambda b: np.log((good[b] + 1) / (sum(good.values()) + n)) - np.log((raw[b] + 1) / (sum(raw.values()) + n))
    rids = {(r.doc_id, r.text): r.u for r in docs.select("doc_id", "text", row_key().alias("rid")).withColumn("u", (F.shiftrightunsigned(F.xxhash64("rid", F.lit(importance.SEED)), 11).cast("double") + 0.5) / F.lit(2.0**53)).collect()}
    keys = [sum(map(ratio, g)) - np.log(-np.log(rids[d, t])) for (d, t, _), g in zip(corpus, every, strict=True)]
    fraction = 5 / 8
    least = sorted(keys, reverse=True)[round(fraction * len(keys)) - 1]
    wanted = sorted((repr(d), len(g), round(k, 3), k >= least - 1e-6) for (d, _, _), g, k in zip(corpus, every, keys, strict=True))
    got = sorted((repr(r.doc_id), r.n_grams, round(r.key, 3), r.kept) for r in importance.resample(docs, labels).collect())
    assert [g[:2] + g[3:] for g in got] == [w[:2] + w[3:] for w in wanted]
    assert [g[2] for g in got] == pytest.approx([w[2] for w in wanted], abs=0.002)


def test_url_filters(spark):
    urls = [None, "", "no-scheme", "https://www.Example.com/en/1?x#y", "http://a.example.com/en/2", "http://a.example.com/fr/2", "https://x.net/es/9", "https://x.net/de/9", "http://cheap-pills.example.org/x", "http://notexample.com", "http://example.com/en/", "HTTP://q.org?u=://b.net/fr/", "http://x.org/online-casino/1"]
    pages = spark.createDataFrame([(i, u, "h") for i, u in enumerate([*urls, urls[3]])], "page_id bigint, url string, host string")
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in url_filters.judge_urls(pages).collect()}
    assert got[0] == got[1] == got[2] == ("", "", None, "allow")
    assert got[3] == got[13] == ("www.example.com", "/en/1", "www.example.com/en/", "allow")
    assert got[4][2:] == ("example.com/en/", "block") and got[5][2:] == ("com/", "allow")
    assert got[6][2:] == ("net/es/", "block") and got[7][2:] == (None, "allow")
    assert got[8][2:] == (None, "block") and got[9][2:] == (None, "allow") and got[12][3] == "block"
    assert got[10][2:] == ("example.com/en/", "block") and got[11][0] == "q.org"


def test_url_index_finds_what_all_patterns_find(spark):
    """Every way in which a pattern can match is fetched: the verdicts are those of all patterns run on all URLs."""
    bits = [
        "cheap-pills", "cheap-meds", "cheap-viagra", "casino-bonus", "casinos-online", "casinobonus", "casinosonline", "casinoonline", "casinosbonus", "online-casino", "onlinecasino", "free-spins", "freespins",
        "payday-loan", "payday-loans", "paydayloan", "paydayloans", "replica-watch", "replica-watches", "buy-viagra", "buy-cialis", "buy-tramadol", "porn", "xxx", "wp-login", "wp-admin", "calendar/2024/01/02",
        "watch", "casino", "online", "bonus", "free", "payday", "loans", "replica", "jsessionid",
    ]
    urls = [f"http://h.org/{b}{end}" for b in bits for end in ("/", ".php", "?x", "y/", "")]
    urls += [f"http://h.org/{b.upper()}/" for b in bits] + [f"http://h.org/a{mark}{key}=0123456789ab" for mark in "?&" for key in ("phpsessid", "jsessionid", "JSESSIONID", "sessionid")]
    urls += ["http://h.org/?add-to-cart=7", "http://mirror12.h.org/pub/x", "http://a.mirror.org/pub/", "http://h.org/mirror3.x/pub/"]
    urls += [f"http://h.org/replica/{i}" for i in range(40)]  # so that the other token is the rarer one
    pages = spark.createDataFrame([(u,) for u in urls], "url string")
    found = {r.url: r.pattern_verdict for r in url_filters.pattern_verdicts(pages).collect()}
    fit = [r for u in set(urls) for r in [(u, next((r.verdict for r in url_filters.PATTERN_RULES if re.search(r.pattern, u.lower())), None))] if r[1]]
    assert found == dict(fit) and len(fit) > 60


def test_url_host_rules_are_looked_up(spark):
    """The longest rule that fits a host or its parents, against a scan of all rules; hosts of many parts, ties, ports, repeated and null URLs."""
    rng = np.random.default_rng(6)
    part = lambda n: ".".join(rng.choice(["a", "b", "net", "com", ""], n))
    rules = tuple(url_filters.HostRule(("allow", "block")[int(rng.integers(0, 2))], h, p) for h, p in sorted({(part(int(rng.integers(1, 4))), str(rng.choice(["/", "/a/", "/a/b"]))) for _ in range(60)}))
    urls = [f"http://{part(int(rng.integers(1, 5)))}{rng.choice(['', ':80'])}{rng.choice(['/', '/a/x', '/a/b', '', '?q'])}" for _ in range(300)] + [None, None]
    pages = spark.createDataFrame([(i if i % 50 else None, u) for i, u in enumerate(urls)], "page_id bigint, url string")
    wanted = []
    for r in pages.collect():
        host = (r.url or "://").split("://")[1].split("/")[0].split("?")[0]
        path = (r.url or "").split("://")[-1].split("?")[0][len(host) :]
        fit = [x for x in rules if ("." + host).endswith("." + x.host) and path.startswith(x.path)]
        best = max(fit, key=lambda x: (len(x.host) + len(x.path), x.host, x.path), default=None)
        wanted.append((r.page_id, host, path, best and best.host + best.path, best.verdict if best else "allow"))
    for listed, expected in ((rules, wanted), ((), [(i, h, p, None, "allow") for i, h, p, _, _ in wanted])):
        assert sorted((tuple(r) for r in url_filters.judge_urls(pages, listed, ()).collect()), key=repr) == sorted(expected, key=repr)


def test_empty_tables(spark, empty):
    labels = spark.createDataFrame([], "doc_id bigint, quality int, toxic int")
    frames = [
        ngram_join.join_documents(empty), substring_dedup.remove_repeats(empty), toxicity.score_toxicity(empty, labels), fingerprints.against_edits(empty), mixing.taken_words(empty),
        personal_data.find_personal_data(empty), pieces.sample_pieces(empty), quality_rules.judge_quality(empty, labels), importance.resample(empty, labels),
        url_filters.judge_urls(spark.createDataFrame([], "page_id bigint, url string")),
    ]
    assert [f.count() for f in frames] == [0] * 10
