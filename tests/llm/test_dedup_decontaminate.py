import hashlib
import random
import re

import numpy as np
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from cubejoin.llm import components, decontaminate, minhash_join
from cubejoin.llm.textbatch import ALNUM, NON_BLANK, Words, gram_hashes, segment_hashes, slices, string_buffers
from cubejoin.llm.workspace import Workspace

DOC = "doc_id long, text string"


def lowered(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def shingles(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", lowered(text))
    if len(w) < 5:
        return {tuple(w)} if w else set()
    return set(zip(*(w[k:] for k in range(5)), strict=False))


def brute_components(rows, percent=85):
    sets = {i: shingles(t) for i, t in rows}
    parent = {i: i for i in sets}

    def find(a):
        while parent[a] != a:
            a = parent[a]
        return a

    ids = sorted(sets)
    for n, a in enumerate(ids):
        for b in ids[n + 1 :]:
            union = len(sets[a] | sets[b])
            if union and 100 * len(sets[a] & sets[b]) >= percent * union:
                x, y = find(a), find(b)
                parent[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in ids}


@settings(deadline=None)
@given(st.lists(st.text(alphabet="aB zé \t\n0-", max_size=30), min_size=1, max_size=8))
def test_words_match_regular_expressions(texts):
    raw, borders = string_buffers(pa.array(texts))
    for table, expression in ((NON_BLANK, r"[^\x20\x09-\x0D]+"), (ALNUM, r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")):
        words = Words(raw, borders, table)
        seen = {}
        for row, text in enumerate(texts):
            found = re.findall(expression, lowered(text))
            lo, hi = words.rows[row], words.rows[row + 1]
            assert hi - lo == len(found)
            for h, w in zip(words.hashes[lo:hi].tolist(), found, strict=True):
                assert seen.setdefault(w, h) == h
        assert len(set(seen.values())) == len(seen)


def test_slices_cover_rows_and_nulls():
    batch = pa.RecordBatch.from_arrays([pa.array([1, 2, 3, 4]), pa.array(["ab", None, "x" * 50, ""])], names=["doc_id", "text"])
    parts = list(slices(batch, "text", 10))
    assert sum(p.num_rows for p, _, _ in parts) == 4
    assert b"".join(r.tobytes() for _, r, _ in parts) == b"ab" + b"x" * 50


def test_long_words_and_grams():
    data = np.frombuffer(b"a" * 3000 + b"b", np.uint8)
    assert len(segment_hashes(data, np.array([3000, 1]))) == 2
    grams, at, rows = gram_hashes(np.arange(7, dtype=np.uint64), np.array([0, 3, 7]), 3)
    assert rows.tolist() == [0, 1, 3] and at.tolist() == [0, 3, 4]


@pytest.fixture(scope="module")
def corpus():
    rng = random.Random(5)
    words = [f"w{i}" for i in range(400)]
    rows, base = [], [rng.choice(words) for _ in range(60)]
    for i in range(40):  # edited copies of one text, some far from it
        copy = list(base)
        for _ in range(rng.randint(0, 4)):
            copy[rng.randrange(60)] = f"new{rng.randrange(10**6)}"
        rows.append((i, " ".join(copy)))
    rows += [(100 + i, " ".join(base)) for i in range(5)]
    rows += [(200 + i, " ".join(rng.choice(words) for _ in range(rng.randint(1, 80)))) for i in range(60)]
    rows += [(300, None), (301, ""), (302, " \t\n"), (303, "Two words"), (304, "two WORDS"), (305, "a b c d e"), (306, "x" * 20000), (307, "long " * 9000), (308, "LONG " * 9000)]
    return rows


@pytest.mark.parametrize("chosen", [minhash_join.JoinSettings(direct=2, part=3), minhash_join.JoinSettings.for_similarity(80)])
def test_components_match_brute_force(spark, corpus, chosen):
    frame = spark.createDataFrame(corpus, DOC).repartition(3)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in minhash_join.near_duplicates(spark, frame, chosen).collect()}
    assert got == brute_components(corpus, chosen.similarity_percent)


def test_crowds_of_distant_copies_make_few_pairs(spark):
    rng = random.Random(9)
    base = [f"w{i}" for i in range(150)]
    rows = []
    for i in range(150):  # most have two edits of their own and link with nobody
        copy = list(base)
        for at in rng.sample(range(5, 145), 1 if i % 30 == 0 else 2):
            copy[at] = f"new{rng.randrange(10**6)}"
        rows.append((i, " ".join(copy)))
    exact = {i: shingles(t) for i, t in rows}
    links = {(a, b) for a in exact for b in exact if a < b and 100 * len(exact[a] & exact[b]) >= 85 * len(exact[a] | exact[b])}
    sets = spark.createDataFrame(rows, "id long, text string").mapInArrow(minhash_join._set_kernel("text"), "id long, shingles array<long>")
    roots = spark.createDataFrame([], "id long, root long")
    chosen = minhash_join.JoinSettings()
    pairs = {(r.a, r.b) for r in minhash_join._set_prefix_pairs(Workspace(spark, "t"), sets, roots, chosen).collect()}
    assert links <= pairs and len(pairs) < len(links) + 1500  # of 11,175


def test_rows_without_or_with_shared_ids(spark):
    base = [f"w{i}" for i in range(60)]
    a, b = " ".join(base), " ".join(f"v{i}" for i in range(60))
    rows = [(5, a), (5, b), (6, a + " z"), (7, b + " z"), (None, a), (None, "alone here in this long text"), (None, None), (9, None), (9, ""), (9, ""), (None, "alone here in this long text")]
    for order in (1, -1):
        got = sorted(minhash_join.near_duplicates(spark, spark.createDataFrame(rows[::order], DOC)).collect(), key=str)
        seen = sorted(((r.doc_id, r.n_shingles, r.component_id, r.kept) for r in got), key=str)
        alone = 2
        want = [(5, 56, 5, True), (5, 56, 5, True), (6, 57, 5, False), (7, 57, 5, False), (None, 56, 5, False), (None, alone, None, True), (None, alone, None, True), (None, 0, None, True), (9, 0, 9, True), (9, 0, 9, True), (9, 0, 9, True)]
        assert seen == sorted(want, key=str)
        group = {}
        for r in got:
            if r.n_shingles:
                group.setdefault(r.group_id, set()).add((r.doc_id, r.n_shingles))
        assert sorted(map(len, group.values())) == [1, 2, 3]


def test_near_duplicates_of_odd_tables(spark):
    empty = spark.createDataFrame([], "doc_id long, text string, n_shingles int")
    assert minhash_join.near_duplicates(spark, empty).count() == 0
    clash = spark.createDataFrame([(1, "a b c d e f", 9), (1, "a b c d e f", 9), (2, None, 9)], "doc_id long, text string, low int")
    got = minhash_join.near_duplicates(spark, clash).collect()
    assert sorted((r.doc_id, r.component_id, r.kept) for r in got) == [(1, 1, True), (1, 1, True), (2, 2, True)]


def test_components_of_a_sorted_chain(spark):
    chain = [(i, i + 1) for i in range(40)] + [(100, 101), (100, 100)]
    found = components.connected_components(Workspace(spark, "t"), spark.createDataFrame(chain, "a long, b long"), "cc").collect()
    roots = {r.node: r.root for r in found}
    assert len({roots[i] for i in range(41)}) == 1 and roots[100] == roots[101] != roots[0] and len(roots) == 43


def brute_hits(text, windows):
    w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lowered(text))
    hit, items = set(), set()
    for k in {len(x) for x in windows}:
        for s in range(len(w) - k + 1):
            found = windows.get(tuple(w[s : s + k]))
            if found:
                hit.update(range(s, s + k))
                items |= found
    return len(w), len(hit), len(items), hashlib.sha256(",".join(sorted(items)).encode()).hexdigest(), bool(hit)


def test_contamination_matches_brute_force(spark):
    rng = random.Random(6)
    words = [f"v{i}" for i in range(30)]
    items = [(str(i), " ".join(rng.choice(words) for _ in range(rng.choice([0, 1, 3, 7, 10, 11, 25])))) for i in range(30)]
    items += [("dup", items[-1][1]), (None, "v1 v2"), ("nul", None), ("rep", "v1 v1 v1 v1 v1 v1 v1 v1 v1 v1 v1 v1")]
    docs = [(i, " ".join(rng.choice(words) for _ in range(rng.randint(0, 60)))) for i in range(40)]
    docs += [(100 + i, f"Ünrelated {t.upper()}; tail" if t else None) for i, (_, t) in enumerate(items)]
    docs += [(200, "v1 " * 5000), (201, ""), (202, "v1-v1,v1.v1 v1 v1 v1 v1 v1 v1")]
    windows = {}
    for item, text in items:
        w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", lowered(text))
        k = min(10, len(w))
        if item is not None and k:
            for s in range(len(w) - k + 1):
                windows.setdefault(tuple(w[s : s + k]), set()).add(item)
    got = decontaminate.contamination(spark, spark.createDataFrame(docs, DOC), spark.createDataFrame(items, "item_id string, text string")).collect()
    for r in got:
        assert (r.n_words, r.n_hit, r.n_items, r.items_sha256, r.contaminated) == brute_hits(dict(docs)[r.doc_id], windows), r.doc_id
    assert len(got) == len(docs)


def test_contamination_is_told_by_row(spark):
    item = "one two three four five six seven eight nine ten eleven twelve"
    docs = [(1, f"so {item} end"), (1, "two words"), (None, f"x {item}"), (None, "clean words here"), (None, None), (0, "clean words here"), (1, "two words")]
    frame = spark.createDataFrame(docs, DOC).selectExpr("*", "1 as n_hit", "'x' as token", "2 as text_key", "3 as place")
    items = spark.createDataFrame([("a", item), ("b", item), (None, "clean words here"), ("c", None)], "item_id string, text string").selectExpr("*", "'y' as window", "4 as kind")
    got = sorted(((r.doc_id, r.n_words, r.n_hit, r.n_items, r.contaminated) for r in decontaminate.contamination(spark, frame, items).collect()), key=str)
    want = [(1, 14, 12, 2, True), (1, 2, 0, 0, False), (1, 2, 0, 0, False), (None, 13, 12, 2, True), (None, 3, 0, 0, False), (None, 0, 0, 0, False), (0, 3, 0, 0, False)]
    assert got == sorted(want, key=str)


def test_contamination_of_empty_tables(spark):
    docs = spark.createDataFrame([(1, "a b")], DOC)
    none = spark.createDataFrame([], "item_id string, text string")
    assert [(r.n_hit, r.contaminated) for r in decontaminate.contamination(spark, docs, none).collect()] == [(0, False)]
    assert decontaminate.contamination(spark, docs.limit(0), none).count() == 0
