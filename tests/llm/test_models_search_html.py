import functools
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from cubejoin.llm import hilbert_ann, html_wrapper, language_gru, quality_ftrl

DOC = "doc_id long, text string"


def test_gradients_match_differences():
    rng = np.random.Generator(np.random.PCG64(0))
    net = language_gru.ByteGru(4, 3, 1)
    net.p = {k: v.astype(np.float64) for k, v in net.p.items()}
    seq = rng.integers(97, 103, (5, 4)).astype(np.uint8)
    label, weight = np.array([0, 1, 2, 1, 0]), np.array([1.0, 2.0, 1.0, 0.5, 1.0])
    _, grads = net.loss_and_gradients(seq, label, weight)
    for name in net.NAMES:
        flat = net.p[name].ravel()
        spots = range(len(flat)) if not name.startswith("table") else [int(seq[0, 0]) * 12 + k for k in range(12)]
        for i in list(spots)[:12]:
            held = flat[i]
            flat[i] = held + 1e-5
            up, _ = net.loss_and_gradients(seq, label, weight)
            flat[i] = held - 1e-5
            down, _ = net.loss_and_gradients(seq, label, weight)
            flat[i] = held
            assert grads[name].ravel()[i] == pytest.approx((up - down) / 2e-5, abs=1e-6), name


def test_language_accuracy_held_out(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    got = language_gru.identify_languages(spark, docs).join(docs.select("doc_id", "lang"), "doc_id").collect()
    held = [r for r in got if r.held_out]
    assert all(r.held_out == (zlib.crc32(str(r.doc_id).encode()) % 4 == 2) for r in got)
    assert held and sum(r.lang == r.lang_pred for r in held) / len(held) > 0.95
    assert all(0 <= r.score <= 1 for r in got)


def test_language_edge_cases(spark):
    text = {"aa": "baba dada gaga lala", "bb": "zyx wvu tsr qpo"}
    rows = [(i, text["aa" if i % 2 else "bb"] + f" {i}", "aa" if i % 2 else "bb") for i in range(60)]
    rows += [(100, None, "aa"), (101, "", "bb"), (102, "123 !!", "aa"), (103, "baba" * 20000, None), (104, "—–…", None), (105, "DADA GAGA", None)]
    frame = spark.createDataFrame(rows, DOC + ", lang string").withColumn("score", F.lit("x"))
    small = language_gru.GruSettings(epochs=30)
    got = {r.doc_id: r for r in language_gru.identify_languages(spark, frame, small).collect()}
    assert {i for i in got if got[i].lang_pred == "und"} == {100, 101, 102, 104}
    assert got[103].lang_pred == got[105].lang_pred == "aa"
    nothing = language_gru.identify_languages(spark, frame.withColumn("lang", F.lit(None).cast("string"))).collect()
    assert {r.lang_pred for r in nothing} == {"und"}
    assert language_gru.identify_languages(spark, frame.limit(0)).count() == 0


def test_training_bound_is_per_language(spark):
    rows = [(i, " ".join(f"w{'abcdefghij'[i % 10]}{'klmnopqrst'[j % 10]}{'abcdefghij'[j // 10]}{'uvxy'[i // 10]}" for j in range(100)), "big") for i in range(40)]
    rows += [(1000 + i, "ж" * (30 + i), f"rare{i}") for i in range(200)]
    small = language_gru.GruSettings(segments=50)
    got = language_gru.training_segments(spark.createDataFrame(rows, DOC + ", lang string"), small).collect()
    count = {}
    for r in got:
        count[r.lang] = count.get(r.lang, 0) + 1
    assert count["big"] == 50
    assert len(count) == 1 + sum(zlib.crc32(str(1000 + i).encode()) % 4 != 2 for i in range(200))  # no language is left out
    assert all(len(r.segment) <= small.segment for r in got)
    assert any(b" " in bytes(r.segment) for r in got)


def test_streams_and_segments():
    import pyarrow as pa

    from cubejoin.llm.textbatch import string_buffers

    raw, borders = string_buffers(pa.array(["ab, cd!", "", None, "  é1é", "x", "9"]))
    data, rows = language_gru.letter_stream(raw, borders)
    assert [data[a:b].tobytes().decode() for a, b in zip(rows, rows[1:], strict=False)] == ["ab cd ", "", "", "é é", "x", ""]
    starts, lengths, ranges = language_gru.cut_segments(np.array([0, 6, 6, 11]), 4)
    assert starts.tolist() == [0, 4, 6, 10] and lengths.tolist() == [4, 2, 4, 1] and ranges.tolist() == [0, 2, 2, 4]


def test_batched_labels_equal_single_ones():
    net = language_gru.ByteGru(5, 3, 3)
    data = np.random.Generator(np.random.PCG64(1)).integers(97, 123, 200).astype(np.uint8)
    starts, lengths, _ = language_gru.cut_segments(np.array([0, 150, 171, 200]), 40)
    sums = language_gru.SegmentLabeller(net).sums(data, starts, lengths)
    for s, n, got in zip(starts, lengths, sums, strict=True):
        assert got == pytest.approx(net.probabilities(data[s : s + n][None])[0].sum(0), abs=1e-4)


def test_network_reads_across_runs(spark):
    """The two languages use the same words; only their order differs."""
    rng = random.Random(3)
    rows = []
    for i in range(240):
        words = [w for _ in range(30) for w in (("ka", "lo", "mi") if i % 2 else ("mi", "lo", "ka"))]
        at = rng.randrange(3)
        rows.append((i, " ".join(words[at:]), "up" if i % 2 else "down"))
    got = language_gru.identify_languages(spark, spark.createDataFrame(rows, DOC + ", lang string"), language_gru.GruSettings(epochs=30)).collect()
    held = [r for r in got if r.held_out]
    assert held and sum((r.lang_pred == "up") == bool(r.doc_id % 2) for r in held) / len(held) > 0.95


def test_languages_of_repeated_rows_and_null_ids(spark):
    rows = [(i, "baba dada" if i % 2 else "zyx wvu", "aa" if i % 2 else "bb") for i in range(60)] + [(1, "baba dada", "aa"), (None, "baba dada", "aa"), (None, None, None)]
    frame = spark.createDataFrame(rows, DOC + ", lang string").selectExpr("*", "1 as k", "2 as place", "3 as segment", "4 as lang_pred", "5 as lowered")
    got = language_gru.identify_languages(spark, frame, language_gru.GruSettings(epochs=20)).collect()
    assert len(got) == 63 and sorted(r.lang_pred for r in got if r.doc_id is None) == ["aa", "und"]
    assert len({(r.lang_pred, r.score) for r in got if r.doc_id == 1}) == 1


def test_quality_held_out(spark, tiny):
    docs, labels = spark.read.parquet(f"{tiny}/documents.parquet"), spark.read.parquet(f"{tiny}/labels.parquet")
    got = quality_ftrl.classify(spark, docs, labels).join(labels, "doc_id").collect()
    held = [r for r in got if r.held_out]
    assert held and sum(r.predicted == r.quality for r in held) / len(held) > 0.9
    assert all(r.predicted == int(r.score >= 0.3) for r in got)


def test_quality_scores_are_sparse_dot_products(spark):
    weights = np.random.Generator(np.random.PCG64(1)).standard_normal(1 << 10)
    model = quality_ftrl.QualityModel(weights, 0.25, 10, 8.0)
    rows = [(1, "One two three two two"), (2, None), (3, ""), (4, "w " * 30000), (1, "One two three two two")]
    got = quality_ftrl.score_documents(spark, spark.createDataFrame(rows, DOC), model).collect()
    assert len(got) == 5
    import pyarrow as pa

    from cubejoin.llm.textbatch import string_buffers

    for r in got:
        text = dict(rows)[r.doc_id] or ""
        total = 0.25
        for grams, borders in quality_ftrl.features(*string_buffers(pa.array([text])), 10):
            own = grams[borders[0] : borders[1]]
            total += 8.0 * sum(weights[g] for g in own.tolist()) / len(own) if len(own) else 0.0
        assert r.score == pytest.approx(1 / (1 + np.exp(-total)), rel=1e-9)


def test_quality_without_labels(spark):
    docs = spark.createDataFrame([(1, "a"), (2, None)], DOC)
    none = spark.createDataFrame([], "doc_id long, quality int")
    assert [r.score for r in quality_ftrl.classify(spark, docs, none).collect()] == [0.5, 0.5]


def test_ftrl_learns_a_separable_sample():
    model = quality_ftrl.Ftrl(quality_ftrl.FtrlSettings(bits=4))
    for _ in range(60):
        model.learn(np.array([1, 2]), np.array([1.0, 1.0]), 1)
        model.learn(np.array([2, 3]), np.array([1.0, 1.0]), 0)
    assert model.weights()[1] > 0.5 and model.weights()[3] < -0.5 and model.weights()[7] == 0


def test_hilbert_keys_walk_the_grid():
    for n, bits in ((2, 3), (3, 2)):
        cells = np.stack(np.meshgrid(*[np.arange(1 << bits)] * n, indexing="ij"), -1).reshape(-1, n)
        keys = hilbert_ann.hilbert_keys(cells, bits)
        assert sorted(keys) == list(range((1 << bits) ** n))
        path = cells[np.argsort(keys)]
        assert np.abs(np.diff(path, axis=0)).sum(1).max() == 1


def brute(ids, vectors, k):
    out = {}
    for q in [i for i in range(len(ids)) if ids[i] % 20 == 0]:
        scored = sorted((-float(np.sum(vectors[q] * vectors[j])), ids[j]) for j in range(len(ids)) if ids[j] != ids[q])
        out[ids[q]] = [i for _, i in scored[:k]]
    return out


@pytest.mark.parametrize("clustered", [False, True])
def test_neighbours_match_brute_force(spark, clustered):
    rng = np.random.Generator(np.random.PCG64(2))
    vectors = rng.standard_normal((400, 16)).astype(np.float32).astype(np.float64)
    if clustered:
        vectors[200:] = vectors[200:] * 0.01 + np.repeat(rng.standard_normal((4, 16)) * 5, 50, 0)
        vectors = vectors.astype(np.float32).astype(np.float64)
    rows = [(i, v.tolist()) for i, v in enumerate(vectors)]
    settings = hilbert_ann.CurveSettings(block=16, ball=32, query_block=8, partitions=3, orderings=2, reach=1)
    got = hilbert_ann.nearest(spark, spark.createDataFrame(rows, "vec_id long, embedding array<float>"), F.col("vec_id") % 20 == 0, settings).collect()
    found = {}
    for r in sorted(got, key=lambda r: (r.query_id, r.rank)):
        found.setdefault(r.query_id, []).append(r.vec_id)
        assert r.score == pytest.approx(float(np.sum(vectors[r.query_id] * vectors[r.vec_id])), rel=1e-12)
    assert found == brute(list(range(400)), vectors, 20)


def test_neighbours_with_ties_and_bad_vectors(spark):
    rows = [(i, [1.0, 0.0]) for i in range(60)] + [(100, None), (101, [0.0, 0.0]), (102, [float("nan"), 1.0]), (103, [None, 1.0]), (104, [float("inf"), 1.0]), (105, [1.0]), (120, [2.0]), (None, [1.0, 1.0]), (3, [1.0, 0.0])]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumn("score", F.lit(1))
    got = hilbert_ann.nearest(spark, frame, F.col("vec_id") % 20 == 0, hilbert_ann.CurveSettings(block=16)).collect()
    for q in (0, 20, 40):
        assert [r.vec_id for r in sorted(got, key=lambda r: r.rank) if r.query_id == q] == [i for i in range(22) if i != q][:20]
    assert {r.query_id for r in got} == {0, 20, 40, 120}
    assert [(r.rank, r.vec_id, r.score) for r in got if r.query_id == 120] == [(1, 105, 2.0)]  # another length, searched by itself
    assert hilbert_ann.nearest(spark, frame.limit(0), F.col("vec_id") % 20 == 0).count() == 0
    few = spark.createDataFrame([(0, [1.0, 2.0]), (1, [2.0, 1.0])], "vec_id long, embedding array<float>")
    assert [(r.query_id, r.rank, r.vec_id, r.score) for r in hilbert_ann.nearest(spark, few, F.col("vec_id") % 20 == 0).collect()] == [(0, 1, 1, 4.0)]


def test_shelves_keep_exact_neighbours():
    rng = np.random.default_rng(4)
    v = np.repeat(rng.standard_normal((40, 6)), 3, axis=0)  # ties
    ids, balls = rng.permutation(len(v)) * 7, np.arange(len(v)) // 16
    q_ids, q = np.array([ids[5], 10_000, 3]), v[[5, 60, 100]]
    floors = np.array([-np.inf, 1.0, -np.inf])
    got = hilbert_ann.best_on_shelf(q_ids, q, floors, ids, v, balls, 5)
    want = []
    for i, x, floor in zip(q_ids, q, floors, strict=True):
        scores = hilbert_ann.exact_scores(np.repeat(x[None, :], len(v), 0), v)
        best = sorted((-s, j) for s, j in zip(scores, ids, strict=True) if j != i and s >= floor)[:5]
        want += [(i, j, -s) for s, j in best]
    assert sorted(zip(*got, strict=True)) == sorted(want)


def test_no_join_of_vectors_is_broadcast(spark, monkeypatch):
    plans = {}

    def table(self, name, frame, batch=512):
        plans[name] = frame._jdf.queryExecution().executedPlan().toString()
        return kept(self, name, frame, batch)

    kept = hilbert_ann.Workspace.table
    monkeypatch.setattr(hilbert_ann.Workspace, "table", table)
    frame = spark.createDataFrame([(i, v) for i, v in enumerate(np.random.default_rng(8).standard_normal((300, 8)).tolist())], "vec_id long, embedding array<float>")
    hilbert_ann.nearest(spark, frame, F.col("vec_id") % 20 == 0, hilbert_ann.CurveSettings(block=16, ball=32))
    assert not [n for n in ("first", "asks", "bounds", "shelves", "wide") if "BroadcastHashJoin" in plans[n]]


@pytest.mark.parametrize("n", [2000, 8000])
def test_windows_alone_find_neighbours_in_clusters(spark, n):
    """Recall of the windows without widening, where they hold less than a fifth of the vectors."""
    rng = np.random.Generator(np.random.PCG64(3))
    centres = rng.standard_normal((n // 50, 24))
    centres /= np.linalg.norm(centres, axis=1, keepdims=True)
    vectors = np.repeat(centres, 50, 0) + rng.standard_normal((n, 24)) * 0.04
    vectors = rng.permutation(vectors / np.linalg.norm(vectors, axis=1, keepdims=True))
    frame = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(vectors)], "vec_id long, embedding array<double>")
    settings = hilbert_ann.CurveSettings(block=16 * n // 2000, reach=1, expand=False)
    assert hilbert_ann.visited_share(spark, frame, None, settings)["share"] < 0.2
    got = {(r.query_id, r.vec_id) for r in hilbert_ann.nearest(spark, frame, F.col("vec_id") % 20 == 0, settings).collect()}
    true = 0
    for q in range(0, n, 20):
        s = vectors @ vectors[q]
        s[q] = -np.inf
        true += sum((q, int(j)) in got for j in np.argpartition(-s, 20)[:20])
    assert true / (20 * (n // 20)) >= 0.9


def test_close_scores_are_decided_exactly():
    rng = np.random.Generator(np.random.PCG64(7))
    v = np.repeat(rng.standard_normal((1, 64)), 300, 0)
    v[np.arange(300), rng.integers(0, 64, 300)] += rng.standard_normal(300) * 1e-15  # differences far below any rounding to decimals
    q = rng.standard_normal((3, 64))
    ids = rng.permutation(300) + 100
    a, b, s = hilbert_ann.best_pairs(np.arange(3), q, np.full(3, -np.inf), ids, v, 20)
    for k in range(3):
        scored = sorted((-functools.reduce(lambda t, j: t + j, (float(x) * float(y) for x, y in zip(q[k], v[j], strict=True)), 0.0), int(ids[j])) for j in range(300))
        assert [(-x, y) for x, y in zip(s[a == k].tolist(), b[a == k].tolist(), strict=True)] == scored[:20]


def test_huge_components_and_negative_scores(spark):
    rng = np.random.Generator(np.random.PCG64(9))
    rows = [(i, (rng.standard_normal(4) - 5).tolist()) for i in range(60)] + [(100, [5.0, 5.0, 5.0, 5.0]), (200, [1e200, 1e200, 1.0, 1.0]), (201, [1e200, -1e200, 1.0, 1.0])]
    frame = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = hilbert_ann.nearest(spark, frame, F.col("vec_id").isin(100, 200), hilbert_ann.CurveSettings(block=8, ball=8, reach=0, orderings=1)).collect()
    vectors = dict(rows)
    for q in (100, 200):
        score = lambda j: float(hilbert_ann.exact_scores(np.array([vectors[q]]), np.array([vectors[j]]))[0])  # noqa: E731, B023
        want = sorted((-score(j), j) for j in vectors if j != q)[:20]
        assert [r.vec_id for r in sorted(got, key=lambda r: r.rank) if r.query_id == q] == [j for _, j in want]


PAGE = "<!DOCTYPE html><html><head><title>T &amp; x</title><style>p{}</style><script>var t='</p>';</script></head><body><nav><ul><li><a>Home</a></li></ul></nav><!-- c --><div class=\"ad\">Buy</div><article><h1>Head &amp; line</h1><p>One  <b>two</b><br>three<p>Four&nbsp;five &lt;six&gt;{extra}</p></article><footer>&copy; x</footer></body></html>"


def extract(spark, rows):
    frame = spark.createDataFrame(rows, "page_id long, url string, html string").withColumn("host", F.lit("clash"))
    return {r.page_id: r for r in html_wrapper.extract(spark, frame).collect()}


def test_article_text(spark):
    rows = [(1, "http://a.b/c", PAGE.replace("{extra}", "")), (2, None, None), (3, "x", ""), (4, "http://a.b/d", "plain text only"), (5, "http://a.b/e", "<p>" * 3000 + "deep"), (6, "http://a.b/f", "<article><p>unclosed <b>bold<p>next<aside>side</aside><form>f</form><div class='user-comments'>no</div><ul><li>a<li>b</ul></article>")]
    got = extract(spark, rows)
    assert got[1].text == "Head & line\nOne two three\nFour five <six>"
    assert got[2].text == got[3].text == "" and got[2].n_chars == 0
    assert got[4].text == "plain text only" and got[5].text == "deep"
    assert got[6].text == "unclosed bold\nnext\na\nb"
    assert all(r.n_chars == len(r.text) for r in got.values())
    assert html_wrapper.extract(spark, spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


def test_constant_nodes_are_template(spark):
    rng = random.Random(1)
    page = lambda i: f"<html><body><div><p>Welcome to the site</p></div><div><p>Story {i} {rng.random()}</p>{'<p>more %d</p>' % i * (i % 3)}</div><div><p>All rights reserved</p></div></body></html>"
    rows = [(i, "http://host.example/p", page(i)) for i in range(20)]
    rows += [(100 + i, "http://copies.example/p", "<body><p>Same</p><p>Text</p></body>") for i in range(30)]
    got = extract(spark, rows)
    for i in range(20):
        assert "Welcome" not in got[i].text and "reserved" not in got[i].text and f"Story {i} " in got[i].text
        assert got[i].text.count("more") == i % 3
    assert got[100].text == "Same\nText"  # equal pages prove nothing


def test_small_hosts_and_stubs_have_templates(spark):
    page = lambda i: f"<html><body><div><p>Welcome to the site</p></div><div><p>Story {i} told</p></div><div><p>All rights reserved</p></div></body></html>"
    rows = [(i, f"http://small{i % 2}.example/p", page(i)) for i in range(4)] + [(10 + i, "http://stub.example/p", page(i)) for i in range(12)] + [(99, "http://stub.example/p", "<p>moved</p>"), (98, "http://one.example/", page(1))]
    got = extract(spark, rows)
    assert all(got[i].text == f"Story {i % 10 if i < 10 else i - 10} told" for i in [*range(4), *range(10, 22)])
    assert got[99].text == "moved" and got[98].text == "Welcome to the site\nStory 1 told\nAll rights reserved"


def test_words_of_class_names_do_not_drop_the_article():
    def text(source):
        dom = html_wrapper.Dom(source)
        return "|".join(t for _, t in dom.blocks(dom.content_nodes()))

    assert text("<article><div class='entry-header'><h1>Title</h1></div><h2 id='related-work'>R</h2><section id='discussion'><p>D</p></section><h2 id='side-effects'>S</h2><div class='share-buttons'>x</div></article>") == "Title|R|D|S"
    assert text("<div class='content no-sidebar'><p>All</p></div><div class='site-header'>x</div>") == "All"
    assert text("<div class='has sidebar'><article>A</article></div><div id='comments'><article>B</article></div>") == "A"
    assert text("<div class='sidebar-left layout'><p>Most of the text is here</p></div><div class='sidebar'>x</div>") == "Most of the text is here"


def test_constant_text_inside_an_article_stays(spark):
    page = lambda i: f"<body><div>Menu {i}</div><article><h1>T{i}</h1><p>As always, we begin.</p><p>Story {i}</p></article><div>Foot</div></body>"
    got = extract(spark, [(i, "http://h.example/p", page(i)) for i in range(12)])
    assert all(got[i].text == f"T{i}\nAs always, we begin.\nStory {i}" for i in range(12))


def plain_page(rng, i, deep, parts):
    """A page without any telling tag, class or role, and its article."""
    words = lambda n: " ".join(rng.choice("red green blue house tree river stone cloud night path".split()) + str(rng.randrange(100)) for _ in range(n))
    title, paragraphs = words(5), [words(rng.randint(30, 60)) for _ in range(parts)]
    menu = "".join(f"<div><a href='/{k}'>{words(1)}</a></div>" for k in range(5))
    story = f"<div><h2>{title}</h2>" + "".join(f"<div>{p}</div>" for p in paragraphs) + "</div>"
    html = f"<html><body><div><div>The host's own name</div>{menu}</div><div>{words(4)}</div>{'<div>' * deep}{story}{'</div>' * deep}<div>Some fixed words. {words(3)}</div><div>All rights reserved</div></body></html>"
    return html, "\n".join([title, *paragraphs])


@pytest.mark.parametrize("deep", [0, 200])
def test_induction_decides_where_nothing_is_marked(spark, deep):
    """Hosts of 1, 2, 7, 8 and many pages: two pages tell the article from menus, notices and footers that vary."""
    rng = random.Random(12 + deep)
    rows, want, page = [], {}, 0
    for host, n in (("two", 2), ("seven", 7), ("eight", 8), ("many", 300 if not deep else 20)):
        for i in range(n):
            html, text = plain_page(rng, i, deep, 3 + i % 4)
            rows.append((page, f"http://{host}.example/{i}", html))
            want[page] = text
            page += 1
    alone, _ = plain_page(rng, 0, deep, 3)
    rows += [(9000, "http://one.example/0", alone), (9001, "http://many.example/x", None), (9002, "http://many.example/y", ""), (9003, None, alone), rows[0], rows[5]]
    frame = spark.createDataFrame(rows, "page_id long, url string, html string").selectExpr("*", "1 as template", "2 as exemplar", "3 as slots", "4 as text")
    got = html_wrapper.extract(spark, frame).collect()
    assert len(got) == len(rows)
    wrong = [r.page_id for r in got if r.page_id in want and r.text != want[r.page_id]]
    assert not wrong
    without = {r.page_id: r.text for r in html_wrapper.extract(spark, frame, html_wrapper.WrapperSettings(pages=10**9)).collect()}
    assert all(without[i] != want[i] for i in want)  # without the template nothing is right
    assert {r.text for r in got if r.page_id in (9001, 9002)} == {""}
    assert {r.text for r in got if r.page_id in (9000, 9003)} == {without[9000]}


def test_tree_matching_is_optimal_on_small_trees():
    def size(a, b, x=0, y=0):
        if a.tags[x] != b.tags[y]:
            return 0
        m = [[0] * (len(b.children[y]) + 1) for _ in range(len(a.children[x]) + 1)]
        for i, u in enumerate(a.children[x], 1):
            for j, v in enumerate(b.children[y], 1):
                m[i][j] = max(m[i - 1][j], m[i][j - 1], m[i - 1][j - 1] + size(a, b, u, v))
        return 1 + m[-1][-1]

    rng = random.Random(2)

    def tree(depth):
        if depth == 0:
            return ""
        return "".join(f"<{t}>{tree(depth - 1)}</{t}>" for t in (rng.choice(["div", "span", "b"]) for _ in range(rng.randint(0, 4))))

    for _ in range(60):
        a, b = html_wrapper.Dom(tree(3)), html_wrapper.Dom(tree(3))
        found = html_wrapper.tree_matching(a, b)
        assert len(found) == size(a, b)
        assert len(set(found.values())) == len(found)


def test_aligned_nodes_are_read_once():
    """Subtrees of one structure are walked child by child, not pair by pair."""
    reads = []

    class Counted(list):
        def __getitem__(self, at):
            reads.append(at)
            return super().__getitem__(at)

    page = html_wrapper.Dom("<div>" + "<p><b>a</b> x<i>y</i></p>" * 30 + "<h1>t</h1></div><ul><li>a</ul>")
    model = html_wrapper.Dom("<div>" + "<p><b>c</b> z<i>w</i></p>" * 30 + "<h1>u</h1></div>")
    page.shape(), page.subtree_sizes()
    page.children = Counted(page.children)
    assert html_wrapper.tree_matching(page, model) == {k: k for k in range(len(model.tags))}
    assert len(reads) <= 2 * len(page.tags)


def test_blanks_inside_a_block_are_one_space():
    import sys

    from cubejoin.llm.html_wrapper import Dom

    blanks = "".join(c for c in map(chr, range(1, sys.maxunicode + 1)) if re.fullmatch(r"\s", c))
    assert [t for _, t, _ in Dom(f"<p>{blanks}a{blanks}&nbsp;b{blanks}</p>").linked_blocks()] == ["a b"]
