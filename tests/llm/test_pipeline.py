import functools
import re

import corpus_pipeline
import pytest
from pyspark.sql import functions as F

from cubejoin.llm import bpe_codec

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="module")
def given(spark, tmp_path_factory):
    """A corpus of planted cases, and what each stage must keep of it."""
    folder = str(tmp_path_factory.mktemp("planted"))
    item = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu"
    spark.createDataFrame([("a", item), ("b", None), (None, "x")], "item_id string, text string").coalesce(1).write.parquet(f"{folder}/benchmark.parquet")
    words = lambda k, n=60: " ".join(f"{'stu'[k % 3]}{'abcdefghij'[k // 3 % 10]}{'klmnopqrst'[j % 10]}{'uvwxyzabcd'[j // 10]}" for j in range(n))
    rows = [(i, words(i), "en", "s", len(words(i))) for i in range(30)]
    rows += [(100, words(0) + " end", "en", "s", 1), (101, words(0), "en", "s", 1), (None, words(0), "en", "s", 1), (7, words(7), "en", "s", 1)]  # copies and a repeated row
    rows += [(200, f"{words(1, 20)} {item} {words(2, 20)}", "en", "s", 1), (7, f"so {item.upper()}", "en", "s", 1)]
    rows += [(300, "write to some.one@example.org or 10.0.0.1 please", "en", "s", 1), (None, "only this +1 (555) 010-2030 number", "en", "s", 1), (None, "only clean words in this one", "en", "s", 1)]
    rows += [(400, None, "en", "s", 0), (401, "", "en", "s", 0), (402, "123 !!", "en", "s", 6), (None, None, None, None, None), (403, "word " * 9000, "en", "s", 1)]
    docs = spark.createDataFrame(rows, DOCS).selectExpr("*", "1 as found", "2 as xd", "3 as of_doc", "4 as text_key", "5 as score", "6 as doc", "8 as group_id")
    docs.coalesce(2).write.parquet(f"{folder}/documents.parquet")
    return folder, rows


def texts(frame):
    return sorted(((r.doc_id, r.text) for r in frame.collect()), key=str)


def brute(rows):
    """(doc_id, text) after each of the first four stages, by Python."""
    kept = [(i, t) for i, t, *_ in rows if t and any(c.isalpha() for c in t)]
    stages = [sorted(kept, key=str)]

    @functools.cache
    def shingles(t):
        w = t.lower().split()
        return {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))}

    groups: list[list] = []
    for row in dict.fromkeys(kept):
        near = [g for g in groups if any(len(shingles(row[1]) & shingles(o[1])) * 100 >= 80 * len(shingles(row[1]) | shingles(o[1])) for o in g)]
        groups = [g for g in groups if g not in near] + [[row, *(o for g in near for o in g)]]
    kept = [min(g, key=lambda o: (o[0] is None, o[0] or 0)) for g in groups]
    stages.append(sorted(kept, key=str))
    kept = [o for o in kept if "alpha beta gamma delta epsilon zeta eta theta iota kappa" not in o[1].lower()]
    stages.append(sorted(kept, key=str))
    hidden = [("some.one@example.org", "<email>"), ("10.0.0.1", "<ip>"), ("+1 (555) 010-2030", "<phone>")]
    for a, b in hidden:
        kept = [(i, t.replace(a, b)) for i, t in kept]
    stages.append(sorted(kept, key=str))
    return stages


def test_stages_and_run_match_brute_force(spark, given):
    folder, rows = given
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["language_id", "minhash_near_dedup", "benchmark_decontamination", "pii_redaction", "bpe_round_trip"]
    wanted = brute(rows)
    for want, (name, stage) in zip(wanted, corpus_pipeline.STAGES, strict=False):
        out = stage(spark, docs, folder)
        assert out.columns == docs.columns and texts(out) == want, name
        out.write.mode("overwrite").parquet(f"{folder}/{name}")
        docs = spark.read.schema(docs.schema).parquet(f"{folder}/{name}")
    assert docs.where("n_chars <> char_length(text)").count() == 0
    final = corpus_pipeline.run(spark, folder)
    codec = bpe_codec.codec(corpus_pipeline.vocabulary_path())
    assert sorted(((r.doc_id, r.n_tokens) for r in final.collect()), key=str) == sorted(((i, len(codec.encode(t))) for i, t in wanted[-1]), key=str)


def test_empty_table(spark, given, tmp_path):
    folder, _ = given
    docs = spark.read.parquet(f"{folder}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, folder).count() == 0


def test_redaction_of_given_documents(spark, tiny):
    docs = spark.read.parquet(f"{tiny}/documents.parquet")
    hidden = texts(corpus_pipeline.pii_redaction(spark, docs, tiny))
    assert len(hidden) == docs.count()
    assert not any(re.search(r"[a-z0-9.]+@[a-z0-9-]+\.[a-z]+", t or "") for _, t in hidden)
    clean = {r.doc_id: r.text for r in docs.where(~F.col("text").rlike("[0-9@]")).collect()}
    assert clean and all(t == clean[i] for i, t in hidden if i in clean)
