import sys

import __spark_entry__ as entry


def test_names_and_oracles():
    names = entry.queries()
    assert len(names) > 80
    assert set(entry.oracle_sql()) <= set(names)
    assert all(callable(f) for f in names.values())


def test_corpus_part_is_optional(monkeypatch):
    monkeypatch.setitem(sys.modules, "corpus_pipeline", None)  # importing it now fails
    names = entry.queries()
    assert not any(n.startswith("op") for n in names) and "pipeline" not in names and "q1d_custord" in names
    assert set(entry.oracle_sql()) <= set(names)


def test_flagship(spark):
    assert entry.entry(spark).columns == ["x", "y", "z"]
