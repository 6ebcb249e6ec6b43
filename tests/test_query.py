import json

import pytest

from cubejoin.query import Atom, ConjunctiveQuery, fold_predicates, parse_rule, query_from_json, query_to_json


def test_parse_rule_and_json_agree(tmp_path):
    query = parse_rule("Q(x, y, z) :- R(x, y), S(y, z), T(x, z)")
    assert query.head == ("x", "y", "z")
    assert [a.relation for a in query.atoms] == ["R", "S", "T"]
    path = tmp_path / "q.json"
    path.write_text(query_to_json(query))
    assert query_from_json(str(path)) == query
    assert query_from_json(json.dumps({"head": ["x"], "atoms": [{"relation": "R", "vars": ["x"]}]})).head == ("x",)


def test_constants_and_strings():
    query = parse_rule("Q(x) :- R(x, 3, 'a')")
    assert query.atoms[0].constants == {1: 3, 2: "a"}


@pytest.mark.parametrize("rule", ["Q(x, y) :- R(x, z)", "Q(x) R(x)", "Q(x, x) :- R(x, x)", "Q(x) :- R(x, y)"])
def test_bad_rules(rule):
    with pytest.raises(ValueError):
        parse_rule(rule)


def test_fold(spark):
    frame = spark.createDataFrame([(1, 1, 3), (1, 2, 3), (2, 2, 4), (5, 5, 3)], "a long, b long, c long")
    query = ConjunctiveQuery(("x",), (Atom("R", ("x", "x"), {2: 3}),), ((("x",), lambda x: x < 5),))
    folded, frames = fold_predicates(query, {"R": frame})
    assert [r.x for r in frames["r0"].collect()] == [1]
    assert not folded.filters
    with pytest.raises(ValueError):
        fold_predicates(parse_rule("Q(x) :- R(x)"), {"R": frame})
    with pytest.raises(ValueError):
        fold_predicates(parse_rule("Q(x) :- S(x)"), {"R": frame})
