"""Full conjunctive queries: the model, its parsers and predicate folding."""

from __future__ import annotations

import json
import re
from collections.abc import Callable, Mapping, Sequence
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

Filter = Callable[..., Column]


@dataclass(frozen=True)
class Atom:
    """A relation over variables.  ``constants`` fixes positions; a variable may repeat."""

    relation: str
    vars: tuple[str, ...]
    constants: Mapping[int, object] = field(default_factory=dict)

    def distinct_vars(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(self.vars))


@dataclass(frozen=True)
class ConjunctiveQuery:
    """Head (all variables) and atoms; ``filters`` are (variables, condition) pairs.

    A condition takes one Column per variable.  Unknown variables, head
    variables without an atom and atoms without variables raise ValueError.
    """

    head: tuple[str, ...]
    atoms: tuple[Atom, ...]
    filters: tuple[tuple[tuple[str, ...], Filter], ...] = ()

    def __post_init__(self):
        object.__setattr__(self, "head", tuple(self.head))
        object.__setattr__(self, "atoms", tuple(self.atoms))
        self.validate()

    def validate(self) -> None:
        if not self.atoms:
            raise ValueError("a query needs an atom")
        used = {v for a in self.atoms for v in a.vars}
        if len(set(self.head)) != len(self.head):
            raise ValueError("a head variable is repeated")
        for v in self.head:
            if v not in used:
                raise ValueError(f"variable {v} is in no atom")
        for v in sorted(used):
            if v not in self.head:
                raise ValueError(f"variable {v} is not in the head")
        for vs, _ in self.filters:
            for v in vs:
                if v not in used:
                    raise ValueError(f"filter on unknown variable {v}")

    @property
    def scopes(self) -> list[tuple[str, ...]]:
        """Distinct variables of each atom."""
        return [a.distinct_vars() for a in self.atoms]


_ATOM = re.compile(r"\s*([A-Za-z_]\w*)\s*\(([^()]*)\)\s*")
_CONSTANT = re.compile(r"-?\d+$|'[^']*'$")


def _parse_atom(text: str) -> Atom:
    m = _ATOM.fullmatch(text)
    if not m:
        raise ValueError(f"not an atom: {text!r}")
    names, constants = [], {}
    for at, term in enumerate(x.strip() for x in m[2].split(",")):
        if _CONSTANT.match(term):
            constants[at] = term[1:-1] if term[0] == "'" else int(term)
        elif re.fullmatch(r"[A-Za-z_]\w*", term):
            names.append(term)
        else:
            raise ValueError(f"not a term: {term!r}")
    return Atom(m[1], tuple(names), constants)


def parse_rule(text: str) -> ConjunctiveQuery:
    """``Q(x, y) :- R(x, y), S(y, 3)`` as a query."""
    head, arrow, body = text.partition(":-")
    if not arrow:
        raise ValueError("a rule needs ':-'")
    atoms = [_parse_atom(part) for part in re.findall(r"[^,()]+\([^()]*\)", body)]
    return ConjunctiveQuery(_parse_atom(head).vars, tuple(atoms))


def query_from_json(source: str) -> ConjunctiveQuery:
    """A query from JSON text or a path to it: {"head": [...], "atoms": [{"relation", "vars", "constants"}]}."""
    text = source
    if not source.lstrip().startswith("{"):
        with open(source, encoding="utf-8") as f:
            text = f.read()
    spec = json.loads(text)
    atoms = [Atom(a["relation"], tuple(a["vars"]), {int(k): v for k, v in a.get("constants", {}).items()}) for a in spec["atoms"]]
    return ConjunctiveQuery(tuple(spec["head"]), tuple(atoms))


def query_to_json(query: ConjunctiveQuery) -> str:
    if query.filters:
        raise ValueError("filters have no JSON form")
    return json.dumps({"head": list(query.head), "atoms": [{"relation": a.relation, "vars": list(a.vars), "constants": {str(k): v for k, v in a.constants.items()}} for a in query.atoms]})


def fold_predicates(query: ConjunctiveQuery, relations: Mapping[str, DataFrame]) -> tuple[ConjunctiveQuery, dict[str, DataFrame]]:
    """An equal query without constants, repeated variables or one-atom filters, and its relations.

    Atom j reads relation ``r<j>`` whose columns are its variables: constants
    and repeated variables become filters below the projection (Catalyst pushes
    them to the scan), filters whose variables lie in an atom are applied there,
    and rows with a null in a variable that several atoms share are dropped.
    """
    shared = {v for v in query.head if sum(v in a.vars for a in query.atoms) > 1}
    out: dict[str, DataFrame] = {}
    atoms, left = [], []
    applied: set[int] = set()
    for j, atom in enumerate(query.atoms):
        if atom.relation not in relations:
            raise ValueError(f"unknown relation {atom.relation}")
        frame = relations[atom.relation]
        width = len(atom.vars) + len(atom.constants)
        if len(frame.columns) != width:
            raise ValueError(f"{atom.relation} has {len(frame.columns)} columns, its atom {width} terms")
        names = iter(atom.vars)
        first: dict[str, str] = {}
        for at, column in enumerate(frame.columns):
            if at in atom.constants:
                frame = frame.where(F.col(f"`{column}`") == F.lit(atom.constants[at]))
                continue
            v = next(names)
            if v in first:
                frame = frame.where(F.col(f"`{first[v]}`") == F.col(f"`{column}`"))
            else:
                first[v] = column
        frame = frame.select(*(F.col(f"`{c}`").alias(v) for v, c in first.items()))
        for v in first:
            if v in shared:
                frame = frame.where(F.col(v).isNotNull())
        for k, (vs, condition) in enumerate(query.filters):
            if set(vs) <= set(first):
                frame = frame.where(condition(*(F.col(v) for v in vs)))
                applied.add(k)
        out[f"r{j}"] = frame
        atoms.append(Atom(f"r{j}", tuple(first)))
    left = [f for k, f in enumerate(query.filters) if k not in applied]
    return ConjunctiveQuery(query.head, tuple(atoms), tuple(left)), out


def check_order(query: ConjunctiveQuery, order: Sequence[str]) -> tuple[str, ...]:
    if sorted(order) != sorted(query.head):
        raise ValueError(f"{tuple(order)} is no permutation of {query.head}")
    return tuple(order)
