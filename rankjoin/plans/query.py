"""Conjunctive queries: text, normal form and families."""

from __future__ import annotations

import re
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_ATOM = re.compile(r"\s*([A-Za-z_]\w*)\s*\(([^()]*)\)\s*")


@dataclass(frozen=True)
class Atom:
    """A relation used once: its name, and a variable or constant for each column."""

    relation: str
    terms: tuple

    @property
    def variables(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(t for t in self.terms if isinstance(t, str)))


@dataclass(frozen=True)
class Constant:
    value: object


@dataclass(frozen=True)
class ConjunctiveQuery:
    """Atoms and the variables that the answers show."""

    atoms: tuple[Atom, ...]
    free: tuple[str, ...] = field(default=())

    @property
    def variables(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(v for a in self.atoms for v in a.variables))

    @property
    def is_full(self) -> bool:
        return set(self.free) == set(self.variables)

    @property
    def has_self_join(self) -> bool:
        return len({a.relation for a in self.atoms}) < len(self.atoms)


def parse(text: str) -> ConjunctiveQuery:
    """`Q(x, z) :- R(x, y), S(y, z)`; numbers and quoted strings are constants; `Q(*)` shows all variables."""
    head, _, body = text.partition(":-")
    if not body:
        raise ValueError("a rule needs ':-'")
    atoms, at = [], 0
    while at < len(body):
        m = _ATOM.match(body, at)
        if not m:
            raise ValueError(f"not an atom: {body[at:]!r}")
        atoms.append(Atom(m[1], tuple(_term(t.strip()) for t in m[2].split(","))))
        at = m.end()
        if at < len(body):
            if body[at] != ",":
                raise ValueError(f"expected a comma: {body[at:]!r}")
            at += 1
    shown = _ATOM.match(head)
    names = [t.strip() for t in shown[2].split(",") if t.strip()] if shown else []
    q = ConjunctiveQuery(tuple(atoms))
    free = q.variables if names == ["*"] else tuple(names)
    if unknown := set(free) - set(q.variables):
        raise ValueError(f"not in the body: {sorted(unknown)}")
    return ConjunctiveQuery(tuple(atoms), free)


def _term(text: str):
    if re.fullmatch(r"-?\d+", text):
        return Constant(int(text))
    if text[:1] in "'\"":
        return Constant(text[1:-1])
    if not re.fullmatch(r"[A-Za-z]\w*", text):
        raise ValueError(f"not a variable or constant: {text!r}")
    return text


def bind(q: ConjunctiveQuery, relations: dict[str, DataFrame], weight: str = "w") -> list[DataFrame]:
    """One frame per atom with a column per variable and `_w`.

    Columns of a relation are taken by position, without its weight column. Constants and repeated
    variables become filters that reach the scan; rows with a null in a variable cannot
    join and go; a self-join is the same plan under other names, so its scan is shared.
    """
    out = []
    for atom in q.atoms:
        df = relations[atom.relation]
        columns = [c for c in df.columns if c != weight]
        if len(columns) != len(atom.terms):
            raise ValueError(f"{atom.relation} has {len(columns)} columns, the query names {len(atom.terms)}")
        first: dict[str, str] = {}
        for column, term in zip(columns, atom.terms, strict=True):
            if isinstance(term, Constant):
                df = df.where(F.col(column) == F.lit(term.value))
            elif term in first:
                df = df.where(F.col(column) == F.col(first[term]))
            else:
                first[term] = column
                df = df.where(F.col(column).isNotNull())
        out.append(df.select(*(F.col(c).alias(v) for v, c in first.items()), F.col(weight).alias("_w")))
    return out


# -- families -------------------------------------------------------------------
def path(length: int, relation: str = "E") -> ConjunctiveQuery:
    """E(x0, x1), E(x1, x2), ..."""
    return _full([(relation, (f"x{i}", f"x{i + 1}")) for i in range(length)])


def alternating(length: int, relation: str = "E") -> ConjunctiveQuery:
    """A path over a graph with two kinds of nodes, walked to and fro: E(x0, x1), E(x2, x1), E(x2, x3), ..."""
    return _full([(relation, (f"x{i}", f"x{i + 1}") if i % 2 == 0 else (f"x{i + 1}", f"x{i}")) for i in range(length)])


def star(length: int, relation: str = "E", hub_first: bool = True) -> ConjunctiveQuery:
    """Atoms that share one variable."""
    return _full([(relation, ("c", f"x{i}") if hub_first else (f"x{i}", "c")) for i in range(length)])


def wide_star(length: int) -> ConjunctiveQuery:
    """One wide atom and an atom at each of its variables."""
    return _full([("R0", tuple(f"c{i}" for i in range(1, length)))] + [(f"R{i}", (f"c{i}", f"x{i}")) for i in range(1, length)])


def branch(length: int, relation: str = "E") -> ConjunctiveQuery:
    """A path with one more atom at its last variable but one: two atoms share what they hang on."""
    return _full([(relation, (f"x{i}", f"x{i + 1}")) for i in range(length - 1)] + [(relation, (f"x{length - 2}", "y"))])


def cycle(length: int, relation: str = "E") -> ConjunctiveQuery:
    return _full([(relation, (f"x{i}", f"x{(i + 1) % length}")) for i in range(length)])


def alternating_cycle(length: int, relation: str = "E", back: str = "B") -> ConjunctiveQuery:
    """A closed walk to and fro over a graph with two kinds of nodes, of even length: E(x0, x1), B(x1, x2), ...; B has E's edges turned round."""
    return _full([((relation, back)[i % 2], (f"x{i}", f"x{(i + 1) % length}")) for i in range(length)])


def product(length: int) -> ConjunctiveQuery:
    """Atoms without a shared variable."""
    return _full([(f"R{i}", (f"x{i}",)) for i in range(length)])


def _full(atoms: list[tuple[str, tuple]]) -> ConjunctiveQuery:
    q = ConjunctiveQuery(tuple(Atom(r, t) for r, t in atoms))
    return ConjunctiveQuery(q.atoms, q.variables)


def boolean(q: ConjunctiveQuery) -> ConjunctiveQuery:
    return ConjunctiveQuery(q.atoms, ())


def endpoints(length: int, relation: str = "E") -> ConjunctiveQuery:
    """The ends of a path: not free-connex from length 2 on."""
    return ConjunctiveQuery(path(length, relation).atoms, ("x0", f"x{length}"))
