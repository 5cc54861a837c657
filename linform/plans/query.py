"""Queries with linear forms: representation, text form, span, changes of variables, constraints.

A form is a vector of coefficients over the query's variables. A query sums, over the classes of variable
values that its forms can tell apart, the product of its atoms, and groups the sums by the values of the head.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, replace
from fractions import Fraction
from math import lcm

from linform.functions import linalg
from linform.functions.fields import Q

Form = tuple


class UnsafeQueryError(ValueError):
    """A head form is not determined by the body."""


class QueryTextError(ValueError):
    pass


@dataclass(frozen=True)
class Atom:
    name: str
    forms: tuple[Form, ...]


@dataclass(frozen=True)
class LinearQuery:
    variables: tuple[str, ...]
    head: tuple[Form, ...]
    atoms: tuple[Atom, ...]
    field: object = Q

    @property
    def width(self) -> int:
        return len(self.variables)

    @property
    def body(self) -> list[Form]:
        """Distinct body forms that are not zero, in order."""
        return [f for f in dict.fromkeys(f for a in self.atoms for f in a.forms) if any(f)]

    def span(self) -> list[Form]:
        return linalg.rref(self.body, self.field)[0]

    @property
    def dim(self) -> int:
        return len(self.span())

    def null_space(self) -> list[Form]:
        """Changes of variable values that no form notices."""
        return linalg.null_basis(self.body, self.width, self.field)

    def check_safe(self) -> LinearQuery:
        for f in self.head:
            if not linalg.contains(self.body, [f], self.field):
                raise UnsafeQueryError(f"the body does not determine {self.show(f)}")
        return self

    def is_plain(self) -> bool:
        """Every form is one variable."""
        one = self.field.of(1)
        return all(sum(map(bool, f)) == 1 and one in f for f in [*self.body, *self.head]) and all(any(f) for a in self.atoms for f in a.forms)

    def is_independent(self) -> bool:
        return linalg.rank(self.body, self.field) == len(self.body)

    def substitute(self, images: list[Form], variables: tuple[str, ...] | None = None) -> LinearQuery:
        """Replace variable i by the form images[i] over new variables; the map must be one-to-one on the span."""
        width = len(images[0]) if images else 0
        move = lambda f: linalg.combine(f, list(images), width, self.field)
        if linalg.rank([move(f) for f in self.span()], self.field) < self.dim:
            raise ValueError("the change of variables is not injective on the span")
        names = variables or tuple(f"V{i}" for i in range(width))
        return LinearQuery(names, tuple(map(move, self.head)), tuple(Atom(a.name, tuple(map(move, a.forms))) for a in self.atoms), self.field)

    def over_basis(self, basis: list[Form]) -> LinearQuery:
        """The query rewritten so that variable i stands for basis[i]; the basis must span all forms."""

        def move(f: Form) -> Form:
            found = linalg.coordinates(f, basis, self.field)
            if found is None:
                raise ValueError("the basis does not span the query")
            return found

        return LinearQuery(tuple(f"V{i}" for i in range(len(basis))), tuple(map(move, self.head)), tuple(Atom(a.name, tuple(map(move, a.forms))) for a in self.atoms), self.field)

    def normalize(self) -> LinearQuery:
        """The equivalent query with as many variables as the span has dimensions."""
        self.check_safe()
        return self if self.dim == self.width else self.over_basis([self.body[i] for i in linalg.independent(self.body, self.field)])

    def to_plain(self) -> LinearQuery:
        """An independent query with each form as a variable."""
        if not self.is_independent():
            raise ValueError("the body forms are dependent")
        return self.check_safe().over_basis(self.body)

    def show(self, f: Form) -> str:
        parts = []
        for c, v in zip(f, self.variables, strict=True):
            if c:
                sign = "-" if c < 0 else "+" if parts else ""
                size = "" if abs(c) == 1 else f"{abs(c)}"
                parts.append(f"{sign}{size}{v}")
        return "".join(parts) or "0"

    def __str__(self) -> str:
        args = lambda forms: ",".join(map(self.show, forms))
        return f"Q({args(self.head)}) <- " + "*".join(f"{a.name}({args(a.forms)})" for a in self.atoms)


_TERM = re.compile(r"\s*([+-]?)\s*(?:(\d+(?:/\d+)?)\s*\*?\s*)?([A-Za-z_]\w*)?\s*")


def parse_form(text: str) -> dict[str, Fraction]:
    out: dict[str, Fraction] = {}
    at = 0
    while at < len(text):
        m = _TERM.match(text, at)
        if not m or m.end() == at or not (m[2] or m[3]) or (at and not m[1]):
            raise QueryTextError(f"cannot read the form {text!r}")
        c = Fraction(m[2] or 1) * (-1 if m[1] == "-" else 1)
        if m[3]:
            out[m[3]] = out.get(m[3], Fraction(0)) + c
        elif c:
            raise QueryTextError(f"forms have no constants: {text!r}")
        at = m.end()
    return out


def _split(text: str, at: str) -> list[str]:
    """Split at a sign outside parentheses."""
    out, depth, start = [], 0, 0
    for i, c in enumerate(text):
        depth += (c == "(") - (c == ")")
        if c == at and not depth:
            out.append(text[start:i])
            start = i + 1
    return [*out, text[start:]]


def parse_query(text: str, field=Q, variables: tuple[str, ...] | None = None) -> LinearQuery:
    """From text such as Q(2X+2Z) <- A(X)*B(Y-X,Z-Y)*C(Z)."""
    head, arrow, body = text.partition("<-")
    if not arrow:
        raise QueryTextError("no <- in the query")
    parsed = []
    for part in (head, *_split(body, "*")):
        m = re.fullmatch(r"\s*(\w+)\s*\((.*)\)\s*", part, re.DOTALL)
        if not m:
            raise QueryTextError(f"cannot read {part!r}")
        parsed.append((m[1], [parse_form(x.strip()) for x in _split(m[2], ",")] if m[2].strip() else []))
    names = variables or tuple(dict.fromkeys(v for _, forms in parsed for f in forms for v in f))
    vector = lambda f: tuple(field.of(f.get(v, 0)) for v in names)
    atoms = tuple(Atom(n, tuple(map(vector, forms))) for n, forms in parsed[1:])
    return LinearQuery(names, tuple(map(vector, parsed[0][1])), atoms, field)


def integral(v: Form) -> tuple[Form, int]:
    """The least multiple of a rational vector with whole coefficients, and the factor."""
    den = lcm(*(x.denominator for x in v)) if v else 1
    return tuple(x * den for x in v), den


# ---- constrained plain queries ------------------------------------------------------------------------------


@dataclass(frozen=True)
class ConstrainedQuery:
    """A query and homogeneous linear equations between its variables."""

    query: LinearQuery
    equations: tuple[Form, ...]


UNIT = "_zero"


def constraints_as_atoms(c: ConstrainedQuery) -> LinearQuery:
    """Each equation becomes an atom over the relation UNIT, which holds the value 0 only."""
    return replace(c.query, atoms=(*c.query.atoms, *(Atom(UNIT, (e,)) for e in c.equations)))


def constraints_eliminated(c: ConstrainedQuery) -> LinearQuery:
    """The equations are solved, and their pivot variables replaced; no relation is added."""
    q = c.query
    solved, pivots = linalg.rref(list(c.equations), q.field)
    free = [i for i in range(q.width) if i not in pivots]
    images = []
    for i in range(q.width):
        if i in pivots:
            row = solved[pivots.index(i)]
            images.append(tuple(q.field.neg(row[j]) for j in free))
        else:
            images.append(tuple(q.field.of(int(i == j)) for j in free))
    move = lambda f: linalg.combine(f, images, len(free), q.field)
    return LinearQuery(tuple(q.variables[i] for i in free), tuple(map(move, q.head)), tuple(Atom(a.name, tuple(map(move, a.forms))) for a in q.atoms), q.field)


def to_constrained(q: LinearQuery) -> ConstrainedQuery:
    """The inverse view: a variable for each argument of each atom, and equations for their dependencies."""
    q.check_safe()
    slots = [(i, j) for i, a in enumerate(q.atoms) for j in range(len(a.forms))]
    forms = [q.atoms[i].forms[j] for i, j in slots]
    unit = lambda s: tuple(q.field.of(int(s == t)) for t in range(len(slots)))
    atoms, s = [], 0
    for a in q.atoms:
        atoms.append(Atom(a.name, tuple(unit(s + j) for j in range(len(a.forms)))))
        s += len(a.forms)
    base = linalg.independent(forms, q.field)
    head = []
    for f in q.head:
        c = linalg.coordinates(f, [forms[i] for i in base], q.field)
        row = [q.field.of(0)] * len(slots)
        for i, x in zip(base, c, strict=True):
            row[i] = x
        head.append(tuple(row))
    plain = LinearQuery(tuple(f"S{i}_{j}" for i, j in slots), tuple(head), tuple(atoms), q.field)
    return ConstrainedQuery(plain, tuple(linalg.dependencies(forms, q.field)))
