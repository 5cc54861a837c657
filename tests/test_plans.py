"""Exact algebra, covers, trees and widths: hand values, the exponents of the worked examples, and invariances."""

import random
from fractions import Fraction as Fr
from itertools import product

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from linform.functions import linalg
from linform.functions.fields import ExtensionField, PrimeField
from linform.plans import covers, trees
from linform.plans.query import ConstrainedQuery, QueryTextError, UnsafeQueryError, constraints_as_atoms, constraints_eliminated, parse_query, to_constrained

SKEW = "Q(X,Y,Z) <- A(X,Y)*B(Y,Z)*C(X+Y,Y+Z)"
TREE4 = "Q(X+Y) <- A(X)*B(Y)*C(Z-X-Y)*D(Z)"
FIVE = "Q(Y+Z) <- R1(W+X,X+Y)*R2(W,X)*R3(X,Y)*R4(Y,Z)*R5(X+Y,Y+Z)"


def ksum(k):
    xs = [f"X{i}" for i in range(1, k + 1)]
    return "Q() <- " + "*".join(f"A{i}({x})" for i, x in enumerate(xs)) + f"*S({'+'.join(xs)})"


@pytest.mark.parametrize(
    ("text", "k", "rho", "dim", "vec", "frac"),
    [
        (SKEW, 3, Fr(3, 2), 2, 2, Fr(3, 2)),
        ("Q() <- R(X,Y)*S(Y,X+Y)", 2, 1, 1, 1, 1),
        (TREE4, 3, 3, 1, 1, 2),
        (ksum(2), 2, 2, 1, 1, 2),
        (ksum(3), 3, 3, 1, 1, 2),
        (ksum(4), 4, 4, 1, 2, 3),
        (ksum(5), 5, 5, 1, 2, 3),
        (FIVE, 4, 2, 2, 2, Fr(3, 2)),
        ("Q(X,Y,Z) <- R(X,Y)*S(Y,Z)*T(X,Z)", 3, Fr(3, 2), 2, 2, Fr(3, 2)),
        ("Q(2X+2Z) <- A(X)*B(Y-X,Z-Y)*C(Z)", 3, 2, 1, 1, 2),
        ("Q(I,J) <- A(I+L,J+K)*P(L,K)", 4, 2, 3, 3, 2),
        ("Q() <- R(X,Y)*S(Y,Z)", 3, 2, 1, 1, 1),
        ("Q() <- E(A,B,X)*E(B,C,Y)*E(C,D,-X-Y)", 6, 2, 3, 3, 2),
    ],
)
def test_exponents_of_the_examples(text, k, rho, dim, vec, frac):
    q = parse_query(text)
    assert q.dim == k and covers.cover_number(q).value == rho
    assert trees.widths(q) == {"dim": dim, "vec": vec, "frac": frac}


def test_text_and_errors():
    q = parse_query("Q(2X+2Z) <- A(X)*B(Y-X,Z-Y)*C(Z)")
    assert str(q) == "Q(2X+2Z) <- A(X)*B(Y-X,Z-Y)*C(Z)" or parse_query(str(q), variables=q.variables) == q
    assert parse_query("Q() <- R(1/2X - 3*Y, 0)").atoms[0].forms == ((Fr(1, 2), Fr(-3)), (0, 0))
    for bad in ("Q(X) A(X)", "Q(X) <- A(X+3)", "Q(X) <- A(X Y)", "Q(X) <- A", "Q() <- A(+)"):
        with pytest.raises(QueryTextError):
            parse_query(bad)
    with pytest.raises(UnsafeQueryError):
        parse_query("Q(X) <- R(X+Y)").check_safe()
    assert parse_query("Q(X+Y) <- R(X+Y)").check_safe().normalize().width == 1
    assert parse_query("Q(X) <- R(X,Y)*S(Y)").is_plain() and not parse_query(SKEW).is_plain()
    assert parse_query("Q() <- R(X+Y,Y)").is_independent() and not parse_query(SKEW).is_independent()
    with pytest.raises(ValueError, match="injective"):
        parse_query("Q() <- R(X,Y)").substitute([(Fr(1),), (Fr(1),)])


def test_skew_triangle_becomes_a_triangle():
    q = parse_query(SKEW)
    c = covers.cover_number(q)
    assert c.weights == (Fr(1, 2),) * 3 and set(c.index_sets) == {frozenset(x) for x in ((0, 1), (0, 2), (1, 2))}
    assert covers.is_cover(q, q.span(), (1, 1, 0)) and not covers.is_cover(q, q.span(), (Fr(1, 2), Fr(1, 2), 0))
    assert covers.given_cover(q, (1, 1, 0)).value == 2


def test_five_atoms_intersections():
    q = parse_query(FIVE)
    sets = dict(covers.closures(q))
    v = {x: tuple(Fr(int(x == y)) for y in q.variables) for x in q.variables}
    add = lambda a, b: tuple(x + y for x, y in zip(v[a], v[b], strict=True))
    for s, form in (({0, 1}, add("W", "X")), ({1, 2}, v["X"]), ({0, 2, 4}, add("X", "Y")), ({2, 3}, v["Y"]), ({3, 4}, add("Y", "Z"))):
        assert linalg.space_key(list(sets[frozenset(s)])) == linalg.space_key([form])


@settings(max_examples=60, deadline=None)
@given(st.integers(0, 10**9))
def test_invariances(seed):
    rng = random.Random(seed)
    d = rng.randrange(1, 4)
    form = lambda: tuple(Fr(rng.randrange(-1, 3)) for _ in range(d))
    from linform.plans.query import Atom, LinearQuery

    atoms = tuple(Atom(f"R{i}", tuple(form() for _ in range(rng.randrange(1, 3)))) for i in range(rng.randrange(1, 4)))
    q = LinearQuery(tuple("XYZ"[:d]), (), atoms)
    # a unimodular change of variables keeps all measures
    m = [[Fr(int(i == j)) for j in range(d)] for i in range(d)]
    for _ in range(4):
        i, j = rng.randrange(d), rng.randrange(d)
        if i != j:
            t = rng.randrange(-2, 3)
            m[i] = [a + t * b for a, b in zip(m[i], m[j], strict=True)]
    moved = q.substitute([tuple(r) for r in m])
    assert covers.cover_number(q).value == covers.cover_number(moved).value
    w = trees.widths(q)
    assert w == trees.widths(moved) and w["dim"] <= w["vec"]
    for kind in w:
        t = trees.find_tree(q, kind).validate(q)
        low = t.minimize(q)
        assert low.minimize(q) == low and all(linalg.contains(list(b), list(s)) for b, s in zip(t.bags, low.bags, strict=True))
        for n in trees.factorize(q, low):
            assert linalg.space_key(n.query.body or []) == linalg.space_key(list(low.bags[n.node]))
    spanned = [f for f in q.span()]
    assert len(covers.vector_cover(q, spanned)) == len(spanned)
    c = to_constrained(q)
    assert c.query.is_plain() or any(not any(f) for a in q.atoms for f in a.forms)
    assert constraints_eliminated(c).dim == q.dim == constraints_as_atoms(c).dim - len(c.equations) + (len(c.equations) - linalg.rank(list(c.equations)) if c.equations else 0)


def test_plain_queries_have_classical_measures():
    rng = random.Random(3)
    for _ in range(40):
        atoms = [set(rng.sample("XYZW", rng.randrange(1, 4))) for _ in range(rng.randrange(1, 5))]
        used = set().union(*atoms)
        q = parse_query("Q() <- " + "*".join(f"R{i}({','.join(sorted(a))})" for i, a in enumerate(atoms)))
        assert covers.cover_number(q).value == covers.plain_cover_number(atoms, used)
        w = trees.widths(q)
        assert w["dim"] == w["vec"]


def test_covering_program_against_corner_search():
    rng = random.Random(8)
    for _ in range(60):
        m = rng.randrange(1, 4)
        sets = [frozenset(rng.sample(range(m), rng.randrange(1, m + 1))) for _ in range(rng.randrange(1, 4))]
        value, w = covers.covering_program(sets, [Fr(1)] * m)
        assert all(sum(w[i] for i in s) >= 1 for s in sets) and sum(w) == value
        grid = [Fr(i, 6) for i in range(7)]
        assert value <= min(sum(x) for x in product(grid, repeat=m) if all(sum(x[i] for i in s) >= 1 for s in sets))


def test_trees_by_hand():
    q = parse_query(TREE4)
    t = trees.find_tree(q, "dim")
    assert len(t.parent) == 2 and [sorted(c) for c in t.covers] in ([[0, 1], [2, 3]], [[0, 1], [3, 2]])
    assert linalg.space_key(t.interface(q, 1)) == linalg.space_key([q.head[0]])
    with pytest.raises(ValueError):
        trees.assign(q, [None, 0], [[q.atoms[0].forms[0], q.atoms[1].forms[0]], [q.atoms[3].forms[0], q.atoms[0].forms[0]]])
    sub, rest = trees.factor_once(q, [2, 3])
    assert linalg.space_key(list(sub.head)) == linalg.space_key([q.head[0]]) and rest.atoms[-1].name == trees.message(1)
    p = parse_query("Q() <- R(X,Y)*S(Y,Z)")
    c = trees.from_classical(p, [None, 0], [{"X", "Y"}, {"Y", "Z"}])
    assert trees.tree_width(p, c, "dim") == 1
    for k in (2, 3, 4, 5):
        q = parse_query(ksum(k))
        chain = trees.sum_chain(q)
        assert trees.tree_width(q, chain, "dim") == 1 and trees.tree_width(q, chain, "vec") == -(-(k + 1) // 2) - 1
    many = parse_query("Q() <- " + "*".join(f"R{i}(X{i},X{i + 1})" for i in range(9)))
    trees.find_tree(many, "dim")


def test_fields():
    for f in (PrimeField(7), ExtensionField(2, 2), ExtensionField(3, 2)):
        els = range(f.order)
        for a in els:
            assert f.add(a, f.neg(a)) == 0 and (a == 0 or f.mul(a, f.inv(a)) == 1)
            for b in els:
                assert f.mul(a, b) == f.mul(b, a)
                assert all(f.mul(a, f.add(b, c)) == f.add(f.mul(a, b), f.mul(a, c)) for c in els)
    g = ExtensionField(2, 4)
    assert g.subfield_degree([0, 1]) == 1 and g.subfield_degree([2]) == 4
    assert sum(g.subfield_degree([a]) == 2 for a in range(16)) == 2
    q = parse_query("Q() <- R(X+Y)*S(X-Y)", PrimeField(2))
    assert q.dim == 1 and parse_query("Q() <- R(X+Y)*S(X-Y)").dim == 2


def test_constraints():
    q = parse_query("Q() <- R(X,Y)*S(Y,Z)")
    c = ConstrainedQuery(q, ((Fr(1), Fr(1), Fr(-1)),))
    e = constraints_eliminated(c)
    assert covers.cover_number(e).value == 1 and e.dim == 2 and len(constraints_as_atoms(c).atoms) == 3
