"""All evaluators against brute force: the worked examples, random queries, semirings, fields, edge cases."""

import random
from fractions import Fraction as Fr
from itertools import product

import pytest

from linform.functions import semirings as S
from linform.functions.fields import ExtensionField, PrimeField
from linform.operators import evaluate as E
from linform.operators import reducts as R
from linform.operators.relation import AnnotatedRelation as Rel
from linform.operators.relation import Database
from linform.plans import covers, trees
from linform.plans.query import Atom, LinearQuery, UnsafeQueryError, parse_query

BAG = {6: 27, 10: 108, 14: 180}


def bag(spark, semiring=S.COUNT):
    a = [(1, 1), (2, 3), (3, 4), (4, 5)]
    b = [(-1, 0, 1), (0, -1, 5), (0, 1, 3)]
    return Database({"A": Rel.of_rows(spark, a, 1, semiring), "B": Rel.of_rows(spark, b, 2, semiring), "C": Rel.of_rows(spark, a, 1, semiring)}, semiring)


def rows(df):
    return {tuple(r)[:-1]: r.ann for r in df.collect()}


def test_bag_example(spark):
    db = bag(spark)
    q = parse_query("Q(2X+2Z) <- A(X)*B(Y-X,Z-Y)*C(Z)")
    moved = parse_query("Q(4U+2V+2W) <- A(U)*B(V,W)*C(U+V+W)")
    for name, run in E.EVALUATORS.items():
        assert rows(run(q, db)) == {(k,): v for k, v in BAG.items()}, name
        assert rows(run(moved, db)) == {(k,): v for k, v in BAG.items()}, name
    for join in ("levelwise", "hypercube", "hypercube_frames", "binary"):
        assert rows(E.eval_sparse(q, db, join=join)) == {(k,): v for k, v in BAG.items()}
    assert rows(E.eval_dense(q, db, guard_atoms=[0, 1])) == {(k,): v for k, v in BAG.items()}
    # adding a guard as an atom changes nothing, and reducts do not exceed their relations
    guard = E.sparse_guard(q, db, covers.cover_number(q))
    for a in q.atoms:
        guard = R.restrict_to(guard, a, db[a.name], q.field)
    assert rows(E.eval_guarded(q, guard, db)) == {(k,): v for k, v in BAG.items()} and guard.df.count() == 9


def slow(q, data, field):
    """Sums over all combinations of tuples whose linear system is consistent, by elimination."""
    from linform.functions import linalg

    forms = [f for a in q.atoms for f in a.forms]
    base = linalg.independent(forms, field)
    deps = linalg.dependencies(forms, field)
    out = {}
    for combo in product(*(data[a.name].items() for a in q.atoms)):
        values = [x for key, _ in combo for x in key]
        dot = lambda c, v: __import__("functools").reduce(field.add, (field.mul(a, field.of(b)) for a, b in zip(c, v, strict=True)), field.of(0))
        if any(dot(d, values) for d in deps):
            continue
        head = tuple(dot(linalg.coordinates(f, [forms[i] for i in base], field), [values[i] for i in base]) for f in q.head)
        ann = 1
        for _, x in combo:
            ann *= x
        out[head] = out.get(head, 0) + ann
    return {k: v for k, v in out.items() if v}


def values(df, n):
    out = {}
    for r in df.collect():
        d = r.asDict()
        out[tuple(Fr(d[f"h{i}"], d.get(f"h{i}_den", 1)) for i in range(n))] = r.ann
    return out


@pytest.mark.parametrize("seed", range(8))
def test_random_queries(spark, seed):
    rng = random.Random(seed)
    d = rng.randrange(1, 4)
    form = lambda: tuple(Fr(rng.randrange(-1, 3)) for _ in range(d))
    m = rng.randrange(2, 5)
    atoms = tuple(Atom(f"R{i % 3}", tuple(form() for _ in range(1 + i % 2))) for i in range(m))
    atoms = tuple(Atom(a.name, a.forms[: {"R0": 1, "R1": 2, "R2": 1}[a.name]] + tuple(form() for _ in range({"R0": 1, "R1": 2, "R2": 1}[a.name] - len(a.forms)))) for a in atoms)
    body = [f for a in atoms for f in a.forms]
    head = tuple(tuple(x + y for x, y in zip(rng.choice(body), rng.choice(body), strict=True)) for _ in range(rng.randrange(0, 3)))
    q = LinearQuery(tuple("XYZ"[:d]), head, atoms)
    data = {n: {tuple(rng.randrange(-3, 4) for _ in range(k)): rng.choice([-2, -1, 1, 2]) for _ in range(6)} for n, k in (("R0", 1), ("R1", 2), ("R2", 1))}
    db = Database({n: Rel.of_rows(spark, [(*k, v) for k, v in x.items()], len(next(iter(x)))) for n, x in data.items()})
    want = slow(q, data, q.field)
    for name, run in E.EVALUATORS.items():
        if name != "grid" or q.dim <= 2:
            assert values(run(q, db, drop_zero=True), len(head)) == want, (name, str(q))
    assert values(E.eval_sparse(q, db, by_size=True, drop_zero=True), len(head)) == want


def test_head_without_forms_and_empty_relations(spark):
    db = bag(spark)
    q = parse_query("Q() <- A(X)*C(X+X)")
    none = Database({"A": Rel.of_rows(spark, [(1, 1)], 1), "C": Rel.of_rows(spark, [], 1)})
    for name, run in E.EVALUATORS.items():
        assert [tuple(r) for r in run(q, db).collect()] == [(1 * 3 + 3 * 5,)], name
        assert [tuple(r) for r in run(q, none).collect()] == [(0,)], name
        assert run(q, none, drop_zero=True).count() == 0, name
    assert run(parse_query("Q(X) <- A(X)*C(X)"), none).count() == 0
    with pytest.raises(UnsafeQueryError):
        E.eval_dense(parse_query("Q(X) <- A(X+Y)"), db)
    assert rows(E.eval_sparse(parse_query("Q() <- A(X+Y)"), db)) == {(): 13}
    half = E.eval_dense(parse_query("Q(1/2X) <- A(X)"), db).collect()
    assert {(r.h0, r.h0_den): r.ann for r in half} == {(1, 2): 1, (2, 2): 3, (3, 2): 4, (4, 2): 5}


def test_semirings(spark):
    rng = random.Random(2)
    text = "Q(X+Y) <- A(X)*B(Y)*C(Z-X-Y)*D(Z)"
    q = parse_query(text)
    data = {n: {rng.randrange(8): rng.randrange(1, 9) for _ in range(5)} for n in "ABCD"}
    ops = {
        "sum": (S.COUNT, lambda x, y: x + y, lambda x, y: x * y),
        "big": (S.BIG_COUNT, lambda x, y: x + y, lambda x, y: x * y),
        "min-plus": (S.MIN_PLUS, min, lambda x, y: x + y),
        "max-plus": (S.MAX_PLUS, max, lambda x, y: x + y),
        "max-times": (S.MAX_TIMES, max, lambda x, y: x * y),
        "bottleneck": (S.BOTTLENECK, max, min),
        "mod": (S.modular(5), lambda x, y: (x + y) % 5, lambda x, y: x * y % 5),
        "real": (S.REAL, lambda x, y: x + y, lambda x, y: x * y),
        "user": (S.user("gcd", "long", 1, lambda s: int(__import__("numpy").gcd.reduce(s)), lambda a, b: a * b), __import__("math").gcd, lambda x, y: x * y),
    }
    for name, (semiring, plus, times) in ops.items():
        want = {}
        for x, y, w, z in product(*(data[n] for n in "ABCD")):
            if w == z - x - y:
                v = times(times(data["A"][x], data["B"][y]), times(data["C"][w], data["D"][z]))
                want[x + y,] = plus(want[x + y,], v) if (x + y,) in want else v
        if name == "mod":
            want = {k: v for k, v in want.items() if v}
        db = Database({n: Rel.of_rows(spark, [(k, __import__("decimal").Decimal(v) if name == "big" else float(v) if name == "real" else v) for k, v in data[n].items()], 1, semiring) for n in "ABCD"}, semiring)
        for run in (E.eval_dense, E.eval_by_value, E.eval_by_size) if name != "user" else (E.eval_joined,):
            assert rows(run(q, db)) == want, name
    boolean = Database({n: Rel.of_rows(spark, [(k, True) for k in data[n]], 1, S.BOOLEAN) for n in "ABCD"}, S.BOOLEAN)
    assert set(rows(E.eval_by_domain(q, boolean))) == set(rows(E.eval_dense(q, Database({n: Rel.of_rows(spark, [(k, 1) for k in data[n]], 1) for n in "ABCD"}))))
    s = S.witness("bigint")
    wit = Database({n: Rel.of_rows(spark, [(k, (v, [k])) for k, v in data[n].items()], 1, s) for n in "AB"}, s)
    got = E.eval_dense(parse_query("Q() <- A(X)*B(Y)"), wit).first().ann
    assert got.cost == min(data["A"].values()) + min(data["B"].values()) and len(got.wit) == 2
    sets = Database({n: Rel.of_rows(spark, [(k, [v]) for k, v in data[n].items()], 1, S.SETS) for n in "AB"}, S.SETS)
    assert E.eval_dense(parse_query("Q() <- A(X)*B(Y)"), sets).first().ann == sorted({a + b for a in data["A"].values() for b in data["B"].values()})


@pytest.mark.parametrize("field", [PrimeField(7), ExtensionField(2, 2)])
def test_finite_fields(spark, field):
    rng = random.Random(6)
    data = {n: {tuple(rng.randrange(field.order) for _ in range(2)): rng.randrange(1, 4) for _ in range(9)} for n in "RS"}
    db = Database({n: Rel.of_rows(spark, [(*k, v) for k, v in x.items()], 2) for n, x in data.items()}, field=field)
    for text in ("Q(A+B) <- R(A,C)*S(A+C,B)", "Q(2A,B) <- R(A,2B+A)*S(A+3B,B)", "Q() <- R(A,B)*S(B,A)*R(A+B,B)"):
        q = parse_query(text, field)
        want = slow(q, data, field)
        for run in (E.eval_dense, E.eval_grid, E.eval_sparse, E.eval_by_value, E.eval_by_domain, E.eval_by_size, E.eval_unguarded, E.eval_finite_field, E.eval_bruteforce, E.eval_where):
            assert values(run(q, db, drop_zero=True), len(q.head)) == {tuple(map(Fr, k)): v for k, v in want.items()}, (run, text)


def test_guards_stay_within_their_bounds(spark):
    rng = random.Random(12)
    q = parse_query("Q(X,Y,Z) <- A(X,Y)*B(Y,Z)*C(X+Y,Y+Z)")
    mk = lambda n, hi: Rel.of_rows(spark, {(rng.randrange(hi), rng.randrange(hi)): 1 for _ in range(n)} and [(x, y, 1) for x, y in {(rng.randrange(hi), rng.randrange(hi)) for _ in range(n)}], 2)
    db = Database({"A": mk(120, 12), "B": mk(120, 12), "C": mk(200, 22)})
    c = covers.cover_number(q)
    sizes = [db.stats([a.name])[a.name]["size"] for a in q.atoms]
    from linform.operators.wcoj import size_bound

    for join in ("levelwise", "hypercube", "hypercube_frames"):
        assert E.sparse_guard(q, db, c, join).df.count() <= size_bound(sizes, c.weights) + 1e-6
    want = rows(E.eval_where(q, db))
    assert want == rows(E.eval_inequality_bags(q, db))
    assert want == rows(E.eval_sparse(q, db)) == rows(E.eval_sparse(q, db, weights=(1, 1, 0))) == rows(E.eval_inequality_pairs(q, db))
    seen = []
    k = parse_query("Q() <- A(X1)*B(X2)*C(X3)*D(X4)*S(X1+X2+X3+X4)")
    un = lambda n, m: Rel.of_rows(spark, [(x * m, 1) for x in range(n)], 1)
    kdb = Database({"A": un(4, 1), "B": un(4, 4), "C": un(4, 16), "D": un(4, 64), "S": un(4, 5)})
    tree = trees.find_tree(k, "vec")
    got = E.eval_by_domain(k, kdb, tree, watch=lambda v, g, out: seen.append((g.df.count(), out.count())))
    assert rows(got) == rows(E.eval_where(k, kdb))
    assert all(m <= g or m <= 1 for g, m in seen) and max(g for g, _ in seen) <= 4**3
    worst = []
    E.eval_unguarded(k, kdb, trees.sum_chain(k), watch=lambda v, g, out: worst.append(out.count()))
    assert worst[:2] == [16, 64]  # messages of the unguarded chain grow with every step


def test_relation_algebra(spark):
    a = Rel.of_rows(spark, [(1, 2, 5), (2, 1, 7), (1, 2, 1), (3, 3, 0)], 2)
    assert rows(a.df) == {(1, 2): 6, (2, 1): 7}
    assert rows(a.project([[1, 1]]).df) == {(3,): 13}
    assert rows(a.transpose([1, 0]).union(a).df) == {(2, 1): 13, (1, 2): 13}
    assert rows(a.union(a.scale(-1)).df) == {}
    assert rows(a.shift([10, 0]).df) == {(11, 2): 6, (12, 1): 7}
    assert rows(a.restrict(spark.createDataFrame([(1,)], "c0 long"), ["c0"]).df) == {(1, 2): 6}
    assert rows(a.product(Rel.of_rows(spark, [(9, 2)], 1)).df) == {(1, 2, 9): 12, (2, 1, 9): 14}
    from pyspark.sql import functions as F

    b = Rel.of_frame(spark.createDataFrame([(1, None), (None, 2), (3, 4), (3, 4)], "x long, y long"), ["x", F.col("y") + 1])
    assert rows(b.df) == {(3, 5): 2}


def test_grid_of_the_least_subfield(spark):
    field = ExtensionField(2, 4)
    four = field.subfield([0, 1, next(a for a in range(2, 16) if field.power(a, 4) == a)])
    assert len(four) == 4 and len(field.subfield([2])) == 16 and field.subfield([0, 1]) == [0, 1]
    assert all(field.add(a, b) in four and field.mul(a, b) in four for a in four for b in four)
    rng = random.Random(3)
    data = {n: {(rng.choice(four), rng.choice(four)): rng.randrange(1, 4) for _ in range(9)} for n in "RS"}
    db = Database({n: Rel.of_rows(spark, [(*k, v) for k, v in x.items()], 2) for n, x in data.items()}, field=field)
    q = parse_query("Q(A+B) <- R(A,C)*S(A+C,B)", field)
    assert E.field_values(q, db) == four
    plan = E.eval_grid(q, db)._jdf.queryExecution().optimizedPlan().toString()
    assert "Range (0, 64," in plan  # 4**3 points, not 16**3
    assert values(E.eval_grid(q, db, drop_zero=True), 1) == {tuple(map(Fr, k)): v for k, v in slow(q, data, field).items()}
    wide = parse_query("Q(2A+B) <- R(A,C)*S(A+C,B)", field)
    assert len(E.field_values(wide, db)) == 16
    assert values(E.eval_grid(wide, db, drop_zero=True), 1) == {tuple(map(Fr, k)): v for k, v in slow(wide, data, field).items()}


def test_hypercube_has_one_exchange_after_its_reducts(spark):
    q = parse_query("Q(X,Y,Z) <- A(X,Y)*B(Y,Z)*C(X+Y,Y+Z)")
    rng = random.Random(4)
    mk = lambda: Rel.of_rows(spark, [(x, y, 1) for x, y in {(rng.randrange(9), rng.randrange(9)) for _ in range(50)}], 2)
    db = Database({n: mk() for n in "ABC"})
    found, basis = R.cover_reducts(q, db, list(covers.cover_number(q).basis))
    from linform.operators import wcoj

    df = wcoj.hypercube(found, list(range(len(basis))), cells=16)
    df.collect()
    plan = df._jdf.queryExecution().executedPlan().toString()
    final = plan.partition("Initial Plan")[0]
    assert final.count("Exchange") == 1 and "Join" not in final and df.rdd.getNumPartitions() == 16
    assert sorted(map(tuple, df.collect())) == sorted(map(tuple, wcoj.levelwise(found, list(range(len(basis)))).collect()))
    cut = wcoj.shares([100, 100, 100], [[0, 1], [1, 2], [0, 2]], [0, 1, 2], 64)
    assert cut == {0: 4, 1: 4, 2: 4} and wcoj.shares([10**6, 10, 10], [[0, 1], [1, 2], [0, 2]], [0, 1, 2], 64)[2] == 1


def test_local_join_against_products():
    import numpy as np

    from linform.operators import wcoj

    rng, kept = np.random.default_rng(1), wcoj.AT_ONCE
    wcoj.AT_ONCE = 7
    try:
        for _ in range(20):
            k = int(rng.integers(2, 5))
            haves = [sorted(rng.choice(k, size=rng.integers(1, min(3, k) + 1), replace=False).tolist()) for _ in range(3)]
            haves += [[i] for i in range(k) if not any(i in h for h in haves)]
            relations = [np.unique(rng.integers(-4, 5, (40, len(h))), axis=0) for h in haves]
            order = rng.permutation(k).tolist()
            got = {tuple(int(x[order.index(i)]) for i in range(k)) for part in wcoj.local_join(relations, haves, order) for x in part}
            sets = [{tuple(map(int, x)) for x in r} for r in relations]
            assert got == {v for v in product(range(-4, 5), repeat=k) if all(tuple(v[i] for i in h) in s for h, s in zip(haves, sets, strict=True))}
    finally:
        wcoj.AT_ONCE = kept


def test_tiles_equal_the_general_evaluators(spark):
    from linform.operators import tensor

    rng = random.Random(5)
    image = Rel.of_rows(spark, [(v, c, i, j, rng.randrange(-5, 6)) for v in range(2) for c in range(3) for i in range(-3, 11) for j in range(9) if rng.random() < 0.7], 4)
    kernel = Rel.of_rows(spark, [(f, c, k, m, rng.randrange(1, 4)) for f in range(2) for c in range(3) for k in range(-1, 3) for m in (-2, 0, 1)], 4)
    q = parse_query("Q(V,F,I,J) <- A(V,C,I+L,J+K)*P(F,C,L,K)")
    want = rows(E.eval_joined(q, Database({"A": image, "P": kernel})))
    for tile in (1, 4, 64):
        assert rows(tensor.convolve(image, kernel, shared=1, filters=1, channels=1, tile=tile)) == want
    with pytest.raises(ValueError, match="fit together"):
        tensor.convolve(image, kernel, filters=1)


def _plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("run", [E.eval_where, E.eval_inequality_pairs, E.eval_bruteforce])
def test_baselines_find_tuples_by_key(spark, run):
    db = Database({"R": Rel.of_rows(spark, [(1, 2, 1), (3, 2, 2)], 2), "S": Rel.of_rows(spark, [(2, 3, 5), (2, 5, 7), (2, 4, 1)], 2)})
    got = run(parse_query("Q(X) <- R(X,Y)*S(Y,X+Y)"), db)
    assert sorted(map(tuple, got.collect())) == [(1, 5), (3, 14)]
    assert "NestedLoop" not in _plan(got) and "CartesianProduct" not in _plan(got)


@pytest.mark.parametrize("join", ["levelwise", "hypercube", "hypercube_frames", "binary"])
def test_joins_carry_annotations(spark, join):
    q = parse_query("Q(X,Y,Z) <- A(X,Y)*B(Y,Z)*C(X+Y,Y+Z)")
    db = Database({"A": Rel.of_rows(spark, [(1, 2, 3), (2, 2, 4)], 2), "B": Rel.of_rows(spark, [(2, 5, 7), (2, 6, 9)], 2), "C": Rel.of_rows(spark, [(3, 7, 11), (4, 8, 13)], 2)})
    guard = E.sparse_guard(q, db, covers.cover_number(q), join, q)
    assert {"_a0", "_a1", "_a2"} <= set(guard.df.columns)  # no lookups, so the guard is not joined again
    assert sorted(map(tuple, E.eval_sparse(q, db, join=join).collect())) == [(1, 2, 5, 3 * 7 * 11), (2, 2, 6, 4 * 9 * 13)]


def test_tuples_out_of_range_are_left_out(spark):
    q = parse_query("Q() <- A(X)*B(Y)*C(X+Y)")
    db = Database({"A": Rel.of_rows(spark, [(1, 1), (2, 1), (90, 1)], 1), "B": Rel.of_rows(spark, [(1, 1), (3, 2)], 1), "C": Rel.of_rows(spark, [(-5, 1), (4, 1), (5, 3), (93, 2), (100, 1)], 1)})
    small = R.trimmed(q, db)
    assert sorted(r.c0 for r in small["C"].df.collect()) == [4, 5, 93]
    assert E.eval_joined(q, small).first().ann == E.eval_joined(q, db).first().ann == 2 + 6 + 4
    empty = R.trimmed(q, Database({**db.relations, "C": Rel.of_rows(spark, [(1000, 1)], 1)}))
    assert E.eval_dense(q, empty).first().ann == 0


@pytest.mark.parametrize("s", [S.COUNT, S.BOOLEAN, S.witness("bigint")], ids=["count", "boolean", "witness"])
def test_pairs_are_summed_inside_tasks(spark, monkeypatch, s):
    from pyspark.sql import functions as F

    from linform.operators import pairs

    q, rng = parse_query("Q() <- A(X)*B(Y)*C(2X-Y)"), random.Random(3)
    rows = {a: [(v, rng.randint(1, 9)) for v in rng.sample(range(-n, 3 * n), n)] for a, n in (("A", 20), ("B", 35), ("C", 25))}
    ann = {"sum": F.col("n"), "boolean": F.lit(True), "witness": F.struct(F.col("n").alias("cost"), F.array("c0").alias("wit"))}[s.name]
    made = lambda: Database({a: Rel(spark.createDataFrame(r, "c0 long, n long").select("c0", ann.alias("ann")), 1, s) for a, r in rows.items()}, s)
    want = E.eval_joined(q, made()).first().ann
    found = []
    real = pairs.pair_sums
    monkeypatch.setattr(pairs, "PAIRS", 0)
    monkeypatch.setattr(pairs, "pair_sums", lambda *a: found.append(real(*a)) or found[-1])
    for run in (E.eval_dense, E.eval_sparse, E.eval_by_domain, E.eval_by_size, E.eval_joined):
        db = made()
        for a in rows:
            db._stats[a, False] = {"size": len(rows[a]), "distinct": [len(rows[a])], "low": [-100], "high": [100], "most": 100, "mass": 1.0, "top": 1.0}
        assert run(q, db).first().ann == want
    assert len(found) == 5 and all(x is not None for x in found)
