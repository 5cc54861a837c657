"""Large relations dealt once, by a form that all of them determine."""

import random

import pytest

from linform.operators import evaluate as E
from linform.operators import pairs, relation
from linform.operators import reducts as R
from linform.operators.relation import AnnotatedRelation, Database
from linform.plans.query import parse_query
from linform.sources import shared

SKEW = parse_query("Q(X,Y,Z) <- A(X,Y)*B(Y,Z)*C(X+Y,Y+Z)")
RUNS = {
    "dense": E.eval_dense,
    "integral": lambda q, db: E.eval_sparse(q, db, weights=[1, 1, 0]),
    "joined": E.eval_joined,
    "inequality_bags": E.eval_inequality_bags,
}


@pytest.mark.parametrize("how", RUNS)
def test_expanded_rows_are_not_dealt(spark, how, monkeypatch):
    rnd = random.Random(7)
    some = lambda n, a, b: {(rnd.randrange(a), rnd.randrange(b)): rnd.choice((-2, 1, 3)) for _ in range(n)}
    a, b, c = some(20, 4, 5), some(400, 5, 300), some(900, 9, 300)
    db = Database({n: AnnotatedRelation.of_rows(spark, [(*k, w) for k, w in rows.items()], 2) for n, rows in (("A", a), ("B", b), ("C", c))}).settled()
    db.stats()
    monkeypatch.setattr(shared, "FEW", 60)
    monkeypatch.setattr(R, "FEW", 60)
    monkeypatch.setattr(R, "SPREAD", 1)
    deal = R.deal_of(SKEW, db)
    assert deal is not None and deal.form == SKEW.atoms[2].forms[1]
    got = RUNS[how](SKEW, db)
    want = {(x, y, z): w * b[y, z] * c[x + y, y + z] for (x, y), w in a.items() for (v, z) in b if v == y and (x + y, y + z) in c}
    assert {tuple(r)[:3]: r.ann for r in got.collect()} == want and want
    plan = got._jdf.queryExecution().executedPlan().toString()
    joins = [x for x in plan.split("\n") if "SortMergeJoin" in x or "CartesianProduct" in x]
    top = plan.split("ShuffledHashJoin")[0]
    assert not joins and "Exchange" not in top, plan  # what joins make is not exchanged, nor summed


def test_hot_values_are_not_dealt(spark, monkeypatch):
    rows = [(0, z, 1) for z in range(100)] + [(y, 50 - y, 1) for y in range(1, 100)]  # one value of Y+Z has half of B
    db = Database({"A": AnnotatedRelation.of_rows(spark, [(0, 0, 1)], 2), "B": AnnotatedRelation.of_rows(spark, rows, 2), "C": AnnotatedRelation.of_rows(spark, rows, 2)})
    db.stats()
    monkeypatch.setattr(shared, "FEW", 60)
    assert R.deal_of(SKEW, db) is None


@pytest.mark.parametrize("how", ["dense", "value", "size", "domain"])
def test_counts_of_sums_make_no_row_a_pair(spark, how, monkeypatch):
    q = parse_query("Q() <- A(X)*B(Y)*C(X+Y)")
    rows = {"A": range(0, 40), "B": range(0, 90, 3), "C": range(0, 130, 2)}
    db = Database({n: AnnotatedRelation.of_rows(spark, [(x, x % 3 + 1) for x in xs], 1) for n, xs in rows.items()}).settled()
    db.stats()
    monkeypatch.setattr(pairs, "PAIRS", 100)
    got = E.EVALUATORS[how](q, db)
    want = sum((x % 3 + 1) * (y % 3 + 1) * ((x + y) % 3 + 1) for x in rows["A"] for y in rows["B"] if x + y in rows["C"])
    assert got.first().ann == want
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan or how == "domain"


def test_tuples_out_of_range_are_not_summed(spark, monkeypatch):
    q = parse_query("Q(X,Y,Z) <- A(X,Y)*B(Y,Z)*C(X+Y,Y+Z)")
    raw = {"A": "id % 1000 AS c0, id % 7 AS c1", "B": "id % 7 AS c0, id % 90 AS c1", "C": "id % 30 AS c0, id % 50 AS c1"}
    summed = lambda cols: spark.range(20_000).selectExpr(*cols.split(", ")).groupBy("c0", "c1").count().withColumnRenamed("count", "ann")
    db = Database({n: AnnotatedRelation(summed(cols), 2) for n, cols in raw.items()})
    seen = {}
    kept = lambda df, name: (seen.setdefault(name, df), shared.written(df, name))[1]
    monkeypatch.setattr(relation, "written", kept)
    small = R.trimmed(q, db)
    assert seen["A"].agg({"c0": "max"}).first()[0] == 29 and small.rows("A") == 30 * 7 - 21  # X+Y has 30 values
    plan = seen["A"]._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("Aggregate") < plan.index("Filter") < plan.index("Range"), plan  # out of range: not dealt, not written
    rows = lambda d: sorted(map(tuple, E.eval_joined(q, d).collect()))
    assert rows(small) == rows(db.settled()) != []


def test_only_what_is_prolonged_is_dealt(spark, monkeypatch):
    made = [[(y, z, 1) for y in range(5) for z in range(40)], [(u, w, 1) for u in range(9) for w in range(40)]]
    db = Database({"A": AnnotatedRelation.of_rows(spark, [(x, y, 1) for x in range(4) for y in range(5)], 2), "B": AnnotatedRelation.of_rows(spark, made[0], 2), "C": AnnotatedRelation.of_rows(spark, made[1], 2)}).settled()
    db.stats()
    monkeypatch.setattr(shared, "FEW", 60)
    monkeypatch.setattr(R, "SPREAD", 1)
    deal = R.deal_of(SKEW, db)
    got = RUNS["integral"](SKEW, db)
    assert deal is not None and got.count() == sum(y + z < 40 for x in range(4) for y in range(5) for z in range(40))
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("RepartitionByExpression") == 2, plan  # B once and C once, no projection of B
