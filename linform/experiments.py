"""How rows grow with the input: what evaluators and baselines visit on families of instances, and fitted exponents.

Counted are rows that a method makes, not seconds, so the figures do not depend on the machine: bindings that a
worst-case-optimal join proposes, rows of a bag or of joins two by two, rows of guards and messages on a tree.
"""

from __future__ import annotations

from math import log

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linform.operators import evaluate as E
from linform.operators import reducts as R
from linform.operators import wcoj
from linform.operators.relation import AnnotatedRelation, Database
from linform.plans import covers, trees
from linform.plans.query import LinearQuery, parse_query
from linform.sources.shared import scope

SKEW = "Q(X,Y,Z) <- A(X,Y)*B(Y,Z)*C(X+Y,Y+Z)"
LINEAR = "Q() <- R(X,Y)*S(Y,X+Y)"
HUBS, SQUARES, SUMS = (60, 180, 540), (6, 12, 24), (2, 3, 4)


def _pairs(spark: SparkSession, shape: str, n: int) -> DataFrame:
    """hub: 0 with each number below n and each with 0. square: all pairs of numbers below n."""
    if shape == "hub":
        i = spark.range(n).select(F.col("id").alias("x"), F.lit(0).cast("long").alias("y"))
        return i.union(i.where("x > 0").select("y", "x"))
    i = spark.range(n)
    return i.select(F.col("id").alias("x")).crossJoin(i.select(F.col("id").alias("y")))


def _relation(df: DataFrame, *cols: str) -> AnnotatedRelation:
    return AnnotatedRelation(df.select(*(F.expr(c).alias(f"c{i}") for i, c in enumerate(cols)), F.lit(1).cast("long").alias("ann")), len(cols))


def skew_instance(spark: SparkSession, shape: str, n: int) -> Database:
    """Relations whose reducts onto X+Y, Y and Y+Z are the pairs of the shape."""
    p = _pairs(spark, shape, n)
    return Database({"A": _relation(p, "x - y", "y"), "B": _relation(p, "x", "y - x"), "C": _relation(p, "x", "y")})


def linear_instance(spark: SparkSession, shape: str, n: int) -> Database:
    p = _pairs(spark, shape, n)
    return Database({"R": _relation(p, "x", "y"), "S": _relation(p, "x", "y")})


def sum_instance(spark: SparkSession, k: int, n: int, numbers: DataFrame | None = None) -> tuple[LinearQuery, Database]:
    """k summands from {j * n**i}, whose part sums are all different, and the values j of the sum. numbers: the values j,
    below n, in a column id; else all of them."""
    numbers = spark.range(n) if numbers is None else numbers
    names = "ABCDEFG"[:k]
    text = "*".join(f"{a}(X{i})" for i, a in enumerate(names)) + "*S(" + "+".join(f"X{i}" for i in range(k)) + ")"
    made = {a: _relation(numbers, f"id * {n**i}") for i, a in enumerate(names)}
    return parse_query(f"Q() <- {text}"), Database(made | {"S": _relation(numbers, "id")})


def proposed(q: LinearQuery, db: Database, weights=None) -> int:
    """Bindings that the join of a cover's reducts proposes, all levels together."""
    cover = covers.given_cover(q, weights) if weights is not None else covers.cover_number(q)
    found, basis = R.cover_reducts(q, db, list(cover.basis))
    seen: list[DataFrame] = []
    wcoj.levelwise(found, list(range(len(basis))), seen)
    return sum(x.count() for x in seen)


def joined(q: LinearQuery, db: Database) -> int:
    """Rows of the largest relation that joins two by two hold: the one they begin with, or one of their results."""
    order = [s.atom for s in E.join_steps(q, db)]
    most = 0
    for n in range(1, len(order) + 1):
        part = tuple(q.atoms[i] for i in order[:n])
        most = max(most, E.solved_join(LinearQuery(q.variables, (), part, q.field), db).df.count())
    return most


def on_tree(q: LinearQuery, db: Database, run, tree: trees.SpanTree) -> int:
    """Rows of the largest guard or message."""
    rows = []
    run(q, db, tree, watch=lambda v, guard, message: rows.extend([guard.df.count(), message.count()]) and None)
    return max(rows)


def growth(spark: SparkSession, hubs=HUBS, squares=SQUARES, sums=SUMS) -> list[tuple[str, str, str, int, int, int]]:
    """(workload, instance, method, n, size, rows)"""
    out, skew, linear = [], parse_query(SKEW), parse_query(LINEAR)

    def add(workload: str, shape: str, n: int, size: int, told: dict[str, int]) -> None:
        out.extend((workload, shape, method, n, size, rows) for method, rows in told.items())

    with scope(spark):
        for n in hubs:
            db = skew_instance(spark, "hub", n)
            add("skew_triangle", "hub", n, 2 * n - 1, {"sparse": proposed(skew, db), "integral": proposed(skew, db, [1, 1, 0]), "inequality_bags": E.inequality_bag(skew, db)[1].df.count(), "joined": joined(skew, db)})
            db = linear_instance(spark, "hub", n)
            apart = parse_query("Q() <- R(X,Y)*S(Y,Z)")  # the bag of the older plan holds all variables
            add("linear_guard", "hub", n, 2 * n - 1, {"sparse": proposed(linear, db), "inequality_bags": joined(apart, db), "joined": joined(linear, db)})
        for n in squares:
            db = skew_instance(spark, "square", n)
            add("skew_triangle", "square", n, n * n, {"sparse": proposed(skew, db), "joined": joined(skew, db)})
        for n in sums:
            q, db = sum_instance(spark, 5, n)
            tree = trees.sum_chain(q)
            add("ksum5", "spread", n, n, {name: on_tree(q, db, run, tree) for name, run in (("unguarded", E.eval_unguarded), ("domain", E.eval_by_domain))})
    return out


#: What growth counts, in closed form.
ROWS = {
    ("skew_triangle", "hub", "sparse"): "6 * n - 3", ("skew_triangle", "hub", "integral"): "n * n + 5 * n - 3",
    ("skew_triangle", "hub", "inequality_bags"): "n * n + n - 1", ("skew_triangle", "hub", "joined"): "n * n + n - 1",
    ("linear_guard", "hub", "sparse"): "2 * n", ("linear_guard", "hub", "inequality_bags"): "n * n + n - 1", ("linear_guard", "hub", "joined"): "2 * n - 1",
    ("skew_triangle", "square", "sparse"): "n * n * n + n * n + n", ("skew_triangle", "square", "joined"): "n * n * n",
    ("ksum5", "spread", "unguarded"): "n * n * n * n", ("ksum5", "spread", "domain"): "n * n * n",
}


def growth_sql() -> str:
    """The same rows from the closed forms."""
    sizes = {"hub": (HUBS, "2 * n - 1"), "square": (SQUARES, "n * n"), "spread": (SUMS, "n")}
    parts = [f"SELECT '{w}' AS workload, '{shape}' AS instance, '{m}' AS method, n, {sizes[shape][1]} AS size, {rows} AS rows FROM (VALUES {', '.join(f'(CAST({n} AS BIGINT))' for n in sizes[shape][0])}) AS t(n)" for (w, shape, m), rows in ROWS.items()]
    return " UNION ALL ".join(parts)


def exponents(rows: list[tuple[str, str, str, int, int, int]]) -> dict[tuple[str, str, str], float]:
    """(workload, instance, method) -> the slope of log rows over log size, by least squares."""
    found: dict[tuple[str, str, str], list[tuple[float, float]]] = {}
    for workload, shape, method, _, size, n in rows:
        found.setdefault((workload, shape, method), []).append((log(size), log(max(1, n))))
    out = {}
    for key, points in found.items():
        x, y = (sum(p[i] for p in points) / len(points) for i in (0, 1))
        out[key] = sum((a - x) * (b - y) for a, b in points) / sum((a - x) ** 2 for a, _ in points)
    return out
