"""Queries as text over temp views, and the same queries as SQL with predicates."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from linform.functions import linalg
from linform.functions.fields import Q
from linform.functions.semirings import COUNT, Semiring
from linform.operators.reducts import whole_form
from linform.operators.relation import AnnotatedRelation, Database, keys_of
from linform.plans import planner
from linform.plans.query import LinearQuery, parse_query


def linear_sql(spark: SparkSession, text: str, semiring: Semiring = COUNT, field=Q, view: str | None = None) -> DataFrame:
    """Evaluate a query text whose atoms name views with columns c0, c1, ..., ann; view: register the answer."""
    q = parse_query(text, field)
    db = Database({a.name: AnnotatedRelation(spark.table(a.name).select(*keys_of(len(a.forms)), "ann"), len(a.forms), semiring) for a in q.atoms}, semiring, field)
    out = planner.evaluate(q, db)
    if view:
        out.createOrReplaceTempView(view)
    return out


def _sum(coefficients, names: list[str]) -> str:
    parts = [f"{'+' if c > 0 else '-'} {'' if abs(c) == 1 else f'{abs(c)} * '}{n}" for c, n in zip(coefficients, names, strict=True) if c]
    return " ".join(parts).removeprefix("+ ") or "0"


def where_sql(q: LinearQuery, sources: dict[str, str], ann: str, modulus: int | None = None) -> str:
    """SELECT over one source for each atom, equations as predicates. ann: the aggregate, with {product},
    {plus} or {each} for the product, sum or list of annotations; modulus: for a prime field."""
    slots = [(i, j) for i, a in enumerate(q.atoms) for j in range(len(a.forms))]
    forms, names = [q.atoms[i].forms[j] for i, j in slots], [f"t{i}.c{j}" for i, j in slots]
    within = (lambda x: f"((({x}) % {modulus}) + {modulus}) % {modulus}") if modulus else (lambda x: x)
    tests = [f"{within(_sum(whole_form(d, q.field)[0], names))} = 0" for d in linalg.dependencies(forms, q.field)]
    base = linalg.independent(forms, q.field)
    head = []
    for i, f in enumerate(q.head):
        whole, den = whole_form(linalg.coordinates(f, [forms[b] for b in base], q.field), q.field)
        if den != 1:
            raise ValueError("a head form is not whole over the arguments")
        head.append(f"{within(_sum(whole, [names[b] for b in base]))} AS h{i}")
    product = " * ".join(f"t{i}.ann" for i in range(len(q.atoms)))
    each = ", ".join(f"t{i}.ann" for i in range(len(q.atoms)))
    plus = " + ".join(f"t{i}.ann" for i in range(len(q.atoms)))
    sql = f"SELECT {', '.join([*head, ann.format(product=product, plus=plus, each=each) + ' AS ann'])} FROM " + ", ".join(f"{sources[a.name]} t{i}" for i, a in enumerate(q.atoms))
    if tests:
        sql += " WHERE " + " AND ".join(tests)
    if head:
        sql += " GROUP BY " + ", ".join(str(i + 1) for i in range(len(head)))
    return sql
