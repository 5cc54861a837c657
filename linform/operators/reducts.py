"""Reducts (set-valued images of relations under forms) and guards (relations that determine every form)."""

from __future__ import annotations

from dataclasses import dataclass, replace
from math import inf, lcm, prod

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from linform.functions import linalg
from linform.operators.relation import AnnotatedRelation, Database
from linform.plans.query import Atom, Form, LinearQuery
from linform.sources.shared import FEW, crossed, far

#: Rows of large relations in a task about, where they are dealt by one form; values that each such task must have at
#: least; tuples of a value at most (they are searched one by one).
DEAL_ROWS, SPREAD, SEARCHED = 250_000, 16, 1_000


@dataclass(frozen=True)
class Deal:
    """A form whose values decide on the task of a row, and the number of tasks."""

    form: Form
    tasks: int


@dataclass(frozen=True)
class Guard:
    """Distinct values b0, b1, ... of independent vectors that span every form asked of it."""

    df: DataFrame
    basis: tuple[Form, ...]
    #: Where df is the cross product of frames with one b-column each: these, and rows of each as far as they are known.
    factors: tuple[tuple[DataFrame, float], ...] = ()
    #: How df lies in tasks, by its column _w.
    deal: Deal | None = None

    @property
    def columns(self) -> list[str]:
        return [f"b{i}" for i in range(len(self.basis))]


def whole_form(coefficients, field) -> tuple[tuple, int]:
    """Integer coefficients and the common denominator (1 in finite fields)."""
    if field.characteristic:
        return tuple(coefficients), 1
    den = lcm(*(x.denominator for x in coefficients)) if coefficients else 1
    return tuple(x * den for x in coefficients), den


def value_of(form: Form, basis, columns: list[Column], field) -> tuple[Column, int]:
    """The form's value times the returned denominator, from values of the basis."""
    found = linalg.coordinates(form, list(basis), field)
    if found is None:
        raise ValueError("the guard does not determine a form")
    whole, den = whole_form(found, field)
    return field.linear(columns, list(whole)), den


def consistent(relation: AnnotatedRelation, forms, field) -> DataFrame:
    """The tuples that some variable values give: keys obey the linear relations among the forms."""
    df = relation.df
    for relation_of in linalg.dependencies(list(forms), field):
        whole, _ = whole_form(relation_of, field)
        df = df.where(field.linear([F.col(k) for k in relation.keys], list(whole)) == 0)
    return df


def reduct(relation: AnnotatedRelation, forms, targets: list[Form], names: list[str], field, carry: str | None = None) -> DataFrame:
    """Distinct values of targets (in the span of the atom's forms, whole over an independent choice of them). carry: a
    column for the annotations; for targets that are one to one with the tuples."""
    base = linalg.independent(list(forms), field)
    cols = [F.col(f"c{i}") for i in base]
    out = []
    for t, name in zip(targets, names, strict=True):
        value, den = value_of(t, [forms[i] for i in base], cols, field)
        if den != 1:
            raise ValueError("scale the target first")
        out.append(value.alias(name))
    rows = consistent(relation, forms, field)
    return rows.select(*out, F.col("ann").alias(carry)) if carry else rows.select(*out).distinct()


def scaled_targets(q: LinearQuery, vectors: list[Form]) -> list[Form]:
    """Each vector times the least whole number by which it is whole in every atom that spans it."""
    if q.field.characteristic:
        return list(vectors)
    out = []
    for v in vectors:
        den = 1
        for a in q.atoms:
            base = linalg.independent(list(a.forms), q.field)
            c = linalg.coordinates(v, [a.forms[i] for i in base], q.field)
            if c is not None:
                den = lcm(den, whole_form(c, q.field)[1])
        out.append(linalg.scale(v, q.field.of(den), q.field))
    return out


def deal_of(q: LinearQuery, db: Database) -> Deal | None:
    """A form that all relations too large for every task determine, if there are two of them, with two columns each. Rows
    that lie in tasks by it find their tuples in each of them without being dealt again, so joins may make many rows and
    exchange none.

    None where statistics are not known, or one of its values has too many tuples. A job for each such relation, kept with
    the statistics.
    """
    if q.field.characteristic or any(db.rows(a.name) == inf for a in q.atoms):
        return None
    large = [a for a in q.atoms if far(db.rows(a.name))]
    if len(large) < 2 or any(len(a.forms) != 2 or linalg.rank(list(a.forms), q.field) != 2 for a in large):
        return None
    if ("deal", q) not in db._stats:
        tasks = max(4 * db[large[0].name].df.sparkSession.sparkContext.defaultParallelism, int(sum(db.rows(a.name) for a in large)) // DEAL_ROWS)
        db._stats["deal", q] = None
        for f in q.body:
            values = [_value_in(a, f, q.field) for a in large]
            if all(v is not None for v in values) and all(_most(db[a.name].df, v) <= min(db.rows(a.name) / (tasks * SPREAD), SEARCHED) for a, v in zip(large, values, strict=True)):
                db._stats["deal", q] = Deal(f, tasks)
                break
    return db._stats["deal", q]


def _value_in(atom: Atom, form: Form, field, name: str = "c") -> Column | None:
    """A form's value from an atom's columns; None if they do not determine it, or not as a whole number."""
    base = linalg.independent(list(atom.forms), field)
    found = linalg.coordinates(form, [atom.forms[i] for i in base], field)
    if found is None or whole_form(found, field)[1] != 1:
        return None
    return field.linear([F.col(f"{name}{i}") for i in base], list(found))


def _most(df: DataFrame, value: Column) -> int:
    """Rows of the value that has most."""
    return df.groupBy(value.alias("_w")).count().agg(F.max("count")).first()[0] or 0


def dealt(side: DataFrame, atom: Atom, deal: Deal, field, name: str = "c", by: str = "_w") -> DataFrame:
    """An atom's tuples (columns <name>0, ...) in the tasks of a deal; by: a new column for the form's value."""
    return side.withColumn(by, _value_in(atom, deal.form, field, name)).repartition(deal.tasks, by)


def number_in(q: LinearQuery | None, atom: Atom) -> int | None:
    """The atom's number in a query; None if it isn't there, or several times."""
    return q.atoms.index(atom) if q is not None and q.atoms.count(atom) == 1 else None


def cover_reducts(q: LinearQuery, db: Database, vectors: list[Form], carry: LinearQuery | None = None) -> tuple[list[tuple[DataFrame, list[int]]], list[Form]]:
    """One reduct for each atom onto the (scaled) vectors in its span: (frame with b-columns, their numbers).

    carry: a query that has these atoms, or some of them. Reducts that are one to one with their relation (their vectors
    span the atom's) bring its annotations along, in columns _a<number of the atom in that query>, and need not be made
    distinct.
    """
    basis = scaled_targets(q, vectors)
    out = []
    for a in q.atoms:
        mine = [i for i, b in enumerate(basis) if any(a.forms) and linalg.contains(list(a.forms), [b], q.field)]
        if mine:
            n = number_in(carry, a)
            whole = n is not None and len(mine) == linalg.rank(list(a.forms), q.field)
            out.append((reduct(db[a.name], a.forms, [basis[i] for i in mine], [f"b{i}" for i in mine], q.field, f"_a{n}" if whole else None), mine))
    return out, basis


def unary_reduct(q: LinearQuery, db: Database, form: Form, name: str, carry: LinearQuery | None = None) -> DataFrame:
    """Distinct values of a body form, in the atom that has fewest of them as far as statistics are known. carry: a query;
    if it has that atom, and the form is all of it, its annotations come along, as in cover_reducts."""
    few = lambda a: db.known(a.name, "distinct", a.forms.index(form))
    atom = min((a for a in q.atoms if form in a.forms), key=few)
    rows, n = consistent(db[atom.name], atom.forms, q.field), number_in(carry, atom)
    value = F.col(f"c{atom.forms.index(form)}").alias(name)
    return rows.select(value, F.col("ann").alias(f"_a{n}")) if n is not None and len(atom.forms) == 1 else rows.select(value).distinct()


def product_guard(q: LinearQuery, db: Database, forms: list[Form], carry: LinearQuery | None = None, deal: Deal | None = None) -> Guard:
    """The cross product of unary reducts of independent body forms; an error if it is known to exceed the budget. carry:
    see unary_reduct. deal: of the first form, whose values are then dealt by it if the others' product can go to every
    task."""
    each = [min(db.known(a.name, "distinct", a.forms.index(f)) for a in q.atoms if f in a.forms) for f in forms]
    df, rows = None, prod(each)
    if db.budget < rows < inf:
        raise ValueError(f"a cross product of {rows:.3g} rows, more than {db.budget:.3g}")
    factors = [(unary_reduct(q, db, f, f"b{i}", carry), n) for i, (f, n) in enumerate(zip(forms, each, strict=True))]
    if deal is not None and len(forms) > 1 and prod(each[1:]) <= FEW:
        rest = factors[1][0]
        for one, _ in factors[2:]:
            rest = rest.crossJoin(F.broadcast(one))
        first = factors[0][0].withColumn("_w", F.col("b0")).repartition(deal.tasks, "_w")
        return Guard(first.crossJoin(F.broadcast(rest)), tuple(forms), tuple(factors), deal)
    for i, (one, _) in enumerate(factors):
        df = one if df is None else crossed(df, one, prod(each[:i]), each[i])
    return Guard(_nothing(db) if df is None else df, tuple(forms), tuple(factors))


def atoms_guard(q: LinearQuery, db: Database, atoms: list[int]) -> Guard:
    """The cross product of whole relations whose forms are independent together."""
    df, basis = None, []
    for i in atoms:
        a = q.atoms[i]
        names = [f"b{len(basis) + j}" for j in range(len(a.forms))]
        one = reduct(db[a.name], a.forms, list(a.forms), names, q.field)
        df = one if df is None else df.crossJoin(one)
        basis += a.forms
    if linalg.rank(basis, q.field) < len(basis):
        raise ValueError("the forms of these atoms are dependent")
    return Guard(df, tuple(basis))


def grid_guard(spark: SparkSession, basis: list[Form], lows: list[int], highs: list[int], codes: list[int] | None = None) -> Guard:
    """All integer points of a box, decoded from one range: no data is read or dealt. codes: values that points stand
    for, by number (of a subfield, whose codes are not consecutive)."""
    sizes = [h - low + 1 for low, h in zip(lows, highs, strict=True)]
    total = prod(sizes)
    if total >= 1 << 63:
        raise OverflowError(f"a grid of {total:.3g} points")
    df, rest, cols = spark.range(total), F.col("id"), []
    for i, (low, s) in enumerate(zip(lows, sizes, strict=True)):
        at = F.pmod(rest, F.lit(s).cast("long")) + F.lit(low).cast("long")
        if codes is not None:
            at = F.get(F.array(*map(F.lit, codes)), at.cast("int"))
        cols.append(at.cast("long").alias(f"b{i}"))
        rest = F.expr(f"id div {prod(sizes[: i + 1])}")
    return Guard(df.select(*cols), tuple(basis))


def _nothing(db: Database) -> DataFrame:
    """One row without columns of interest: the guard of a span of dimension zero."""
    spark = next(iter(db.relations.values())).df.sparkSession
    return spark.range(1).select(F.lit(0).alias("_none"))


def onto(guard: Guard, vectors: list[Form], field) -> Guard:
    """The guard's image on other vectors (scaled to whole ones), distinct."""
    if linalg.space_key(list(vectors), field) == linalg.space_key(list(guard.basis), field):
        return guard
    cols, basis = [], []
    for i, v in enumerate(vectors):
        value, den = value_of(v, guard.basis, [F.col(c) for c in guard.columns], field)
        cols.append(value.alias(f"b{i}"))
        basis.append(linalg.scale(v, field.of(den), field))
    if not cols:
        return Guard(guard.df.select(F.lit(0).alias("_none")).limit(1), ())
    return Guard(guard.df.select(*cols).distinct(), tuple(basis))


def trimmed(q: LinearQuery, db: Database) -> Database:
    """The database without tuples that ranges alone rule out, written, with statistics: of each equation among the
    columns, the part that one atom has must lie in the range that the columns of the others leave. Answers stay as they are.
    Ranges are of the columns before sums, and tuples go before sums, so those left out are neither dealt nor written.

    Relations that several atoms use are left whole; so are finite fields, and plain queries, which have equalities only.
    """
    at = [(a, j) for a in q.atoms for j in range(len(a.forms))]
    equations = [] if q.field.characteristic or q.is_plain() else [whole_form(d, q.field)[0] for d in linalg.dependencies([a.forms[j] for a, j in at], q.field)]
    if not equations:
        return db
    names, parts = list(dict.fromkeys(a.name for a in q.atoms)), None
    for n in names:
        ends = [f(k).cast("long") for k in db[n].keys for f in (F.min, F.max)]
        one = db[n].df.agg(F.lit(n).alias("name"), F.array(*ends).alias("ends") if ends else F.lit(None).cast("array<bigint>").alias("ends"))
        parts = one if parts is None else parts.unionAll(one)
    ends = {r.name: r.ends or [] for r in parts.collect()}  # one row a relation
    if any(x is None for e in ends.values() for x in e):
        return db.settled()  # a relation without tuples
    low, high = [ends[a.name][2 * j] for a, j in at], [ends[a.name][2 * j + 1] for a, j in at]

    def left_by(equation, outside) -> tuple[int, int]:
        """Range of the negative of an equation's part in some of the columns."""
        sides = [sorted((-int(equation[s]) * low[s], -int(equation[s]) * high[s])) for s in outside]
        return sum(x for x, _ in sides), sum(y for _, y in sides)

    for _ in range(3):  # ranges of single columns first
        for e in equations:
            for s, w in enumerate(e):
                if w:
                    least, most = left_by(e, [o for o, x in enumerate(e) if x and o != s])
                    least, most = (least, most) if w > 0 else (-most, -least)
                    low[s], high[s] = max(low[s], -(-least // abs(int(w)))), min(high[s], most // abs(int(w)))
                    if low[s] > high[s]:
                        return replace(db, relations=db.relations | {n: replace(db[n], df=db[n].df.where(F.lit(False))) for n in names[:1]}, _stats={}).settled()
    once = [a for a in q.atoms if sum(b.name == a.name for b in q.atoms) == 1]
    made = {}
    for a in once:
        df = db[a.name].df
        for e in equations:
            mine = [s for s, (b, _) in enumerate(at) if b is a and e[s]]
            rest = [s for s, (b, _) in enumerate(at) if b is not a and e[s]]
            if mine and rest:
                df = df.where(q.field.linear([F.col(f"c{at[s][1]}") for s in mine], [e[s] for s in mine]).between(*(F.lit(x) for x in left_by(e, rest))))
        made[a.name] = replace(db[a.name], df=df)
    db = replace(db, relations=db.relations | made, _stats={}).settled()
    db.stats(names)
    return db


def restrict_to(guard: Guard, atom: Atom, relation: AnnotatedRelation, field) -> Guard:
    """The guard rows that an atom of the query allows (a semi-join); leaves the answer as it is."""
    cols = [F.col(c) for c in guard.columns]
    right = relation.df.select(*(F.col(k).alias(f"_k{j}") for j, k in enumerate(relation.keys)))
    on = None
    for j, f in enumerate(atom.forms):
        value, den = value_of(f, guard.basis, cols, field)
        test = value == (F.col(f"_k{j}") if den == 1 else F.col(f"_k{j}") * F.lit(den).cast("long"))
        on = test if on is None else on & test
    return Guard(guard.df.join(right, on, "left_semi"), guard.basis)
