"""Evaluators: dense, plain, sparse, on trees by value, by active domain or by size, over finite fields, baselines.

All return a frame h0, h1, ..., ann with one row for each head value whose sum is not zero; a head without forms
gives one row, with the semiring's zero where nothing matches (none with drop_zero). A head form that can have
fractional values is returned as numerator h<i> and denominator h<i>_den.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass
from functools import reduce
from math import inf, log

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from linform.functions import linalg
from linform.functions.fields import PrimeField
from linform.operators import pairs
from linform.operators import reducts as R
from linform.operators.relation import AnnotatedRelation, Database
from linform.operators.wcoj import JOINS
from linform.plans import covers, trees
from linform.plans.query import Atom, Form, LinearQuery
from linform.sources import shared
from linform.sources.shared import crossed, far, few, redealt


def _finish(found: DataFrame, db: Database, head: list[tuple], drop_zero: bool, single: bool = False) -> DataFrame:
    """Sum by head values. found: h-columns and ann; head: denominators. single: no two rows have the same head values."""
    s = db.semiring
    if single and head and s.grouped is None:  # each row is a sum already, so none is dealt
        out = found.withColumn("ann", F.col("ann").cast(s.kind))
        out = out.where(s.keep(F.col("ann"))) if s.keep else out
    else:
        out = s.group(found, [f"h{i}" for i in range(len(head))])
    if not head and not drop_zero:
        one = out.sparkSession.range(1).select(F.lit(0).alias("_one"))
        out = one.join(out, F.lit(True), "left").select(F.coalesce(F.col("ann"), s.zero()).alias("ann"))
    cols = []
    for i, den in enumerate(head):
        cols.append(F.col(f"h{i}"))
        if den != 1:
            cols.append(F.lit(den).cast("long").alias(f"h{i}_den"))
    return out.select(*cols, "ann")


def _single(q: LinearQuery, basis: Sequence[Form]) -> bool:
    """Whether the head determines all values of a basis."""
    return not q.field.characteristic and linalg.rank(list(q.head), q.field) == len(basis)


def _found(df: DataFrame, basis: Sequence[Form], side: DataFrame, a: Atom, deal: R.Deal, db: Database, name: str, ann: str) -> DataFrame:
    """df, which lies in tasks by a deal and determines the forms of an atom, with annotations of the tuples (columns
    <name>0, <name>1) that it finds. The tuples of each value of the deal's form are one map, which meets df by that value
    alone: a join by all columns would deal df again."""
    j = next(j for j, f in enumerate(a.forms) if linalg.rank([deal.form, f], db.field) == 2)
    value, den = R.value_of(a.forms[j], basis, [F.col(f"b{i}") for i in range(len(basis))], db.field)
    key = F.col(f"{name}{j}") * F.lit(den).cast("long")
    maps = R.dealt(side, a, deal, db.field, name, "_v").groupBy("_v").agg(F.map_from_entries(F.collect_list(F.struct(key, ann))).alias("_m"))
    met = df.join(maps.hint("shuffle_hash"), F.col("_w") == F.col("_v")).withColumn(ann, F.try_element_at("_m", value))
    return met.where(F.col(ann).isNotNull()).drop("_v", "_m")


def eval_guarded(q: LinearQuery, guard: R.Guard, db: Database, drop_zero: bool = False) -> DataFrame:
    """For each guard row the keys of every atom follow by linear expressions; each lookup finds one tuple at most.
    Atoms whose annotations the guard carries need no lookup."""
    if not q.head and (parts := pairs.pair_sums(q, guard, db)) is not None:
        return _finish(parts, db, [], drop_zero)
    df, cols, ann = guard.df, [F.col(c) for c in guard.columns], None
    for i, a in enumerate(q.atoms):
        if f"_a{i}" in guard.df.columns:
            ann = F.col(f"_a{i}") if ann is None else db.semiring.times(ann, F.col(f"_a{i}"))
            continue
        rel = db[a.name]
        side = rel.df.select(*(F.col(k).alias(f"_k{i}_{j}") for j, k in enumerate(rel.keys)), F.col("ann").alias(f"_a{i}"))
        if rel.arity and not rel.bucketed:
            side = few(redealt(side, f"_k{i}_0"), db.rows(a.name))
        on = None
        if guard.deal and far(db.rows(a.name)):
            df = _found(df, guard.basis, side, a, guard.deal, db, f"_k{i}_", f"_a{i}")
            ann = F.col(f"_a{i}") if ann is None else db.semiring.times(ann, F.col(f"_a{i}"))
            continue
        for j, f in enumerate(a.forms):
            value, den = R.value_of(f, guard.basis, cols, q.field)
            key = F.col(f"_k{i}_{j}")
            test = value == (key if den == 1 else key * F.lit(den).cast("long"))
            on = test if on is None else on & test
        df = df.crossJoin(side) if on is None else df.join(side, on)
        df = df.drop(*(f"_k{i}_{j}" for j in range(rel.arity)))
        ann = F.col(f"_a{i}") if ann is None else db.semiring.times(ann, F.col(f"_a{i}"))
    head, dens = [], []
    for i, f in enumerate(q.head):
        value, den = R.value_of(f, guard.basis, cols, q.field)
        head.append(value.alias(f"h{i}"))
        dens.append(den)
    return _finish(df.select(*head, ann.alias("ann")), db, dens, drop_zero, _single(q, guard.basis))


# ---- basic evaluators ---------------------------------------------------------------------------------------


def eval_dense(q: LinearQuery, db: Database, guard_atoms: list[int] | None = None, drop_zero: bool = False) -> DataFrame:
    """Guard: all combinations of values of a basis of body forms, or of the tuples of some independent atoms."""
    q.check_safe()
    if guard_atoms is not None:
        guard = R.atoms_guard(q, db, guard_atoms)
    else:
        deal = R.deal_of(q, db)
        body = [deal.form, *q.body] if deal else q.body
        guard = R.product_guard(q, db, [body[i] for i in linalg.independent(body, q.field)], q, deal)
    return eval_guarded(q, guard, db, drop_zero)


def grid_box(q: LinearQuery, db: Database, basis: list[Form]) -> tuple[list[int], list[int]]:
    """Least and largest values of body forms, by the narrowest range that an atom has for each."""
    stats, lows, highs = db.stats(a.name for a in q.atoms), [], []
    for f in basis:
        ranges = [(stats[a.name]["low"][j], stats[a.name]["high"][j]) for a in q.atoms for j, g in enumerate(a.forms) if g == f]
        low, high = min(ranges, key=lambda x: x[1] - x[0])
        lows.append(low)
        highs.append(high)
    return lows, highs


def field_values(q: LinearQuery, db: Database) -> Sequence[int]:
    """Codes of the least subfield that holds the coefficients of the query and the values of the database."""
    if isinstance(q.field, PrimeField):
        return range(q.field.p)
    known = {x for a in [*q.atoms, Atom("", q.head)] for f in a.forms for x in f}
    values = None
    for a in q.atoms:
        for k in db[a.name].keys:
            one = db[a.name].df.select(F.col(k).alias("v")).distinct()
            values = one if values is None else values.union(one)
    if values is not None:
        known |= {r.v for r in values.distinct().limit(q.field.order).collect()}  # at most the field
    return q.field.subfield(known)


def eval_grid(q: LinearQuery, db: Database, drop_zero: bool = False) -> DataFrame:
    """Dense evaluation over a full grid: the box of the values that forms can take, or the least subfield that holds
    all values and coefficients."""
    q.check_safe()
    basis = [q.body[i] for i in linalg.independent(q.body, q.field)]
    spark = next(iter(db.relations.values())).df.sparkSession
    if q.field.characteristic:
        codes = field_values(q, db)
        guard = R.grid_guard(spark, basis, [0] * len(basis), [len(codes) - 1] * len(basis), codes if len(codes) < q.field.order else None)
    else:
        guard = R.grid_guard(spark, basis, *grid_box(q, db, basis))
    return eval_guarded(q, guard, db, drop_zero)


def sparse_guard(q: LinearQuery, db: Database, cover: covers.Cover, join: str = "levelwise", carry: LinearQuery | None = None) -> R.Guard:
    """The join of one reduct for each atom onto the cover's vectors. carry: with annotations, for an evaluation of that
    query."""
    found, basis = R.cover_reducts(q, db, list(cover.basis), carry)
    if not basis:
        return R.product_guard(q, db, [])
    if len(found) == len(basis) and all(len(have) == 1 for _, have in found):
        factors = sorted(((have[0], frame, frame.count()) for frame, have in found), key=lambda x: x[0])
        df, rows = factors[0][1], factors[0][2]
        for _, frame, n in factors[1:]:
            df, rows = crossed(df, frame, rows, n), rows * n
        return R.Guard(df, tuple(basis), tuple((frame, n) for _, frame, n in factors))
    order = list(range(len(basis)))
    if join != "levelwise":
        return R.Guard(JOINS[join](found, order), tuple(basis))
    found, deal = _reduct_dealt(q, db, found, basis)
    return R.Guard(JOINS[join](found, order, tasks=deal.tasks if deal else None), tuple(basis), deal=deal)


def _reduct_dealt(q: LinearQuery, db: Database, found: list, basis: list[Form]) -> tuple[list, R.Deal | None]:
    """The reducts, of which the only one that is too large for every task has a column _w to be dealt by, where it carries
    annotations and tuples of other such relations are to be looked up."""
    deal = R.deal_of(q, db)
    held = [a for a in q.atoms if any(a.forms) and any(linalg.contains(list(a.forms), [b], q.field) for b in basis)]
    large = [i for i, a in enumerate(held) if far(db.rows(a.name))]
    if deal is None or len(large) != 1 or not any(far(db.rows(a.name)) for a in q.atoms if a not in held):
        return found, None
    frame, have = found[large[0]]
    if len(frame.columns) == len(have):
        return found, None
    value, den = R.value_of(deal.form, [basis[i] for i in have], [F.col(f"b{i}") for i in have], q.field)
    if den != 1:
        return found, None
    return [*found[: large[0]], (frame.withColumn("_w", value), have), *found[large[0] + 1 :]], deal


def size_costs(q: LinearQuery, db: Database) -> list[float]:
    stats = db.stats(a.name for a in q.atoms)
    return [max(log(max(2, stats[a.name]["size"])), 0.01) for a in q.atoms]


def eval_sparse(q: LinearQuery, db: Database, weights=None, join: str = "levelwise", by_size: bool = False, drop_zero: bool = False) -> DataFrame:
    """Guard: worst-case-optimal join of the reducts of a least fractional cover (or of the weights given)."""
    q.check_safe()
    if weights is not None:
        cover = covers.given_cover(q, weights)
    else:
        cover = covers.cover_number(q, costs=size_costs(q, db) if by_size else None)
    return eval_guarded(q, sparse_guard(q, db, cover, join, carry=q), db, drop_zero)


def eval_plain(q: LinearQuery, db: Database, join: str = "levelwise", drop_zero: bool = False) -> DataFrame:
    """A plain query: the full join of its relations over the variables, then sums."""
    if not q.is_plain():
        raise ValueError("the query is not plain")
    q.check_safe()
    variables, found = [f for f in q.body], []
    for n, a in enumerate(q.atoms):
        mine = [variables.index(f) for f in dict.fromkeys(a.forms)]
        if mine:  # one to one: each distinct variable of the atom is a column
            found.append((R.reduct(db[a.name], a.forms, [variables[i] for i in mine], [f"b{i}" for i in mine], q.field, f"_a{n}"), mine))
    guard = R.Guard(JOINS[join](found, list(range(len(variables)))), tuple(variables))
    return eval_guarded(q, guard, db, drop_zero)


# ---- joins that solve the forms as they go ------------------------------------------------------------------


@dataclass(frozen=True)
class JoinStep:
    """An atom's turn: its tuples (_k0, ..., _a), equal sides of its equi-join (of what was joined before and of the
    tuples), the positions that bring new columns, and the basis after it."""

    atom: int
    side: DataFrame
    ours: tuple[Column, ...]
    theirs: tuple[Column, ...]
    new: tuple[int, ...]
    basis: tuple[Form, ...]


def join_steps(q: LinearQuery, db: Database) -> list[JoinStep]:
    """The atoms one by one, those next that share most forms with what was joined.

    Forms that what was joined before determines become keys; forms that depend on it and on new columns are
    rearranged so that each side of the equality belongs to one input. Every join is thus an equi-join.
    """
    left, basis, steps = list(range(len(q.atoms))), [], []
    while left:
        known = lambda i: sum(linalg.contains(basis, [f], q.field) for f in q.atoms[i].forms)  # noqa: E731, B023
        pick = max(left, key=lambda i: (known(i), len(q.atoms[i].forms) if not basis else 0, -i))
        left.remove(pick)
        a, rel = q.atoms[pick], db[q.atoms[pick].name]
        base = R.consistent(rel, a.forms, q.field)
        side = base.select(*(F.col(k).alias(f"_k{j}") for j, k in enumerate(rel.keys)), F.col("ann").alias("_a"))
        new, ours, theirs = [], [], []
        for j, f in enumerate(a.forms):
            extended = [*basis, *(a.forms[x] for x in new)]
            c = linalg.coordinates(f, extended, q.field) if extended else (() if not any(f) else None)
            if c is None:
                new.append(j)
                continue
            if not basis:
                continue  # the relation among the atom's own forms was filtered
            whole, den = R.whole_form(c, q.field)
            if any(whole[: len(basis)]) or not new:
                ours.append(q.field.linear([F.col(f"b{i}") for i in range(len(basis))], list(whole[: len(basis)])))
                theirs.append(q.field.linear([F.col(f"_k{j}"), *(F.col(f"_k{x}") for x in new)], [q.field.of(den), *(q.field.neg(x) for x in whole[len(basis) :])]))
        basis = [*basis, *(a.forms[j] for j in new)]
        steps.append(JoinStep(pick, side, tuple(ours), tuple(theirs), tuple(new), tuple(basis)))
    return steps


def solved_join(q: LinearQuery, db: Database, deal: R.Deal | None = None) -> R.Guard:
    """All atoms joined one by one, with annotations multiplied into a column ann of the guard's frame. deal: the tuples of
    relations too large for every task lie in tasks by it, and what is joined before them goes to every task if it is small
    enough."""
    df, width, rows, lies = None, 0, inf, []
    for s in join_steps(q, db):
        a = q.atoms[s.atom]
        n = db.rows(a.name)
        if df is None:
            df, rows = s.side.withColumnRenamed("_a", "ann"), n
            if deal is not None and far(n):
                df, lies = R.dealt(df, a, deal, q.field, "_k"), ["_w"]
        else:
            on = reduce(lambda x, y: x & y, (o == t for o, t in zip(s.ours, s.theirs, strict=True))) if s.ours else None
            if on is None:
                df = crossed(df, s.side, rows, n)
            elif lies and far(n) and not s.new:
                df = _found(df, s.basis, s.side, a, deal, db, "_k", "_a")
            elif deal is not None and far(n) and rows <= shared.FEW:
                df, lies = F.broadcast(df).join(R.dealt(s.side, a, deal, q.field, "_k"), on), ["_w"]
            else:
                df = df.join(few(s.side, n), on)
            rows = inf if s.ours else rows * n
            df = df.withColumn("ann", db.semiring.times(F.col("ann"), F.col("_a"))).drop("_a")
        for j in s.new:
            df = df.withColumnRenamed(f"_k{j}", f"b{width}")
            width += 1
        df = df.select(*(f"b{i}" for i in range(width)), "ann", *lies)
    return R.Guard(df, s.basis, deal=deal if lies else None)


def join_bound(q: LinearQuery, db: Database) -> float:
    """Rows of the largest intermediate result of solved_join, at most: each step multiplies by the largest number of
    tuples that one value of its keys meets. One job; kept with the statistics."""
    if ("joined", q) not in db._stats:
        steps, parts = join_steps(q, db), None
        for i, s in enumerate(steps):
            keyed = s.side.groupBy(*(t.alias(f"_t{j}") for j, t in enumerate(s.theirs) if i)).agg(F.count("*").alias("n"))
            one = keyed.agg(F.lit(i).alias("step"), F.coalesce(F.max("n"), F.lit(0)).cast("double").alias("n"))
            parts = one if parts is None else parts.unionAll(one)
        rows, most = 1.0, 1.0
        for r in sorted(parts.collect()):  # one row an atom
            rows *= r.n
            most = max(most, rows)
        db._stats["joined", q] = most
    return db._stats["joined", q]


def _joined_pairs(q: LinearQuery, db: Database) -> DataFrame | None:
    """The sums of solved_join where it begins with a cross product of two unary relations and all others are found by
    key, made pair by pair; else none."""
    if any(db.rows(a.name) == inf for a in q.atoms):
        return None
    steps = join_steps(q, db)
    if len(steps) < 3 or any(len(q.atoms[s.atom].forms) != 1 for s in steps) or any(s.ours for s in steps[:2]) or not all(s.ours for s in steps[2:]):
        return None
    factors = tuple((s.side.select(F.col("_k0").alias(f"b{i}"), F.col("_a").alias(f"_a{s.atom}")), db.rows(q.atoms[s.atom].name)) for i, s in enumerate(steps[:2]))
    return pairs.pair_sums(q, R.Guard(factors[0][0].crossJoin(factors[1][0]), steps[1].basis, factors), db)


def eval_joined(q: LinearQuery, db: Database, drop_zero: bool = False) -> DataFrame:
    """Binary joins on solved keys, then sums: no guard, no bound."""
    q.check_safe()
    if not q.head and (parts := _joined_pairs(q, db)) is not None:
        return _finish(parts, db, [], drop_zero)
    got = solved_join(q, db, R.deal_of(q, db))
    cols = [F.col(c) for c in got.columns]
    values = [R.value_of(f, got.basis, cols, q.field) for f in q.head]
    return _finish(got.df.select(*(v.alias(f"h{i}") for i, (v, _) in enumerate(values)), "ann"), db, [d for _, d in values], drop_zero, _single(q, got.basis))


# ---- trees --------------------------------------------------------------------------------------------------


def _on_tree(q: LinearQuery, db: Database, tree: trees.SpanTree, node_of, drop_zero: bool, watch=None) -> DataFrame:
    """Node queries bottom-up. node_of(v, bag, atoms, db): a frame with values of a basis, and with ann if it has
    multiplied the annotations already. watch(v, guard, message): sees each node, and may return another frame of
    the message's rows; seen(v, guard), if it has that attribute, another guard."""
    q.check_safe()
    heads: dict[int, tuple[Form, ...]] = {}
    for v in reversed(range(len(tree.parent))):
        atoms = tuple([q.atoms[a] for a in tree.covers[v]] + [Atom(trees.message(u), heads[u]) for u in tree.children(v)])
        node = LinearQuery(q.variables, tuple(tree.interface(q, v)), atoms, q.field)
        guard = node_of(v, list(tree.bags[v]), node, db)
        if hasattr(watch, "seen"):
            guard = watch.seen(v, guard)
        if v and not q.field.characteristic:  # messages take whole values
            scaled = []
            for f in node.head:
                _, den = R.whole_form(linalg.coordinates(f, list(guard.basis), q.field), q.field)
                scaled.append(linalg.scale(f, q.field.of(den), q.field))
            node = LinearQuery(q.variables, tuple(scaled), atoms, q.field)
        heads[v] = node.head
        if "ann" in guard.df.columns:
            cols = [F.col(c) for c in guard.columns]
            values = [R.value_of(f, guard.basis, cols, q.field) for f in node.head]
            out = _finish(guard.df.select(*(x.alias(f"h{i}") for i, (x, _) in enumerate(values)), "ann"), db, [d for _, d in values], bool(v) or drop_zero)
        else:
            out = eval_guarded(node, guard, db, bool(v) or drop_zero)
        if watch:
            out = watch(v, guard, out) or out
        if v == 0:
            return out
        keys = [F.col(f"h{i}").alias(f"c{i}") for i in range(len(node.head))]
        db = db.plus({trees.message(v): AnnotatedRelation(out.select(*keys, "ann"), len(node.head), db.semiring)})
    raise AssertionError("a tree has a root")


def eval_by_value(q: LinearQuery, db: Database, tree: trees.SpanTree | None = None, drop_zero: bool = False, watch=None) -> DataFrame:
    """Each node by the dense evaluator over its bag, messages included; messages hold whole values."""
    tree = tree or trees.find_tree(q, "dim")

    def node_of(v, bag, node, now):
        return R.product_guard(node, now, [node.body[i] for i in linalg.independent(node.body, q.field)], node)

    return _on_tree(q, db, tree, node_of, drop_zero, watch)


def eval_by_domain(q: LinearQuery, db: Database, tree: trees.SpanTree | None = None, drop_zero: bool = False, watch=None) -> DataFrame:
    """Each bag guarded by the product of the unary reducts of a least vector cover, projected on the bag."""
    tree = tree or trees.find_tree(q, "vec")
    stats = db.stats(a.name for a in q.atoms)
    costs = [log(max(2, min(stats[a.name]["distinct"][a.forms.index(f)] for a in q.atoms if f in a.forms))) for f in q.body]

    def node_of(v, bag, node, now):
        return R.onto(R.product_guard(q, db, list(covers.vector_cover(q, bag, costs)), node), bag, q.field)

    return _on_tree(q, db, tree, node_of, drop_zero, watch)


def eval_by_size(q: LinearQuery, db: Database, tree: trees.SpanTree | None = None, join: str = "levelwise", drop_zero: bool = False, watch=None) -> DataFrame:
    """Each bag guarded by the worst-case-optimal join of the reducts of a least fractional cover, projected on it."""
    tree = tree or trees.find_tree(q, "frac")

    def node_of(v, bag, node, now):
        return R.onto(sparse_guard(q, db, covers.cover_number(q, bag), join, node), bag, q.field)

    return _on_tree(q, db, tree, node_of, drop_zero, watch)


def eval_unguarded(q: LinearQuery, db: Database, tree: trees.SpanTree | None = None, drop_zero: bool = False, watch=None) -> DataFrame:
    """Baseline: the same factorisation without guards, each node by plain joins of its atoms and messages."""
    tree = tree or trees.find_tree(q, "frac")
    return _on_tree(q, db, tree, lambda v, bag, node, now: solved_join(node, now), drop_zero, watch)


def eval_finite_field(q: LinearQuery, db: Database, tree: trees.SpanTree | None = None, drop_zero: bool = False) -> DataFrame:
    """Tree evaluation where the domain is a finite field; bags have at most order**dimension values."""
    if not q.field.characteristic:
        raise ValueError("the field is infinite")
    return eval_by_value(q, db, tree, drop_zero)


# ---- baselines ----------------------------------------------------------------------------------------------


def _slots(q: LinearQuery) -> tuple[list[Form], list[str]]:
    at = [(i, j) for i, a in enumerate(q.atoms) for j in range(len(a.forms))]
    return [q.atoms[i].forms[j] for i, j in at], [f"_k{i}_{j}" for i, j in at]


def _sides(q: LinearQuery, names: list[str], whole, new: set[str]) -> tuple[Column, Column]:
    """An equation over columns as two equal values: of the columns that were there before, and of the new ones. A join
    can take each from one of its inputs."""
    old = [(F.col(n), w) for n, w in zip(names, whole, strict=True) if n not in new]
    add = [(F.col(n), q.field.neg(w)) for n, w in zip(names, whole, strict=True) if n in new]
    return tuple(q.field.linear([c for c, _ in part], [w for _, w in part]) for part in (old, add))


def _baseline(q: LinearQuery, db: Database, conditions, drop_zero: bool) -> DataFrame:
    """conditions: (what makes the predicate when an atom brings some new columns, columns that it uses) each."""
    q.check_safe()
    forms, names = _slots(q)
    df, ann, tests, rows = None, None, conditions(forms, names), inf
    have: set[str] = set()
    for i, a in enumerate(q.atoms):
        rel = db[a.name]
        side = rel.df.select(*(F.col(k).alias(f"_k{i}_{j}") for j, k in enumerate(rel.keys)), F.col("ann").alias(f"_a{i}"))
        new, n = {f"_k{i}_{j}" for j in range(rel.arity)}, db.rows(a.name)
        have |= new
        ready = [t(new) for t, uses in tests if uses <= have]
        tests = [(t, uses) for t, uses in tests if not uses <= have]
        if df is None:
            df, rows = side.where(reduce(lambda x, y: x & y, ready)) if ready else side, n
        else:
            df = df.join(few(side, n), reduce(lambda x, y: x & y, ready)) if ready else crossed(df, side, rows, n)
            rows = inf if ready else rows * n
        ann = F.col(f"_a{i}") if ann is None else db.semiring.times(ann, F.col(f"_a{i}"))
    base = linalg.independent(forms, q.field)
    values = [R.value_of(f, [forms[i] for i in base], [F.col(names[i]) for i in base], q.field) for f in q.head]
    return _finish(df.select(*(v.alias(f"h{i}") for i, (v, _) in enumerate(values)), ann.alias("ann")), db, [d for _, d in values], drop_zero)


def eval_bruteforce(q: LinearQuery, db: Database, drop_zero: bool = False) -> DataFrame:
    """Baseline: all combinations of tuples; those whose linear system has a solution count. The last atom's columns stand
    on one side of each equation, so the optimiser may find its tuples by key instead of trying them all."""

    def conditions(forms, names):
        equations = [R.whole_form(d, q.field)[0] for d in linalg.dependencies(forms, q.field)]

        def every(new: set[str]) -> Column:
            return reduce(lambda x, y: x & y, (old == add for old, add in (_sides(q, names, e, new) for e in equations)))

        return [(every, set(names))] if equations else []

    return _baseline(q, db, conditions, drop_zero)


def eval_where(q: LinearQuery, db: Database, drop_zero: bool = False) -> DataFrame:
    """Baseline: a plain query with the equations as predicates, in the order of the atoms; the optimiser does the rest."""

    def conditions(forms, names):
        out = []
        for d in linalg.dependencies(forms, q.field):
            whole, _ = R.whole_form(d, q.field)

            def test(new: set[str], whole=whole) -> Column:
                old, add = _sides(q, names, whole, new)
                return old == add

            out.append((test, {n for n, w in zip(names, whole, strict=True) if w}))
        return out

    return _baseline(q, db, conditions, drop_zero)


def eval_inequality_pairs(q: LinearQuery, db: Database, drop_zero: bool = False) -> DataFrame:
    """Baseline: each equation as two inequalities, the form in which additive inequalities are evaluated. They are tried
    on pairs whose sides lie in one interval of four numbers, as those do that satisfy both."""

    def conditions(forms, names):
        out = []
        for d in linalg.dependencies(forms, q.field):
            whole, _ = R.whole_form(d, q.field)

            def test(new: set[str], whole=whole) -> Column:
                old, add = _sides(q, names, whole, new)
                return (F.shiftright(old, 2) == F.shiftright(add, 2)) & (old <= add) & (old >= add)

            out.append((test, {n for n, w in zip(names, whole, strict=True) if w}))
        return out

    return _baseline(q, db, conditions, drop_zero)


def inequality_bag(q: LinearQuery, db: Database) -> tuple[list[int], R.Guard]:
    """The atoms of the first bag of the inequality plan, a whole cover of the span taken greedily, and their join."""
    if q.field.characteristic:
        raise ValueError("a finite field has no order")
    inside: list[int] = []
    while not linalg.contains([f for i in inside for f in q.atoms[i].forms], q.span(), q.field):
        gain = lambda i: linalg.rank([f for k in (*inside, i) for f in q.atoms[k].forms], q.field)  # noqa: E731, B023
        inside.append(max((i for i in range(len(q.atoms)) if i not in inside), key=lambda i: (gain(i), -i)))
    return inside, solved_join(LinearQuery(q.variables, tuple(q.span()), tuple(q.atoms[i] for i in inside), q.field), db, R.deal_of(q, db))


def eval_inequality_bags(q: LinearQuery, db: Database, drop_zero: bool = False) -> DataFrame:
    """Baseline: the tree plan of the inequality form, which has two adjacent bags for the variables of a condition.

    Atoms that share variables are joined in one bag, up to a whole cover of the span; every other atom is a bag of its
    own with a variable for each argument, tied to the first by pairs of inequalities. The first bag has up to size**c
    rows for a whole cover of c atoms, however few of them the conditions leave: that is the cost of this plan. The
    range that a pair of inequalities leaves is a run of equal keys.
    """
    q.check_safe()
    inside, bag = inequality_bag(q, db)
    cols = [F.col(c) for c in bag.columns]
    df = bag.df
    for i, a in enumerate(q.atoms):
        if i in inside:
            continue
        rel, on = db[a.name], None
        side = rel.df.select(*(F.col(k).alias(f"_k{j}") for j, k in enumerate(rel.keys)), F.col("ann").alias("_a"))
        for j, f in enumerate(a.forms):
            value, den = R.value_of(f, bag.basis, cols, q.field)
            test = value == F.col(f"_k{j}") * F.lit(den).cast("long")  # key <= value and key >= value: one run of equal keys
            on = test if on is None else on & test
        if bag.deal and far(db.rows(a.name)):
            df = _found(df, bag.basis, side, a, bag.deal, db, "_k", "_a")
        else:
            df = df.crossJoin(side) if on is None else df.join(side, on)
        df = df.withColumn("ann", db.semiring.times(F.col("ann"), F.col("_a"))).select(*bag.columns, "ann", *(["_w"] if bag.deal else []))
    values = [R.value_of(f, bag.basis, cols, q.field) for f in q.head]
    return _finish(df.select(*(v.alias(f"h{i}") for i, (v, _) in enumerate(values)), "ann"), db, [d for _, d in values], drop_zero, _single(q, bag.basis))


EVALUATORS = {
    "dense": eval_dense,
    "grid": eval_grid,
    "sparse": eval_sparse,
    "joined": eval_joined,
    "value": eval_by_value,
    "domain": eval_by_domain,
    "size": eval_by_size,
    "unguarded": eval_unguarded,
    "where": eval_where,
    "inequalities": eval_inequality_pairs,
    "inequality_bags": eval_inequality_bags,
    "bruteforce": eval_bruteforce,
}
