"""Streams: deltas of one atom against static relations, and windows of event time as ticks.

A query is linear in each atom, so what new tuples of one atom add to the answer is the query with that atom
replaced by the new tuples. With the other atoms static this is a stream-static join and a running sum; it holds
for every semiring as long as tuples are only added.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linform.operators import reducts as R
from linform.operators.evaluate import solved_join
from linform.operators.relation import AnnotatedRelation, Database, keys_of
from linform.plans.query import Atom, LinearQuery

DELTA = "_delta"


def stream_delta(q: LinearQuery, atom: int, stream: DataFrame, db: Database) -> DataFrame:
    """The running answer for a stream (c0, c1, ..., ann) of new tuples of one atom; write it in update or complete
    mode. The other atoms' joins come after the stream's own, so state is kept for the sums only."""
    q.check_safe()
    rest = [a for i, a in enumerate(q.atoms) if i != atom]
    own = q.atoms[atom]
    moved = LinearQuery(q.variables, q.head, (Atom(DELTA, own.forms), *rest), q.field)
    arity = len(own.forms)
    cols = ["ann", *keys_of(arity)]
    more = db.plus({DELTA: AnnotatedRelation(stream.select(*cols), arity, db.semiring)})
    got = solved_join(moved, more)
    values = [R.value_of(f, got.basis, [F.col(c) for c in got.columns], q.field) for f in q.head]
    if any(d != 1 for _, d in values):
        raise ValueError("a head form is not whole; scale the query first")
    out = got.df.select(*(v.alias(f"h{i}") for i, (v, _) in enumerate(values)), "ann")
    heads = [f"h{i}" for i in range(len(values))]
    summed = db.semiring.plus(F.col("ann")).cast(db.semiring.kind).alias("ann")
    return out.groupBy(*heads).agg(summed) if heads else out.groupBy().agg(summed)


def ticks(events: DataFrame, at: str, size: str, slide: str | None = None, late: str = "1 hour", keys: list[str] | None = None, ann=None) -> DataFrame:
    """Tumbling or sliding windows of event time with a watermark: (window start, keys, ann)."""
    window = F.window(at, size, slide) if slide else F.window(at, size)
    got = events.withWatermark(at, late).groupBy(window, *(keys or [])).agg((F.count("*") if ann is None else ann).alias("ann"))
    return got.select(F.col("window.start").alias("start"), *(keys or []), "ann")


def session_ticks(events: DataFrame, at: str, gap: str, key: str, late: str = "1 hour") -> DataFrame:
    got = events.withWatermark(at, late).groupBy(F.session_window(at, gap).alias("w"), key).agg(F.count("*").alias("ann"))
    return got.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), key, "ann")


def lag_pairs(left: DataFrame, right: DataFrame, key: str, at: str, within: str, late: str = "1 hour") -> DataFrame:
    """Stream-stream pairs of a key where right comes at most `within` after left; both watermarks bound the state."""
    a = left.withWatermark(at, late).alias("a")
    b = right.withWatermark(at, late).alias("b")
    on = F.expr(f"a.{key} = b.{key} and b.{at} >= a.{at} and b.{at} <= a.{at} + interval {within}")
    return a.join(b, on).select(F.col(f"a.{key}").alias(key), F.col(f"a.{at}").alias("first"), F.col(f"b.{at}").alias("second"))

