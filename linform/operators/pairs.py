"""Sums over all pairs of two unary relations whose forms find tuples of other unary relations, made inside tasks.

A guard that is such a cross product may have far more rows than anything that is read or returned. Here the larger factor
is dealt over many tasks, the other one and the relations looked up go to every task as sorted columns and as arrays over
their range, and a task returns what its pairs sum to. Every pair is tried; no pair is a row.
"""

from __future__ import annotations

from collections.abc import Iterator
from math import inf, prod

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linform.functions import linalg
from linform.operators.reducts import Guard, whole_form
from linform.operators.relation import Database
from linform.plans.query import LinearQuery
from linform.sources.shared import FEW, PAIRS

#: Longest range of an array of lookups.
RANGE = 1 << 25


def pair_sums(q: LinearQuery, guard: Guard, db: Database) -> DataFrame | None:
    """A frame with a column ann: sums of products over the guard's pairs, some rows of them for each task. None if the
    guard is no cross product of two relations with annotations, or too small, or something is too large for a task."""
    how = db.semiring.local
    if how is None or q.field.characteristic or len(guard.factors) != 2 or not PAIRS < prod(n for _, n in guard.factors) < inf:
        return None
    factors = sorted(((n, i, f) for i, (f, n) in enumerate(guard.factors)), key=lambda x: x[0])
    (few, small, held), (_, large, dealt) = factors
    number = [next((int(c[2:]) for c in f.columns if c.startswith("_a")), None) for _, _, f in factors]
    looked = [i for i in range(len(q.atoms)) if i not in number]
    if None in number or len(looked) != 1 or len(q.atoms[looked[0]].forms) != 1 or max(few, db.rows(q.atoms[looked[0]].name)) > FEW:
        return None
    whole, den = whole_form(linalg.coordinates(q.atoms[looked[0]].forms[0], list(guard.basis), q.field), q.field)
    by = [int(whole[large]), int(whole[small])]
    spark = held.sparkSession
    mine = held.select((F.col(f"b{small}") * by[1]).alias("k"), F.col(f"_a{number[0]}").alias("ann")).orderBy("k").toArrow()
    target = db[q.atoms[looked[0]].name].df.select((F.col("c0") * den).alias("k"), "ann").orderBy("k").toArrow()
    if not len(mine) or not len(target):
        return dealt.select(F.col(f"_a{number[1]}").alias("ann")).limit(0)
    low, high = (target.column("k")[x].as_py() for x in (0, -1))
    if high - low >= RANGE:
        return None
    places = np.full(high - low + 1, -1, np.int32)
    places[target.column("k").to_numpy() - low] = np.arange(len(target), dtype=np.int32)
    cost = lambda c: (c.combine_chunks().field("cost") if how == "least" else c).to_numpy(zero_copy_only=False) if how == "least" else c.to_numpy()
    if how == "sum":
        ours, theirs = mine.column("ann").to_numpy(), target.column("ann").to_numpy()
        if len(ours) * int(np.abs(ours).max()) * int(np.abs(theirs).max()) >= 1 << 62:
            return None
        values = np.zeros(len(places), np.int64)
        values[target.column("k").to_numpy() - low] = theirs
        sent = (mine.column("k").to_numpy(), ours, low, high, values)
    elif how == "least":
        sent = (mine.column("k").to_numpy(), cost(mine.column("ann")), low, high, places, cost(target.column("ann")), mine.column("ann").to_pylist(), target.column("ann").to_pylist())
    else:
        sent = (mine.column("k").to_numpy(), None, low, high, places >= 0)
    shared = spark.sparkContext.broadcast(sent)
    order = sorted([(number[1], 0), (number[0], 1), (looked[0], 2)])  # products are taken in the order of the atoms

    def inside(value: int) -> tuple[slice, np.ndarray]:
        keys, low, high = shared.value[0], shared.value[2], shared.value[3]
        at = slice(*np.searchsorted(keys, [low - value, high - value + 1]))
        return at, keys[at] + (value - low)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, least, best = 0, None, []
        for batch in batches:
            for value, ann in zip((np.asarray(batch.column(0)) * by[0]).tolist(), batch.column(1).to_pylist(), strict=True):
                at, found = inside(value)
                if how == "sum":
                    total += ann * int(np.dot(shared.value[1][at], shared.value[4][found]))
                elif how == "any":
                    if ann and shared.value[4][found].any():
                        yield pa.RecordBatch.from_pydict({"ann": [True]})
                        return
                else:
                    place = shared.value[4][found]
                    hit = np.flatnonzero(place >= 0)
                    if len(hit):
                        costs = shared.value[1][at][hit] + shared.value[5][place[hit]] + ann["cost"]
                        if least is None or costs.min() <= least:
                            best, least = ([] if least is None or costs.min() < least else best), int(costs.min())
                            best += [(ann, shared.value[6][at.start + int(h)], shared.value[7][int(place[h])]) for h in hit[costs == least]]
        if how == "sum" and total:
            if abs(total) >= 1 << 63:
                raise OverflowError("a sum leaves 64 bits")
            yield pa.RecordBatch.from_pydict({"ann": pa.array([total], pa.int64())})
        if best:
            made = [{"cost": least, "wit": [x for _, k in order for x in parts[k]["wit"]]} for parts in best]
            yield pa.RecordBatch.from_pydict({"ann": pa.array(made, types)})

    types = target.schema.field("ann").type
    tasks = 8 * spark.sparkContext.defaultParallelism
    rows = dealt.select(f"b{large}", F.col(f"_a{number[1]}").alias("ann")).repartition(tasks)
    return rows.mapInArrow(run, f"ann {db.semiring.kind}")
