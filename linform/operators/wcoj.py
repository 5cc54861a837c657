"""Worst-case-optimal joins of reducts as compositions of DataFrame operators.

A reduct is a frame of distinct rows over some of the columns b0, b1, ..., with the numbers of those columns. Further
columns (annotations of the rows) are carried along.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce
from math import inf, prod

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linform.sources import shared
from linform.sources.shared import crossed, redealt, written

Reducts = list[tuple[DataFrame, list[int]]]


def _projection(frame: DataFrame, have: list[int], want: list[int]) -> tuple[DataFrame, list[str]]:
    """The rows of some columns; once all are wanted, with what the reduct carries."""
    cols = [f"b{i}" for i in want]
    if set(want) != set(have):
        return frame.select(*cols).distinct(), []
    carried = [c for c in frame.columns if c not in cols]
    return frame.select(*cols, *carried), carried


def _carried(frame: DataFrame, have: list[int]) -> list[str]:
    return [c for c in frame.columns if c not in {f"b{i}" for i in have}]


def _kept(state: DataFrame, offer: DataFrame, carried: list[str], on: list[str]) -> DataFrame:
    """The bindings that a reduct has, with what it carries."""
    return state.join(offer, on) if carried else state.join(offer, on, "left_semi")


def levelwise(reducts: Reducts, order: list[int], proposals: list[DataFrame] | None = None, tasks: int | None = None) -> DataFrame:
    """Bind one column after another. Each binding is prolonged by the reduct that offers it the fewest values, and
    the other reducts filter, so no level holds more rows than the size bound of the query it answers.

    Jobs run while the plan is built: one for each level after the first two, and counts where a level is a cross product.

    The rows are split by their cheapest reduct before the joins, so none is dealt to a reduct that it doesn't use;
    a small prefix goes to every task of a reduct that is to lie in so many tasks by a column _w (dealt there only, its
    projections as they come);
    the bindings are written before the split, so deep queries do not run their first levels again and again, and
    every join deals both sides, so that adaptive execution can split hot prefixes. proposals: filled with the frames
    of prolonged bindings before the other reducts filter them, for those who count what a join visits.
    """
    bound: list[int] = []
    state: DataFrame | None = None
    rows: float | None = None  # of the state, as far as it is a relation or a cross product of some
    for t in order:
        offers = []
        for frame, have in reducts:
            if t in have:
                on = [i for i in bound if i in have]
                offers.append((*_projection(frame, have, [*on, t]), [f"b{i}" for i in on]))
        if state is None:
            state = offers[0][0]
            for offer, carried, _ in offers[1:]:
                state = _kept(state, offer, carried, [f"b{t}"])
            if proposals is not None:
                proposals.append(state)
        elif any(on for _, _, on in offers):
            state, rows = _prolong(state, offers, t, proposals, tasks), inf
        else:
            rows = state.count() if rows is None else rows
            values = reduce(lambda x, o: _kept(x, o[0], o[1], [f"b{t}"]), offers[1:], offers[0][0])
            n = values.count()
            state, rows = crossed(state, values, rows, n), rows * n
            if proposals is not None:
                proposals.append(state)
        bound.append(t)
    return state


def _prolong(state: DataFrame, offers: list[tuple[DataFrame, list[str], list[str]]], t: int, proposals: list[DataFrame] | None = None, tasks: int | None = None) -> DataFrame:
    free, tied = [o for o in offers if not o[2]], [o for o in offers if o[2]]
    new = [f"b{t}", *(c for _, carried, _ in offers for c in carried)]
    if len(tied) == 1:
        offer, _, on = tied[0]
        if tasks and "_w" in offer.columns and state.count() <= shared.FEW:  # what is made stays in the reduct's tasks
            out = F.broadcast(state).join(offer.repartition(tasks, "_w"), on)
        else:
            out = state.join(redealt(offer, on[0]), on)
        if proposals is not None:
            proposals.append(out)
    else:
        counted = state
        for s, (offer, _, on) in enumerate(tied):
            counted = counted.join(redealt(offer.groupBy(*on).agg(F.count("*").alias(f"_n{s}")), on[0]), on)
        counted = written(counted, "bindings")  # each slice below reads it
        least = F.least(*(F.col(f"_n{s}") for s in range(len(tied))))
        taken, parts = F.lit(False), []
        for s, (offer, _, on) in enumerate(tied):
            mine = counted.where((F.col(f"_n{s}") == least) & ~taken).select(*state.columns)
            part = mine.join(redealt(offer, on[0]), on)
            if proposals is not None:
                proposals.append(part)
            for u, (other, carried, with_) in enumerate(tied):
                if u != s:
                    part = _kept(part, redealt(other, with_[0]), carried, [*with_, f"b{t}"])
            parts.append(part.select(*state.columns, f"b{t}", *(c for _, carried, _ in tied for c in carried)))
            taken = taken | (F.col(f"_n{s}") == least)
        out = reduce(DataFrame.unionByName, parts)
    for offer, carried, _ in free:
        out = _kept(out, offer, carried, [f"b{t}"])
    return out.select(*state.columns, *new)


#: Rows that a cell of the hypercube should hold, bindings that a cell prolongs at a time.
CELL_ROWS, AT_ONCE = 500_000, 1 << 16


def shares(sizes: list[int], haves: list[list[int]], order: list[int], cells: int) -> dict[int, int]:
    """How many parts each column is cut in, powers of two, at most `cells` together: those with least rows in a cell."""

    def cuts(columns: int, left: int) -> Iterator[tuple[int, ...]]:
        if not columns:
            yield ()
            return
        for e in range(left + 1):
            yield from ((1 << e, *rest) for rest in cuts(columns - 1, left - e))

    every = (dict(zip(order, cut, strict=True)) for cut in cuts(len(order), max(1, cells).bit_length() - 1))
    return min(every, key=lambda cut: (load(sizes, haves, cut), prod(cut.values())))


def load(sizes: list[int], haves: list[list[int]], cut: dict[int, int]) -> float:
    """Rows in a cell, were values spread evenly."""
    return sum(n / prod(cut[i] for i in have) for n, have in zip(sizes, haves, strict=True))


class Trie:
    """Sorted distinct rows as levels of nodes: value codes, and where each node's children begin."""

    def __init__(self, rows: np.ndarray):
        rows = rows[np.lexsort(rows.T[::-1])]
        n, new = len(rows), np.zeros(len(rows), bool)
        self.values, self.starts, parents = [], [], np.zeros(n, np.int64)
        for level in range(rows.shape[1]):
            new = new | np.r_[True, rows[1:, level] != rows[:-1, level]][:n]
            at = np.flatnonzero(new)
            self.values.append(rows[at, level])
            above = len(self.values[-2]) if level else 1
            self.starts.append(np.searchsorted(parents[at], np.arange(above + 1)))
            parents = np.cumsum(new) - 1
        self.keys = [np.repeat(np.arange(len(s) - 1), np.diff(s)) << 32 | v for s, v in zip(self.starts, self.values, strict=True)]


def local_join(rows: list[np.ndarray], haves: list[list[int]], order: list[int]) -> Iterator[np.ndarray]:
    """The join of distinct rows in memory, one column after another: each binding is prolonged by the relation that
    offers it the fewest values, the others are searched. Bindings go depth first, AT_ONCE at a time."""
    for out, _ in local_matches(rows, haves, order):
        yield out


def local_matches(rows: list[np.ndarray], haves: list[list[int]], order: list[int]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """The join as local_join makes it, with the place of each binding's row in each relation once that is sorted by its
    columns in the order given."""
    if not all(len(r) for r in rows):
        return
    places = {i: [(r, have.index(i)) for r, have in enumerate(haves) if i in have] for i in order}
    codes = {i: np.unique(np.concatenate([rows[r][:, c] for r, c in places[i]])) for i in order}
    tries = []
    for r, have in enumerate(haves):
        mine = [i for i in order if i in have]
        tries.append(Trie(np.stack([np.searchsorted(codes[i], rows[r][:, have.index(i)]) for i in mine], axis=1)))
    levels = {i: [(r, [j for j in order if j in haves[r]].index(i)) for r, _ in places[i]] for i in order}

    def prolong(depth: int, bound: np.ndarray, nodes: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """bound: codes of the columns so far, a row each; nodes: of each relation the node reached."""
        if depth == len(order):
            yield np.stack([codes[i][c] for i, c in zip(order, bound, strict=True)], axis=1), nodes
            return
        t = order[depth]
        low = np.stack([tries[r].starts[d][nodes[r]] for r, d in levels[t]])
        counts = np.stack([tries[r].starts[d][nodes[r] + 1] for r, d in levels[t]]) - low
        pick = counts.argmin(axis=0)
        least = counts.min(axis=0)
        ends = np.cumsum(least)
        at = 0
        while at < len(least):
            done = ends[at - 1] if at else 0
            end = max(at + 1, int(np.searchsorted(ends, done + AT_ONCE, "right")))
            who = np.repeat(np.arange(at, end), least[at:end])
            if len(who):
                step = np.arange(len(who)) - np.repeat(ends[at:end] - least[at:end] - done, least[at:end])
                value = np.empty(len(who), np.int64)
                for s, (r, d) in enumerate(levels[t]):
                    mine = pick[who] == s
                    value[mine] = tries[r].values[d][low[s][who[mine]] + step[mine]]
                keep, found = np.ones(len(who), bool), nodes[:, who].copy()
                for r, d in levels[t]:
                    key = nodes[r][who] << 32 | value
                    place = np.minimum(np.searchsorted(tries[r].keys[d], key), len(tries[r].keys[d]) - 1)
                    keep &= tries[r].keys[d][place] == key
                    found[r] = place
                if keep.any():
                    yield from prolong(depth + 1, np.vstack([bound[:, who[keep]], value[None, keep]]), found[:, keep])
            at = end

    yield from prolong(0, np.zeros((0, 1), np.int64), np.zeros((len(rows), 1), np.int64))


def hypercube(reducts: Reducts, order: list[int], cells: int | None = None) -> DataFrame:
    """One exchange: every column is cut in a number of shares, by the reducts' sizes, a cell is one share of each, and
    a row goes to all cells that agree with its columns. A cell is joined in memory by a worst-case-optimal join over
    sorted Arrow columns, so no cell exceeds its size bound; a hot value meets as many cells as the other columns have
    shares. The reducts are written first, as their sizes decide on the cells: CELL_ROWS rows in each at most.
    """
    brought = [_carried(frame, have) for frame, have in reducts]
    reducts = [(written(frame, "reduct"), have) for frame, have in reducts]
    sizes, haves = [frame.count() for frame, _ in reducts], [have for _, have in reducts]
    spark = reducts[0][0].sparkSession
    cells = cells or max(2 * spark.sparkContext.defaultParallelism, sum(sizes) // CELL_ROWS + 1)
    cut = shares(sizes, haves, order, cells)
    while load(sizes, haves, cut) > CELL_ROWS:
        cells *= 2
        cut = shares(sizes, haves, order, cells)
    tagged: DataFrame | None = None
    for r, (frame, have) in enumerate(reducts):
        cell = F.lit(0)
        for i in order:
            share = F.pmod(F.xxhash64(f"b{i}"), F.lit(cut[i])).cast("int") if i in have else F.explode(F.array(*map(F.lit, range(cut[i]))))
            frame = frame.withColumn(f"_s{i}", share)
            cell = cell * cut[i] + F.col(f"_s{i}")
        one = frame.select(cell.alias("_cell"), F.lit(r).alias("_r"), *((F.col(f"b{i}") if i in have else F.lit(None).cast("long")).alias(f"b{i}") for i in order), *brought[r])
        tagged = one if tagged is None else tagged.unionByName(one, allowMissingColumns=True)
    dealt = tagged.repartitionById(prod(cut.values()), "_cell")  # one cell a partition

    def joined(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held = pa.Table.from_batches(batches) if (batches := list(batches)) else None
        if held is None:
            return
        number = held.column("_r").to_numpy()
        parts = [held.filter(pa.array(number == r)) for r in range(len(haves))]
        rows = [np.stack([part.column(f"b{i}").to_numpy() for i in have], axis=1).astype(np.int64) for part, have in zip(parts, haves, strict=True)]
        more = []  # (relation, column sorted as the relation is)
        for r, (part, have) in enumerate(zip(parts, haves, strict=True)):
            by = np.lexsort([rows[r][:, have.index(i)] for i in reversed(order) if i in have])
            more += [(r, part.column(c).combine_chunks().take(pa.array(by))) for c in brought[r]]
        for out, at in local_matches(rows, haves, order):
            yield pa.RecordBatch.from_arrays([*(pa.array(out[:, k]) for k in range(len(order))), *(x.take(pa.array(at[r])) for r, x in more)], names=names)

    types = {c: t for frame, _ in reducts for c, t in frame.dtypes}
    names = [*(f"b{i}" for i in order), *(c for cs in brought for c in cs)]
    return dealt.mapInArrow(joined, ", ".join(f"{c} {types[c]}" for c in names))


def hypercube_frames(reducts: Reducts, order: list[int], cells: int = 64) -> DataFrame:
    """The same deal in DataFrames alone: cells are joined two by two, and each join deals its cells again."""
    side = max(1, round(cells ** (1 / max(1, len(order)))))
    parts: DataFrame | None = None
    done: list[int] = []
    for frame, have in sorted(reducts, key=lambda r: -len(r[1])):
        cell = F.lit(0)
        spread = frame
        for i in order:
            share = F.pmod(F.xxhash64(f"b{i}"), F.lit(side)).cast("int") if i in have else F.explode(F.array(*map(F.lit, range(side))))
            spread = spread.withColumn(f"_s{i}", share)
            cell = cell * side + F.col(f"_s{i}")
        spread = spread.withColumn("_cell", cell).select("_cell", *frame.columns)
        parts = spread if parts is None else parts.join(spread, ["_cell", *(f"b{i}" for i in have if i in done)])
        done += [i for i in have if i not in done]
    return parts.select(*(f"b{i}" for i in order), *(c for frame, have in reducts for c in _carried(frame, have)))


def binary(reducts: Reducts, order: list[int]) -> DataFrame:
    """Joins two by two, as the optimiser orders them: may exceed the size bound."""
    left, out, done = list(reducts), None, []
    while left:
        pick = max(range(len(left)), key=lambda r: (len(set(left[r][1]) & set(done)), -r)) if done else 0
        frame, have = left.pop(pick)
        on = [f"b{i}" for i in have if i in done]
        out = frame if out is None else out.join(frame, on) if on else out.crossJoin(frame)
        done += [i for i in have if i not in done]
    return out.select(*(f"b{i}" for i in order), *(c for frame, have in reducts for c in _carried(frame, have)))


def size_bound(sizes: list[int], weights) -> float:
    """Product of sizes to the power of their weights."""
    out = 1.0
    for n, w in zip(sizes, weights, strict=True):
        out *= max(1, n) ** float(w)
    return out


JOINS = {"levelwise": levelwise, "hypercube": hypercube, "hypercube_frames": hypercube_frames, "binary": binary}
