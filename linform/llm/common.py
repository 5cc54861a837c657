"""Helpers shared by the training-data operators: shared-folder tables, Arrow maps, components."""

from __future__ import annotations

import gc
from collections.abc import Callable, Hashable, Iterator
from typing import Any

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linform.sources.shared import new_path, redealt
from linform.sources.shared import written as materialise

__all__ = ["arrow_map", "asked_of", "connected_components", "held", "materialise", "new_path", "redealt", "row_ids", "texts_of"]

_HELD: dict[Hashable, Any] = {}


def held(key: Hashable, make: Callable[[], Any] = lambda: None) -> Any:
    """What a worker keeps from task to task under a key, made when first asked for. One key at a time: when a worker comes
    to another operator, what it knew for the last one goes, so memory does not add up over the stages of a job."""
    if key not in _HELD:
        _HELD.clear()
        gc.collect()  # tools refer to themselves
        pa.default_memory_pool().release_unused()
        _HELD[key] = make()
    return _HELD[key]


def asked_of(df: DataFrame, kept: list[str], source: str, kind: str | None = None) -> tuple[DataFrame, int]:
    """The kept columns of df with the source column (cast to a kind), and its number: one that is kept as it is goes to
    the workers once."""
    if source in kept and (kind is None or dict(df.dtypes)[source] == kind):
        return df.select(*kept), kept.index(source)
    return df.select(*kept, (F.col(source).cast(kind) if kind else F.col(source)).alias("_asked")), len(kept)


def arrow_map(df: DataFrame, fn: Callable[[pa.RecordBatch], pa.RecordBatch | dict], schema: str) -> DataFrame:
    """Apply fn to each record batch; a dict result is turned into a batch by column name."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                out = fn(batch)
                yield out if isinstance(out, pa.RecordBatch) else pa.RecordBatch.from_pydict(out)

    return df.mapInArrow(run, schema)


def row_ids(start: int, n: int) -> pa.Array:
    """Ids unique over the job: the task's partition in the high bits, its row number in the low ones.

    Stable only in a table that was written after they were given.
    """
    base = (TaskContext.get().partitionId() << 36) + start
    return pa.array(range(base, base + n), pa.int64())


def texts_of(column: pa.Array) -> list[str]:
    """Texts as Python strings, null as the empty text."""
    return [x or "" for x in column.to_pylist()]


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """(a, b) long edges -> (node, root): root is the least node reachable. Nodes without edges are left out.

    Alternates large-star and small-star contractions; each round is written to the shared folder, and the
    loop ends when a round leaves the edge set as it was. Hubs are pre-aggregated (partial min) and the joins
    back are plain equi-joins, which adaptive execution splits where a hub holds many edges.
    """
    pairs = edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u <> v").distinct()
    pairs = materialise(pairs, "edges")
    before = None
    for _ in range(max_rounds):
        state = pairs.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v")), F.sum(F.xxhash64("v", "u") % 1_000_003)).first()
        if state[0] == 0 or state == before:
            break
        before = state
        both = pairs.union(pairs.select(F.col("v"), F.col("u")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        large = both.where("v > u").join(redealt(least, "u"), "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(redealt(low, "u"), "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v")
        pairs = materialise(small.union(low.select("u", "m")).distinct(), "edges")
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    return pairs.select(F.col("u").alias("node"), F.col("v").alias("root")).union(pairs.select("v", "v").distinct())
