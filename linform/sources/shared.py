"""Intermediate results as written tables in the shared folder.

Tables stay until they are asked to go: what is written inside `scope` is deleted at its end, and `clean` deletes all
that this process has written. Results that read a written table have to be consumed, or saved, before.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from math import inf

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

_OWN: list[str] = []
_WRITTEN: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir; where that is unset, one of our own, in local runs only."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found is None:
        master = spark.sparkContext.master
        if not master.startswith("local") or master.startswith("local-cluster"):
            raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        if not _OWN:
            _OWN.append(f"file://{tempfile.mkdtemp(prefix='linform-')}")
        found = _OWN[0]
    return found.rstrip("/")


def new_path(spark: SparkSession, name: str) -> str:
    path = f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"
    _WRITTEN.append(path)
    return path


def written(df: DataFrame, name: str) -> DataFrame:
    """df written and read again: its plan is run once however often it is used, and lost executors cost no rerun."""
    path = new_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def clean(spark: SparkSession, keep: int = 0) -> int:
    """Delete what this process has written in the shared folder, but for the first `keep` paths; returns how many."""
    gone = _WRITTEN[keep:]
    del _WRITTEN[keep:]
    for path in gone:
        at = spark._jvm.org.apache.hadoop.fs.Path(path)
        at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)
    return len(gone)


@contextmanager
def scope(spark: SparkSession) -> Iterator[None]:
    """What is written inside is deleted at the end, also after an error."""
    before = len(_WRITTEN)
    try:
        yield
    finally:
        clean(spark, before)


#: Rows at most of a frame that goes whole to every task; pairs that one task of a cross product makes.
FEW, PAIRS = 1_000_000, 100_000_000


def few(df: DataFrame, rows: float) -> DataFrame:
    """df, sent whole to every task of its next join if it is known to have few rows: the other side is then not dealt."""
    return F.broadcast(df) if rows <= FEW else df


def far(rows: float) -> bool:
    """Whether a frame has too many rows to go to every task, as far as rows are known."""
    return FEW < rows < inf


def crossed(left: DataFrame, right: DataFrame, n_left: float, n_right: float) -> DataFrame:
    """All pairs. Where rows are known, the fewer go to every task and the others are dealt over many tasks first, as
    small frames lie in few partitions however many pairs they make."""
    if min(n_left, n_right) > FEW:
        return left.crossJoin(right)
    tasks = 4 * left.sparkSession.sparkContext.defaultParallelism
    if n_left * n_right < inf:
        tasks = max(tasks, int(n_left * n_right / PAIRS))
    many = PAIRS < n_left * n_right < inf
    if n_right <= n_left:
        return (left.repartition(min(tasks, int(n_left))) if many else left).crossJoin(F.broadcast(right))
    return F.broadcast(left).crossJoin(right.repartition(min(tasks, int(n_right))) if many else right)


def redealt(df: DataFrame, key: str) -> DataFrame:
    """df with a long or binary key rewritten to itself, so that a join deals df anew by it.

    A sum by the key leaves its rows dealt by it, a join would then take them as they are, and adaptive
    execution could not split the tasks in which the other side has a hot key.
    """
    same = F.concat(F.col(key), F.unhex(F.lit(""))) if dict(df.dtypes)[key] == "binary" else F.col(key).bitwiseXOR(F.lit(0).cast("long"))
    return df.withColumn(key, same)
