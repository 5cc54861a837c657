"""Operators around the methods: ordering, grouping sets, windows, as-of and interval joins, comparisons of results."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from linform.operators.relation import AnnotatedRelation


def top_k(result: DataFrame, k: int, by: str = "ann") -> DataFrame:
    """The k rows of largest value, ties by the other columns."""
    rest = [c for c in result.columns if c != by]
    return result.orderBy(F.desc(by), *rest).limit(k)


def top_k_per(result: DataFrame, keys: list[str], k: int, by: str = "ann") -> DataFrame:
    rest = [c for c in result.columns if c not in (*keys, by)]
    place = F.row_number().over(Window.partitionBy(*keys).orderBy(F.desc(by), *rest))
    return result.withColumn("_n", place).where(F.col("_n") <= k).drop("_n")


def roll_up(result: DataFrame, keys: list[str], ann: Column) -> DataFrame:
    """Sums over all prefixes of the keys; null where a key is summed out."""
    return result.rollup(*keys).agg(ann.alias("ann"))


def cube(result: DataFrame, keys: list[str], ann: Column) -> DataFrame:
    return result.cube(*keys).agg(ann.alias("ann"))


def window_kernel(signal: AnnotatedRelation, weights: list[int], low: int, high: int) -> DataFrame:
    """Convolution with a kernel on offsets 0, 1, ... over a dense index low..high: (h0, ann), by range windows.

    The index range is a property of the signal that the caller states; each weight is one lag of one window.
    """
    spark = signal.df.sparkSession
    block = 4096  # windows stay inside blocks; each block also sees the tail of the one before
    width = len(weights)
    grid = spark.range(low, high + width).select(F.col("id").alias("c0")).join(signal.df, "c0", "left")
    grid = grid.withColumn("_b", F.floor((F.col("c0") - low) / block))
    tail = F.pmod(F.col("c0") - low, F.lit(block)) >= block - (width - 1)
    both = grid.withColumn("_own", F.lit(True)).unionByName(grid.where(tail).withColumn("_b", F.col("_b") + 1).withColumn("_own", F.lit(False)))
    line = Window.partitionBy("_b").orderBy("c0")
    total = F.lit(0).cast("long")
    for i, w in enumerate(weights):
        total = total + F.coalesce(F.lag("ann", i).over(line) if i else F.col("ann"), F.lit(0)) * F.lit(w)
    return both.withColumn("_v", total).where("_own and _v <> 0").select(F.col("c0").alias("h0"), F.col("_v").alias("ann"))


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """Each left row with the latest right value of its key at or before its time; null if there is none.

    One union and one running window instead of a join on an inequality.
    """
    both = left.withColumn("_side", F.lit(1)).withColumn("_v", F.lit(None).cast(right.schema[value].dataType))
    other = right.select(key, at, F.col(value).alias("_v")).withColumn("_side", F.lit(0))
    line = Window.partitionBy(key).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0)
    merged = both.unionByName(other, allowMissingColumns=True).withColumn("_v", F.last("_v", ignorenulls=True).over(line))
    return merged.where("_side = 1").drop("_side").withColumnRenamed("_v", f"{value}_as_of")


def range_join(left: DataFrame, right: DataFrame, key: str, at: str, within: int) -> DataFrame:
    """Pairs of a key whose whole-number times differ by at most `within`: an equi-join on buckets of that width."""
    bucket = lambda c: F.floor(F.col(c) / F.lit(within + 1))
    low = left.withColumn("_b", bucket(at))
    other = right.select(key, F.col(at).alias(f"other_{at}"), *(F.col(c).alias(f"other_{c}") for c in right.columns if c not in (key, at)))
    high = other.withColumn("_b", F.explode(F.array(*(bucket(f"other_{at}") + i for i in (-1, 0, 1)))))
    return low.join(high, [key, "_b"]).where(F.abs(F.col(at) - F.col(f"other_{at}")) <= within).drop("_b")


def sessions(events: DataFrame, key: str, at: str, gap: int) -> DataFrame:
    """(key, first, last, n) of runs of a key with no gap longer than `gap`."""
    line = Window.partitionBy(key).orderBy(at)
    begins = F.coalesce((F.col(at) - F.lag(at).over(line) > gap).cast("int"), F.lit(1))
    told = events.withColumn("_s", begins).withColumn("_s", F.sum("_s").over(line.rowsBetween(Window.unboundedPreceding, 0)))
    return told.groupBy(key, "_s").agg(F.min(at).alias("first"), F.max(at).alias("last"), F.count("*").alias("n")).drop("_s")


def difference(a: DataFrame, b: DataFrame) -> DataFrame:
    """Rows that one result has more often than the other: empty exactly if they are equal."""
    return a.exceptAll(b).withColumn("side", F.lit("a")).unionAll(b.exceptAll(a).withColumn("side", F.lit("b")))


def common_support(a: AnnotatedRelation, b: AnnotatedRelation) -> DataFrame:
    return a.support().intersect(b.support())
