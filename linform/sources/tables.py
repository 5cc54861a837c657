"""Readers, ingest and sinks."""

from __future__ import annotations

from fractions import Fraction
from math import lcm

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from linform.functions.semirings import COUNT, Semiring
from linform.operators.relation import AnnotatedRelation


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_text(spark: SparkSession, path: str, kind: str, schema: str) -> DataFrame:
    """CSV (with a header) or JSON lines, with a given schema."""
    reader = spark.read.schema(schema)
    return reader.option("header", True).csv(path) if kind == "csv" else reader.json(path)


def flatten(df: DataFrame) -> DataFrame:
    """Struct columns as columns named parent_child, as deep as they go."""
    while any(isinstance(f.dataType, T.StructType) for f in df.schema.fields):
        cols = []
        for f in df.schema.fields:
            if isinstance(f.dataType, T.StructType):
                cols += [F.col(f"`{f.name}`.`{c}`").alias(f"{f.name}_{c}") for c in f.dataType.names]
            else:
                cols.append(F.col(f"`{f.name}`"))
        df = df.select(*cols)
    return df


def cells(df: DataFrame, array: str, ids: list[str], width: int) -> DataFrame:
    """An array column as cells (ids, i, j, value) of rows of the given width."""
    out = df.select(*ids, F.posexplode(array).alias("_at", "value"))
    return out.select(*ids, F.floor(F.col("_at") / width).cast("long").alias("i"), (F.col("_at") % width).cast("long").alias("j"), "value")


def entries(df: DataFrame, column: str, ids: list[str]) -> DataFrame:
    """A map column as rows (ids, key, value)."""
    return df.select(*ids, F.explode(column).alias("key", "value"))


def dictionary(df: DataFrame, column: str) -> DataFrame:
    """(value, id): ids 0, 1, ... of the distinct values in their order.

    Values are dealt by range; only one count a partition meets in one place.
    """
    from pyspark.sql import Window

    values = df.select(F.col(column).alias("value")).where("value is not null").distinct().repartitionByRange("value").withColumn("_p", F.spark_partition_id())
    ranked = values.withColumn("_n", F.row_number().over(Window.partitionBy("_p").orderBy("value")))
    line = Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
    before = ranked.groupBy("_p").agg(F.count("*").alias("_c")).withColumn("_b", F.coalesce(F.sum("_c").over(line), F.lit(0)))
    return ranked.join(before, "_p").select("value", (F.col("_b") + F.col("_n") - 1).cast("long").alias("id"))


def day_tick(ts: Column, origin: str) -> Column:
    return F.datediff(ts, F.lit(origin).cast("date")).cast("long")


def hour_tick(ts: Column, origin: str) -> Column:
    return F.timestamp_diff("HOUR", F.lit(origin).cast("timestamp_ntz"), ts).cast("long")


def common_scale(values: list[Fraction]) -> int:
    """The common denominator that clears the given rationals: one scale for all columns of a connected query."""
    return lcm(*(Fraction(v).denominator for v in values)) if values else 1


def scaled(value: Column, by: int) -> Column:
    """A decimal or double column with at most 1/by steps, as a whole number."""
    return F.round(value * F.lit(by)).cast("long")


def unscaled(value: Column, by: int) -> Column:
    return value / F.lit(by)


def ingest(df: DataFrame, keys: list[Column | str], ann: Column | None = None, semiring: Semiring = COUNT) -> AnnotatedRelation:
    """A table as a relation: project, drop tuples with a null, sum equal keys, drop zeros."""
    return AnnotatedRelation.of_frame(df, keys, ann, semiring)


def dropped_rows(df: DataFrame, keys: list[str]) -> DataFrame:
    """One row: how many rows ingest leaves out for a null key."""
    return df.agg(F.count_if(F.expr(" or ".join(f"{k} is null" for k in keys))).alias("dropped"))


# ---- sinks --------------------------------------------------------------------------------------------------


def write_parquet(result: DataFrame, path: str, by: str | None = None, buckets: int = 64) -> None:
    """Parquet, in folders by the hash bucket of a head column if one is named."""
    if by is None:
        result.write.mode("overwrite").parquet(path)
    else:
        spread = result.withColumn("bucket", F.pmod(F.xxhash64(by), F.lit(buckets)).cast("int")).repartition("bucket")
        spread.write.mode("overwrite").partitionBy("bucket").parquet(path)


def write_bucketed(relation: AnnotatedRelation, name: str, on: list[str], buckets: int = 64) -> AnnotatedRelation:
    """A table bucketed and sorted on keys, so that later joins on them need no exchange."""
    relation.df.write.mode("overwrite").bucketBy(buckets, *on).sortBy(*on).saveAsTable(name)
    return AnnotatedRelation(relation.df.sparkSession.table(name), relation.arity, relation.semiring, bucketed=True)
