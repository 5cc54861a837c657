"""Commutative semirings for annotations, as Spark expressions.

`plus` aggregates a column, `times` multiplies two columns; a tuple outside a relation has the semiring's zero
and is never stored, so `keep` filters out zeros that sums have made (semirings in which sums can cancel).
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Semiring:
    name: str
    kind: str
    one: Callable[[], Column]
    zero: Callable[[], Column]
    plus: Callable[[Column], Column]
    times: Callable[[Column, Column], Column]
    keep: Callable[[Column], Column] | None = None
    #: Replaces the built-in grouping where the sum is a user's function.
    grouped: Callable[[DataFrame, list[str]], DataFrame] | None = None
    #: How a task may sum many products at once: "sum" of whole numbers, "any" of them, or those of "least" cost only.
    local: str | None = None

    def group(self, df: DataFrame, keys: list[str]) -> DataFrame:
        """Sum the annotations of equal keys: (keys, ann), without zeros."""
        if self.grouped is not None:
            out = self.grouped(df.select(*keys, "ann"), keys)
        elif keys:
            out = df.groupBy(*keys).agg(self.plus(F.col("ann")).cast(self.kind).alias("ann"))
        else:
            out = df.agg(self.plus(F.col("ann")).cast(self.kind).alias("ann"), F.count("*").alias("_n")).where("_n > 0").drop("_n")
        return out.where(self.keep(F.col("ann"))) if self.keep else out

    def value(self, x) -> Column:
        return F.lit(x).cast(self.kind)


def _constant(x, kind: str) -> Callable[[], Column]:
    return lambda: F.lit(x).cast(kind)


def integers(kind: str = "long") -> Semiring:
    """Sums and products of integers; kind decimal(38,0) where the bound of the result needs it."""
    return Semiring("sum", kind, _constant(1, kind), _constant(0, kind), F.sum, lambda a, b: (a * b).cast(kind), lambda a: a != 0, local="sum" if kind == "long" else None)


COUNT = integers()
BIG_COUNT = integers("decimal(38,0)")
REAL = Semiring("real", "double", _constant(1.0, "double"), _constant(0.0, "double"), F.sum, lambda a, b: a * b, lambda a: a != 0)
BOOLEAN = Semiring("boolean", "boolean", _constant(True, "boolean"), _constant(False, "boolean"), F.bool_or, lambda a, b: a & b, lambda a: a, local="any")
MIN_PLUS = Semiring("min-plus", "long", _constant(0, "long"), _constant(None, "long"), F.min, lambda a, b: a + b)
MAX_PLUS = Semiring("max-plus", "long", _constant(0, "long"), _constant(None, "long"), F.max, lambda a, b: a + b)
MAX_TIMES = Semiring("max-times", "long", _constant(1, "long"), _constant(0, "long"), F.max, lambda a, b: a * b, lambda a: a != 0)
#: The same in 38 digits.
BIG_MAX_TIMES = Semiring("max-times", "decimal(38,0)", _constant(1, "decimal(38,0)"), _constant(0, "decimal(38,0)"), F.max, lambda a, b: (a * b).cast("decimal(38,0)"), lambda a: a != 0)
BOTTLENECK = Semiring("bottleneck", "long", _constant(2**62, "long"), _constant(0, "long"), F.max, F.least, lambda a: a != 0)


def modular(m: int) -> Semiring:
    """Sums and products modulo m."""
    return Semiring(f"mod {m}", "long", _constant(1 % m, "long"), _constant(0, "long"), lambda a: F.pmod(F.sum(a), F.lit(m)), lambda a, b: F.pmod(a * b, F.lit(m)), lambda a: a != 0)


def witness(kind: str) -> Semiring:
    """Least cost with a witness: annotations are structs (cost long, wit array<kind>) and compare by cost first."""
    struct = f"struct<cost: bigint, wit: array<{kind}>>"
    one = lambda: F.struct(F.lit(0).cast("long").alias("cost"), F.array().cast(f"array<{kind}>").alias("wit"))
    times = lambda a, b: F.struct((a["cost"] + b["cost"]).alias("cost"), F.concat(a["wit"], b["wit"]).alias("wit"))
    return Semiring("witness", struct, one, _constant(None, struct), F.min, times, local="least")


#: Sets of integers with union and sums of elements: annotations are not of constant size, for demonstration.
SETS = Semiring(
    "sets", "array<bigint>", lambda: F.array(F.lit(0).cast("long")), lambda: F.array().cast("array<bigint>"),
    lambda a: F.array_sort(F.array_distinct(F.flatten(F.collect_list(a)))),
    lambda a, b: F.array_sort(F.array_distinct(F.flatten(F.transform(a, lambda x: F.transform(b, lambda y: x + y))))),
    lambda a: F.size(a) > 0,
)


def user(name: str, kind: str, one, fold: Callable, times: Callable[[Column, Column], Column]) -> Semiring:
    """A user's semiring: `fold` reduces a pandas Series of annotations; groups go through Arrow."""

    def grouped(df: DataFrame, keys: list[str]) -> DataFrame:
        import pandas as pd

        schema = df.schema.simpleString()[7:-1].replace(":", " ")
        by = keys or ["_all"]
        df = df if keys else df.withColumn("_all", F.lit(0))
        made = df.groupBy(*by).applyInPandas(lambda k, g: pd.DataFrame([[*(k if keys else ()), fold(g["ann"])]], columns=[*keys, "ann"]), schema)
        return made

    return Semiring(name, kind, _constant(one, kind), _constant(None, kind), F.first, times, None, grouped)
