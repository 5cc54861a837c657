"""Annotated relations: integer key columns c0, c1, ... without repeats, and an annotation from a semiring."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass, replace
from dataclasses import field as slot
from math import inf

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from linform.functions.fields import Q
from linform.functions.semirings import COUNT, Semiring
from linform.sources.shared import written

#: Relative standard error of estimates of distinct values.
DEVIATION = 0.05


def keys_of(arity: int) -> list[str]:
    return [f"c{i}" for i in range(arity)]


@dataclass(frozen=True)
class AnnotatedRelation:
    df: DataFrame
    arity: int
    semiring: Semiring = COUNT
    #: The frame is a bucketed table: joins on its buckets take it as it lies.
    bucketed: bool = False

    @property
    def keys(self) -> list[str]:
        return keys_of(self.arity)

    @classmethod
    def of_rows(cls, spark: SparkSession, rows: Iterable[tuple], arity: int, semiring: Semiring = COUNT) -> AnnotatedRelation:
        """From literal rows (key, ..., annotation); equal keys are summed."""
        schema = ", ".join([*(f"{k} long" for k in keys_of(arity)), f"ann {semiring.kind}"])
        return cls(semiring.group(spark.createDataFrame(list(rows), schema), keys_of(arity)), arity, semiring)

    @classmethod
    def of_frame(cls, df: DataFrame, keys: list[Column | str], ann: Column | None = None, semiring: Semiring = COUNT) -> AnnotatedRelation:
        """Project, drop rows with a null key, sum equal keys, drop zeros."""
        cols = [F.col(k) if isinstance(k, str) else k for k in keys]
        made = df.select(*(c.cast("long").alias(n) for c, n in zip(cols, keys_of(len(cols)), strict=True)), (semiring.one() if ann is None else ann.cast(semiring.kind)).alias("ann"))
        made = made.where(" and ".join([*(f"{k} is not null" for k in keys_of(len(cols))), "ann is not null"]))
        return cls(semiring.group(made, keys_of(len(cols))), len(cols), semiring)

    def _with(self, df: DataFrame, arity: int | None = None) -> AnnotatedRelation:
        return AnnotatedRelation(df, self.arity if arity is None else arity, self.semiring)

    def union(self, other: AnnotatedRelation) -> AnnotatedRelation:
        """Sum of two relations of one arity."""
        return self._with(self.semiring.group(self.df.unionByName(other.df), self.keys))

    def product(self, other: AnnotatedRelation) -> AnnotatedRelation:
        """All pairs of tuples, annotations multiplied. Quadratic by nature; for small relations."""
        right = other.df.select(*(F.col(k).alias(f"c{self.arity + i}") for i, k in enumerate(other.keys)), F.col("ann").alias("_right"))
        both = self.df.crossJoin(right).withColumn("ann", self.semiring.times(F.col("ann"), F.col("_right"))).select(*keys_of(self.arity + other.arity), "ann")
        return self._with(both, self.arity + other.arity)

    def project(self, forms: list[list[int]]) -> AnnotatedRelation:
        """Sums over the tuples that give equal values of integer forms of the keys."""
        cols = [Q.linear([F.col(k) for k in self.keys], [Q.of(x) for x in f]).alias(f"c{i}") for i, f in enumerate(forms)]
        return self._with(self.semiring.group(self.df.select(*cols, "ann"), keys_of(len(forms))), len(forms))

    def scale(self, by) -> AnnotatedRelation:
        """Every annotation multiplied."""
        made = self.df.withColumn("ann", self.semiring.times(F.col("ann"), self.semiring.value(by)))
        return self._with(made.where(self.semiring.keep(F.col("ann"))) if self.semiring.keep else made)

    def shift(self, by: list[int]) -> AnnotatedRelation:
        """Every key moved."""
        return self._with(self.df.select(*((F.col(k) + F.lit(int(x)).cast("long")).alias(k) for k, x in zip(self.keys, by, strict=True)), "ann"))

    def restrict(self, guard: DataFrame, on: list[str] | None = None) -> AnnotatedRelation:
        """The tuples whose keys are in a guard."""
        return self._with(self.df.join(guard, on or self.keys, "left_semi"))

    def transpose(self, order: list[int]) -> AnnotatedRelation:
        return self._with(self.df.select(*(F.col(f"c{x}").alias(f"c{i}") for i, x in enumerate(order)), "ann"))

    def support(self) -> DataFrame:
        return self.df.select(*self.keys)


@dataclass
class Database:
    """Named relations over one semiring and one field."""

    relations: dict[str, AnnotatedRelation]
    semiring: Semiring = COUNT
    field: object = Q
    _stats: dict = slot(default_factory=dict)
    #: Rows that a cross product of reducts may have, as far as statistics tell.
    budget: float = inf

    def __getitem__(self, name: str) -> AnnotatedRelation:
        return self.relations[name]

    def plus(self, more: dict[str, AnnotatedRelation]) -> Database:
        told = {k: v for k, v in self._stats.items() if k[0] not in more and k[0] in self.relations}
        return Database({**self.relations, **more}, self.semiring, self.field, told, self.budget)

    def known(self, name: str, what: str, at: int) -> float:
        """A statistic of a column, infinite if nobody asked for the relation's yet."""
        told = self._stats.get((name, True)) or self._stats.get((name, False))
        return told[what][at] if told else inf

    def rows(self, name: str) -> float:
        """Tuples of a relation, infinite if nobody asked for its statistics yet."""
        told = self._stats.get((name, True)) or self._stats.get((name, False))
        return told["size"] if told else inf

    def settled(self) -> Database:
        """Each relation written once in the shared folder: evaluators use a relation for statistics, reducts and
        lookups, and would otherwise scan and sum its base tables each time."""
        return Database({n: replace(r, df=written(r.df, n)) for n, r in self.relations.items()}, self.semiring, self.field, dict(self._stats), self.budget)

    def stats(self, names: Iterable[str] | None = None, exact: bool = False) -> dict[str, dict]:
        """Of each relation: size, distinct values, least and largest value by column, largest absolute value, and for
        numeric annotations the sum ("mass") and the largest ("top") of their absolute values. One job for those not
        known yet.

        Distinct values are estimated by sketches (one pass, no exchange of values) unless exact ones are asked for;
        estimates are raised by three standard errors, so that bounds made of them hold.
        """
        names = list(dict.fromkeys(names or self.relations))
        ask = [n for n in names if (n, exact) not in self._stats]
        if ask:
            parts = None
            for n in ask:
                r = self.relations[n]
                cols = [F.count_distinct(k) if exact else F.least(F.count("*"), F.ceil(F.approx_count_distinct(k, DEVIATION) * (1 + 3 * DEVIATION))) for k in r.keys]
                listed = lambda xs: (F.array(*xs) if xs else F.array()).cast("array<bigint>")
                size = F.abs(F.col("ann").cast("double")) if r.semiring.kind in ("long", "double") or r.semiring.kind.startswith("decimal") else F.lit(None).cast("double")
                one = r.df.agg(
                    F.lit(n).alias("name"), F.count("*").alias("size"), listed(cols).alias("distinct"),
                    listed([F.min(k) for k in r.keys]).alias("low"), listed([F.max(k) for k in r.keys]).alias("high"),
                    F.sum(size).alias("mass"), F.max(size).alias("top"),
                )
                parts = one if parts is None else parts.unionAll(one)
            for row in parts.collect():  # one row a relation
                low, high = ([x or 0 for x in row[c]] for c in ("low", "high"))
                told = {"size": row["size"], "distinct": list(row["distinct"]), "low": low, "high": high, "most": max([0, *map(abs, low), *map(abs, high)])}
                self._stats[row.name, exact] = told | {"mass": row["mass"], "top": row["top"]}
        return {n: self._stats[n, exact] for n in names}
