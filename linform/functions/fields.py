"""Fields for coefficients and domain values: exact arithmetic on the driver, column expressions on Spark.

Rational values are stored as integers over a common denominator (see sources.ingest); finite fields as integers
0 .. order-1, an element of GF(p**k) being its coordinates read as a number in base p.
"""

from __future__ import annotations

from dataclasses import dataclass
from fractions import Fraction
from functools import cached_property
from itertools import product

from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Rationals:
    characteristic: int = 0
    order: int | None = None

    def of(self, x) -> Fraction:
        return Fraction(x)

    def add(self, a, b):
        return a + b

    def mul(self, a, b):
        return a * b

    def neg(self, a):
        return -a

    def inv(self, a):
        return 1 / a

    def linear(self, columns: list[Column], coefficients: list) -> Column:
        """Sum of integer multiples of columns."""
        total = None
        for c, q in zip(columns, coefficients, strict=True):
            if q.denominator != 1:
                raise ValueError("scale the form to integers first")
            if q:
                term = c if q == 1 else -c if q == -1 else c * F.lit(int(q)).cast("long")
                total = term if total is None else total + term
        return F.lit(0).cast("long") if total is None else total


@dataclass(frozen=True)
class PrimeField:
    p: int

    @property
    def characteristic(self) -> int:
        return self.p

    @property
    def order(self) -> int:
        return self.p

    def of(self, x) -> int:
        x = Fraction(x)
        return x.numerator * pow(x.denominator, -1, self.p) % self.p

    def add(self, a, b):
        return (a + b) % self.p

    def mul(self, a, b):
        return a * b % self.p

    def neg(self, a):
        return -a % self.p

    def inv(self, a):
        return pow(a, -1, self.p)

    def linear(self, columns: list[Column], coefficients: list) -> Column:
        total = F.lit(0).cast("long")
        for c, q in zip(columns, coefficients, strict=True):
            if q:
                total = total + c * F.lit(int(q)).cast("long")
        return F.pmod(total, F.lit(self.p).cast("long"))


@dataclass(frozen=True)
class ExtensionField:
    """GF(p**k) over the first irreducible polynomial of degree k in numeric order."""

    p: int
    k: int

    @property
    def characteristic(self) -> int:
        return self.p

    @property
    def order(self) -> int:
        return self.p**self.k

    def digits(self, a: int) -> list[int]:
        return [a // self.p**i % self.p for i in range(self.k)]

    def number(self, digits) -> int:
        return sum(d * self.p**i for i, d in enumerate(digits))

    @cached_property
    def modulus(self) -> tuple[int, ...]:
        """Coefficients below x**k of the monic modulus."""
        for low in product(range(self.p), repeat=self.k):
            low = low[::-1]
            if self._irreducible([*low, 1]):
                return tuple(low)
        raise ValueError("no irreducible polynomial")

    def _irreducible(self, poly: list[int]) -> bool:
        for deg in range(1, self.k // 2 + 1):
            for low in product(range(self.p), repeat=deg):
                rest, divisor = list(poly), [*low, 1]
                for top in range(len(rest) - 1, deg - 1, -1):
                    q = rest[top]
                    for i, d in enumerate(divisor):
                        rest[top - deg + i] = (rest[top - deg + i] - q * d) % self.p
                if not any(rest[:deg]):
                    return False
        return True

    def of(self, x) -> int:
        """Integers mean elements by their code; fractions are taken in the prime field."""
        x = Fraction(x)
        if x.denominator == 1 and 0 <= x < self.order:
            return int(x)
        return PrimeField(self.p).of(x)

    def add(self, a, b):
        return self.number((x + y) % self.p for x, y in zip(self.digits(a), self.digits(b), strict=True))

    def neg(self, a):
        return self.number(-x % self.p for x in self.digits(a))

    def mul(self, a, b):
        out = [0] * (2 * self.k - 1)
        for i, x in enumerate(self.digits(a)):
            for j, y in enumerate(self.digits(b)):
                out[i + j] += x * y
        for top in range(2 * self.k - 2, self.k - 1, -1):
            for i, m in enumerate(self.modulus):
                out[top - self.k + i] -= out[top] * m
        return self.number(x % self.p for x in out[: self.k])

    def inv(self, a):
        if not a:
            raise ZeroDivisionError
        out, power, e = 1, a, self.order - 2
        while e:
            if e & 1:
                out = self.mul(out, power)
            power, e = self.mul(power, power), e >> 1
        return out

    def power(self, a: int, e: int) -> int:
        out = 1
        for _ in range(e):
            out = self.mul(out, a)
        return out

    def subfield_degree(self, elements) -> int:
        """Degree over GF(p) of the smallest subfield that holds the elements."""
        for j in range(1, self.k + 1):
            if self.k % j == 0 and all(self.power(a, self.p**j) == a for a in elements):
                return j
        return self.k

    def subfield(self, elements) -> list[int]:
        """Codes of the least subfield that holds the elements."""
        size = self.p ** self.subfield_degree(set(elements))
        return [a for a in range(self.order) if self.power(a, size) == a]

    def linear(self, columns: list[Column], coefficients: list) -> Column:
        """Multiplication by a constant is linear in the base-p digits, so digits are summed and reduced one by one."""
        sums: list[Column] = [F.lit(0).cast("long") for _ in range(self.k)]
        for c, q in zip(columns, coefficients, strict=True):
            for j in range(self.k):
                image = self.digits(self.mul(q, self.p**j))
                digit = F.pmod(F.floor(c / F.lit(self.p**j)).cast("long"), F.lit(self.p).cast("long"))
                for i, m in enumerate(image):
                    if m:
                        sums[i] = sums[i] + digit * F.lit(m).cast("long")
        total = F.lit(0).cast("long")
        for i, s in enumerate(sums):
            total = total + F.pmod(s, F.lit(self.p).cast("long")) * F.lit(self.p**i).cast("long")
        return total


Q = Rationals()
