"""Length functions, binomials and per-length coefficients."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterable
from dataclasses import dataclass
from fractions import Fraction

from pyspark.sql import DataFrame, SparkSession


@dataclass(frozen=True)
class LengthUtility:
    """f(l) on m..M, nothing outside. ``kind``: const, mean (1/l), power (l**-a), decay (exp(-a l)) or table."""

    kind: str = "const"
    m: int = 1
    M: int | None = None
    a: float = 1.0
    table: tuple[tuple[int, float], ...] = ()

    def __call__(self, length: int) -> Fraction:
        if length < max(self.m, 1) or self.M is not None and length > self.M:
            return Fraction(0)
        if self.kind == "const":
            return Fraction(1)
        if self.kind == "mean":
            return Fraction(1, length)
        if self.kind == "power":
            return Fraction(length**-self.a)
        if self.kind == "decay":
            return Fraction(math.exp(-self.a * length))
        return Fraction(dict(self.table).get(length, 0))

    @classmethod
    def of(cls, f: Callable[[int], float], m: int, M: int) -> LengthUtility:  # noqa: N803
        return cls("table", m, M, table=tuple((x, float(f(x))) for x in range(m, M + 1)))

    @property
    def unbounded(self) -> bool:
        return self.M is None and self.m <= 1

    @property
    def closed(self) -> bool:
        """Whether the coefficient is a closed form of the size."""
        return self.unbounded and self.kind in ("const", "mean")


SUM, MEAN = LengthUtility(), LengthUtility("mean")


def coefficient(n: int, f: LengthUtility) -> Fraction:
    """c(n): a transaction of n items and weight sum S has weight S * c(n). Closed forms without bounds."""
    if f.unbounded and f.kind == "const":
        return Fraction(2 ** (n - 1))
    if f.unbounded and f.kind == "mean":
        return Fraction(2**n - 1, n)
    top = n if f.M is None else min(f.M, n)
    if f.kind == "const" and top - f.m > n // 2:  # fewer terms outside than inside
        out = sum(math.comb(n - 1, x - 1) for x in range(1, f.m)) + sum(math.comb(n - 1, x - 1) for x in range(top + 1, n + 1))
        return Fraction(2 ** (n - 1) - out)
    return sum((math.comb(n - 1, x - 1) * f(x) for x in range(max(f.m, 1), top + 1)), Fraction(0))


def log_of(x: Fraction) -> float:
    return math.log(x.numerator) - math.log(x.denominator)


def coefficients(spark: SparkSession, sizes: Iterable[int], f: LengthUtility) -> DataFrame:
    """(n, c, logc) of each n with a pattern: one row per *distinct* size of transaction."""
    rows = [(n, c) for n in sorted(set(sizes)) if (c := coefficient(n, f))]
    return spark.createDataFrame([(n, float(c) if log_of(c) < 700 else None, log_of(c)) for n, c in rows], "n int, c double, logc double")


def length_law(spark: SparkSession, sizes: Iterable[int], f: LengthUtility, tail: float = 0.0) -> DataFrame:
    """(n, l, lo, hi): the part of (0, 1] that stands for length l in a transaction of n items (it depends on n alone)."""
    rows = []
    for n in sorted(set(sizes)):
        total = coefficient(n, f)
        if not total:
            continue
        run, logs = 0.0, log_of(total)
        top = n if f.M is None else min(f.M, n)
        binom = math.comb(n - 1, max(f.m, 1) - 1)
        for x in range(max(f.m, 1), top + 1):
            v = f(x)
            p = math.exp(math.log(binom) + log_of(v) - logs) if v else 0.0
            if p > tail:
                rows.append((n, x, run, run + p))
            run += p
            binom = binom * (n - x) // x
        if rows:
            rows[-1] = (*rows[-1][:3], 2.0)  # rounding never leaves a gap at the end
    return spark.createDataFrame(rows, "n int, l int, lo double, hi double")


def pascal_cells(n: int) -> int:
    """Cells of a binomial cache that uses symmetry."""
    return (n // 2 + 1) ** 2 if n % 2 == 0 else (n + 1) * (n + 3) // 4


class PascalCache:
    """Rows 0..n of the triangle, half of each."""

    def __init__(self, n: int) -> None:
        self.rows: list[list[int]] = []
        for i in range(n + 1):
            up = self.rows[-1] if i else []
            get = lambda k, i=i, up=up: 0 if k < 0 else up[min(k, i - 1 - k)]
            self.rows.append([1 if k == 0 else get(k - 1) + get(k) for k in range(i // 2 + 1)])

    def __call__(self, n: int, k: int) -> int:
        return self.rows[n][min(k, n - k)] if 0 <= k <= n else 0

    def cells(self) -> int:
        return sum(map(len, self.rows))


def log_factorials(n: int) -> list[float]:
    """n + 1 numbers that replace a cache of about n * n / 4."""
    return [math.lgamma(k + 1) for k in range(n + 1)]
