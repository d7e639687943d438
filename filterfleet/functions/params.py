"""Filter sizes, hash counts and analytic false-positive rates."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

WORD = 64


def derive_k(target_fp: float) -> int:
    """Hash functions for a target false-positive rate."""
    return max(1, math.ceil(-math.log(target_fp) / math.log(2) - 1e-12))


def derive_m(expected_n: int, k: int, word: int = WORD) -> int:
    """Bits for `expected_n` elements and k hash functions, rounded up to whole words."""
    bits = math.ceil(k / math.log(2) * expected_n)
    return max(word, -(-bits // word) * word)


def expected_fp(n: float, m: int, k: int) -> float:
    """Analytic false-positive rate of a filter of m bits with n elements."""
    return (1 - math.exp(-k * n / m)) ** k


def expected_fp_column(n, m, k) -> Column:
    c = lambda x: x if isinstance(x, Column) else F.col(x) if isinstance(x, str) else F.lit(x)
    return F.pow(1 - F.exp(-c(k) * c(n) / c(m)), c(k))


def optimal_k(m: int, n: int) -> int:
    return max(1, round(m / n * math.log(2)))


def saturating_sets(m: int, k: int, n: float) -> float:
    """How many disjoint sets of n elements leave less than one zero bit in their union's filter."""
    return m * math.log(m) / (k * n)


def pruning_sets(m: int, k: int, n: float) -> float:
    """How many disjoint sets a union filter may stand for while it turns away half of all absent elements."""
    return -math.log(1 - 0.5 ** (1 / k)) * m / (k * n)


def odd_multipliers(k: int, seed: int = 1) -> tuple[int, ...]:
    """k odd numbers of 31 bits from a multiplicative walk."""
    out, x = [], seed * 2654435761 % (1 << 31)
    while len(out) < k:
        x = (x * 1103515245 + 12345) % (1 << 31)
        if (a := x | 1) not in out:
            out.append(a)
    return tuple(out)


@dataclass(frozen=True)
class FilterSpec:
    """What all filters of an index share: m bits, k hash functions of one family, its seeds."""

    expected_n: int
    target_fp: float = 0.01
    family: str = "md5_double"
    k: int = 0
    m: int = 0
    seeds: tuple[int, ...] = field(default=())

    def __post_init__(self):
        k = self.k or derive_k(self.target_fp)
        object.__setattr__(self, "k", k)
        object.__setattr__(self, "m", self.m or derive_m(self.expected_n, k))
        object.__setattr__(self, "seeds", self.seeds or odd_multipliers(k))

    @property
    def words(self) -> int:
        return -(-self.m // WORD)

    @property
    def spec_id(self) -> str:
        return f"{self.family}-{self.k}-{self.m}-{'-'.join(map(str, self.seeds)) if self.family == 'linear_odd' else ''}"

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([(self.expected_n, self.target_fp, self.k, self.m, self.family, list(self.seeds))], "expected_n long, target_fp double, k int, m long, family string, seeds array<long>")


def fp_curve(spark: SparkSession, sizes: list[int], n: int, k: int) -> DataFrame:
    """Analytic false-positive rate for each filter size at a fixed number of elements."""
    return spark.createDataFrame([(m,) for m in sizes], "m long").withColumn("fp", expected_fp_column(n, "m", k))
