"""Weightings of coalitions by size, and the numbers that strata need."""

from __future__ import annotations

import math
from collections.abc import Callable
from dataclasses import dataclass
from fractions import Fraction

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Players of one answer that fit a 64-bit mask with its sign bit clear.
MAX_PLAYERS = 62


@dataclass(frozen=True)
class Semivalue:
    """weight(n, k): of a coalition of k others among n players. Over all coalitions the weights sum to 1.

    chance(m): that m given others all belong to a random coalition; it gives unanimity games a closed form."""

    name: str
    weight: Callable[[int, int], Fraction]

    @staticmethod
    def shapley() -> Semivalue:
        return Semivalue("shapley", lambda n, k: Fraction(1, n * math.comb(n - 1, k)))

    @staticmethod
    def banzhaf() -> Semivalue:
        return Semivalue("banzhaf", lambda n, k: Fraction(1, 2 ** (n - 1)))

    @staticmethod
    def beta(alpha: int, beta: int) -> Semivalue:
        """Sizes follow a Beta(beta, alpha) mixture of coin tosses; (1, 1) is Shapley."""

        def b(x: int, y: int) -> Fraction:
            return Fraction(math.factorial(x - 1) * math.factorial(y - 1), math.factorial(x + y - 1))

        return Semivalue(f"beta({alpha},{beta})", lambda n, k: b(k + beta, n - 1 - k + alpha) / b(alpha, beta))

    @staticmethod
    def custom(name: str, by_size: list[float]) -> Semivalue:
        """Total weight of each size among the others, scaled to 1; for games of len(by_size) players only."""
        total = sum(Fraction(x) for x in by_size)

        def weight(n: int, k: int) -> Fraction:
            if n != len(by_size):
                raise ValueError(f"{name} is for {len(by_size)} players")
            return Fraction(by_size[k]) / total / math.comb(n - 1, k)

        return Semivalue(name, weight)

    def chance(self, m: int) -> Fraction:
        """The game of m + 1 players is enough: others don't change the chance (for every weighting but a custom one)."""
        return self.weight(m + 1, m)

    def table(self, largest: int = MAX_PLAYERS) -> list[list[float]]:
        """By number of players the weights by size; none for numbers that a custom weighting isn't for, whose values are null."""

        def weights(n: int) -> list[float]:
            try:
                return [float(self.weight(n, k)) for k in range(n)]
            except ValueError:
                return []

        return [[0.0]] + [weights(n) for n in range(1, largest + 1)]


def with_weights(settings: DataFrame, semivalue: Semivalue) -> DataFrame:
    """Adds `omega`, the weights by coalition size, from a table of at most 62 rows."""
    table = settings.sparkSession.createDataFrame(list(enumerate(semivalue.table())), "n int, omega array<double>")
    return settings.join(F.broadcast(table), "n")


def choose(n: Column, k: Column) -> Column:
    """Binomial coefficient as a double; exact while it fits."""
    product = F.aggregate(F.sequence(F.lit(1), k), F.lit(1.0), lambda a, i: F.round(a * (n - k + i) / i))
    return F.when(k <= 0, F.when(k == 0, 1.0).otherwise(0.0)).when(k > n, 0.0).otherwise(product)


def shapley_weight(n: Column, k: Column) -> Column:
    return 1.0 / (n * choose(n - 1, k))


def shl(x: Column, by: Column | int) -> Column:
    return F.call_function("shiftleft", x, by if isinstance(by, Column) else F.lit(by))


def of_relation(name: str) -> Callable[[Column], Column]:
    """A test of one argument: a second one would be taken for the element's index."""
    return lambda p: p["rel"] == name
