"""Functions for users of SQL: count vectors, subsets by number, and values as views."""

from __future__ import annotations

import math
from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


class EnumerateVectors:
    """SELECT * FROM enumerate_vectors(array(1, 2)): every vector of counts up to the given ones."""

    def eval(self, c: list[int]) -> Iterator[tuple[list[int]]]:
        def deeper(k: int, head: list[int]) -> Iterator[tuple[list[int]]]:
            if k == len(c):
                yield (head,)
            else:
                for x in range(c[k] + 1):
                    yield from deeper(k + 1, [*head, x])

        yield from deeper(0, [])


class UnrankSubset:
    """SELECT * FROM unrank_subset(5, 2, 7): members of the subset of that number, in order of the greatest member."""

    def eval(self, n: int, k: int, rank: int) -> Iterator[tuple[int]]:
        left = k
        for m in range(n - 1, -1, -1):
            if left and rank >= math.comb(m, left):
                rank -= math.comb(m, left)
                left -= 1
                yield (m,)


def register(spark: SparkSession) -> None:
    spark.udtf.register("enumerate_vectors", udtf(EnumerateVectors, returnType="vec: array<int>"))
    spark.udtf.register("unrank_subset", udtf(UnrankSubset, returnType="member: int"))
