"""Table functions for SQL: unit matches of one packed center, and plain matches of one compressed row."""

from __future__ import annotations

from collections.abc import Iterator
from itertools import product

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


class UnitTriangles:
    """Triangles at a center from its packed local graph: ``LATERAL unit_triangles(center, inner)``."""

    def eval(self, center: int, inner: list) -> Iterator[tuple[int, int, int]]:
        for e in inner or []:
            yield center, e["a"], e["b"]


class Decompress:
    """Choices of distinct values, one of each set: ``LATERAL decompress(sets)`` with an array of arrays."""

    def eval(self, sets: list) -> Iterator[tuple[list[int]]]:
        for choice in product(*(sets or [])):
            if len(set(choice)) == len(choice):
                yield (list(choice),)


def register(spark: SparkSession) -> None:
    """Registers ``unit_triangles`` and ``decompress_sets``."""
    spark.udtf.register("unit_triangles", udtf(UnitTriangles, returnType="f_a bigint, f_b bigint, f_c bigint"))
    spark.udtf.register("decompress_sets", udtf(Decompress, returnType="choice array<bigint>"))
