"""Table functions for SQL: register(spark), then SELECT * FROM cells_in_box(...)."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


@udtf(returnType="cell long")
class CellsInBox:
    """Cells of a grid of 2**bits steps over the unit box, in Morton order's numbers, that meet a box."""

    def eval(self, lo: list[float], hi: list[float], bits: int):
        n, d = 1 << bits, len(lo)
        ranges = [range(max(0, min(n - 1, int(a * n))), max(0, min(n - 1, int(b * n))) + 1) for a, b in zip(lo, hi)]

        def walk(i: int, chosen: list[int]):
            if i == d:
                yield (sum((c >> b & 1) << (b * d + k) for b in range(bits) for k, c in enumerate(chosen)),)
                return
            for c in ranges[i]:
                yield from walk(i + 1, [*chosen, c])

        yield from walk(0, [])


@udtf(returnType="orthant int")
class OrthantCodes:
    """All orthant numbers of d dimensions."""

    def eval(self, d: int):
        for code in range(1 << d):
            yield (code,)


def register(spark: SparkSession) -> None:
    spark.udtf.register("cells_in_box", CellsInBox)
    spark.udtf.register("orthant_codes", OrthantCodes)
