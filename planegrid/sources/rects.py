"""Rectangles: queries come as rows (qid, x0, x1, y0, y1), closed on all sides; null is an open side."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Literal rectangles of the workloads, by grid.
RECTS: dict[str, list[tuple]] = {
    "L": [(1, 10, 20, 1_000_000, 2_000_000), (2, 50, 50, 0, 10**9), (3, 1, 50, 0, 10**9), (4, 3, 3, 90_182, 90_182), (5, 20, 10, 0, 10**9), (6, 7, 31, 2_000_001, 2_000_400)],
    "S": [(1, 789004800000000, 820454400000000, 1, 200), (2, 820454400000000, 946684800000000, 500, 520), (3, 0, 1, 0, 1)],
    "O": [(1, 788918400000000, 820454400000000, 10_000_000, 20_000_000), (2, 900000000000000, 900500000000000, 0, 10**9), (3, 788918400000000, 996624000000000, 0, 10**9), (4, 5, 4, 3, 2)],
    "E": [(1, 1704067200000000, 1704499200000000, 0, 49), (2, 1704067200000000, 1704240000000000, 10, 12), (3, 0, 1, 0, 1), (4, 1704067200000000, 2000000000000000, 0, 10**6)],
    "P": [(1, 1, 50, 90_000, 99_990), (2, 10, 20, 92_000, 95_000), (3, 7, 7, 90_000, 99_990), (4, 60, 70, 0, 10**9)],
    "C": [(1, 5, 12, 0, 500_000), (2, 1, 100, -100_000, 1_000_000), (3, 3, 3, -100, 100)],
    "D": [(1, 0, 500, 0, 999), (2, 500, 3_000, 200, 700), (3, 40_000, 50_000, 0, 999), (4, 0, 10**9, 0, 10**18), (5, 500, 3_000, 200, 10**18)],
    "V": [(1, -0.1, 0.1, -0.1, 0.1), (2, -1.0, 1.0, -1.0, 1.0), (3, 0.3, 0.31, 0.3, 0.31)],
}


def rects(spark: SparkSession, grid: str) -> DataFrame:
    kind = "double" if grid == "V" else "bigint"
    return spark.createDataFrame(RECTS[grid], f"qid bigint, x0 {kind}, x1 {kind}, y0 {kind}, y1 {kind}")


def sql(grid: str) -> str:
    kind = "double" if grid == "V" else "bigint"
    rows = ", ".join(f"({', '.join(map(str, r))})" for r in RECTS[grid])
    return f"select cast(qid as bigint) as qid, cast(x0 as {kind}) as x0, cast(x1 as {kind}) as x1, cast(y0 as {kind}) as y0, cast(y1 as {kind}) as y1 from (values {rows}) t(qid, x0, x1, y0, y1)"


def spread(spark: SparkSession, n: int, x: tuple[int, int], y: tuple[int, int]) -> DataFrame:
    """n rectangles by integer arithmetic on the ranges of a grid; sides of 1, 10 and 50 hundredths in turn."""
    side = F.element_at(F.array(F.lit(1), F.lit(10), F.lit(50)), (F.col("id") % 3 + 1).cast("int"))

    def bounds(low: int, high: int, step: int) -> tuple:
        first = F.lit(low) + F.col("id") * step % 997 * (high - low) / 997 * (100 - side) / 100
        return first.cast("bigint"), (first + F.lit(high - low) * side / 100).cast("bigint")

    (x0, x1), (y0, y1) = bounds(*x, 389), bounds(*y, 611)
    return spark.range(n).select(F.col("id").alias("qid"), x0.alias("x0"), x1.alias("x1"), y0.alias("y0"), y1.alias("y1"))
