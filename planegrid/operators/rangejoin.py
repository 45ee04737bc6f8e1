"""Points in rectangles as an equi-join on cells, instead of a nested loop.

The batch's bounding box limits the points before the join (sources push it into the scan, see sources.grids). The x
axis of the box is cut into cells; a rectangle is repeated for each cell that it touches, a point has one cell, and the
exact predicate follows the join. The rectangles are broadcast if their repeated rows are few enough, which is counted
beforehand; then points are neither shuffled nor sorted. A larger batch meets the points in a shuffled join, whose
large partitions Spark splits at run time.
"""

from __future__ import annotations

from dataclasses import dataclass
from typing import Any

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

CELLS = 64
#: Rows (about 60 bytes each) up to which the repeated rectangles are broadcast.
MOST_BROADCAST = 500_000
_PROPER = "coalesce(x0 <= x1, true) and coalesce(y0 <= y1, true)"


@dataclass(frozen=True)
class Box:
    """What a batch of rectangles spans, None for an open side, and how many rectangles there are."""

    x0: Any
    x1: Any
    y0: Any
    y1: Any
    n: int


def box_of(rects: DataFrame) -> Box:
    """Of the rectangles that aren't turned inside out."""
    side = lambda c, f: F.when(F.count("*") == F.count(c), f(c)).alias(c)
    r = rects.where(_PROPER).agg(side("x0", F.min), side("x1", F.max), side("y0", F.min), side("y1", F.max), F.count("*").alias("n")).first()
    return Box(r.x0, r.x1, r.y0, r.y1, r.n)


def _cells(box: Box, cells: int) -> tuple[Column, Column, Column]:
    """The cell of a point, and the first and last cell of a rectangle."""
    low, high = box.x0, box.x1
    if low is None or high is None or not high > low:
        return F.lit(0), F.lit(0), F.lit(0)
    of = lambda c: F.floor((F.col(c).cast("double") - float(low)) / (float(high) - float(low)) * cells).cast("int")
    return of("x"), F.greatest(F.coalesce(of("x0"), F.lit(0)), F.lit(0)), F.least(F.coalesce(of("x1"), F.lit(cells)), F.lit(cells))


def points_in(points: DataFrame, rects: DataFrame, cells: int = CELLS, box: Box | None = None) -> DataFrame:
    """(points' columns, rects' columns) of all pairs with x0 <= x <= x1 and y0 <= y <= y1; null sides are open."""
    box = box or box_of(rects)
    for c in ("x", "y"):
        low, high = getattr(box, f"{c}0"), getattr(box, f"{c}1")
        points = points.where(F.col(c).isNotNull() if low is None else F.col(c) >= low)
        points = points if high is None else points.where(F.col(c) <= high)
    cell, first, last = _cells(box, cells)
    within = lambda c: (F.col(f"{c}0").isNull() | (F.col(c) >= F.col(f"{c}0"))) & (F.col(f"{c}1").isNull() | (F.col(c) <= F.col(f"{c}1")))
    wanted = rects.where(_PROPER).withColumn("_cell", F.explode(F.when(first <= last, F.sequence(first, last)).otherwise(F.array().cast("array<int>"))))
    # a rectangle has one row for each cell at most
    wanted = F.broadcast(wanted) if box.n * (cells + 1) <= MOST_BROADCAST or wanted.count() <= MOST_BROADCAST else wanted
    return points.withColumn("_cell", cell).join(wanted, "_cell").where(within("x") & within("y")).drop("_cell")
