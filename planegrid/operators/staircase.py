"""Dominant points of rectangles, and points visible from a query point.

A point is dominant towards a corner if no other point of the rectangle is at least as far in both directions. The
staircase of a union is the staircase of the parts' staircases, so parts are thinned where they lie before any
rectangle's points meet in one window.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Signs by which a corner's axes are turned so that large is far.
CORNERS = {"NE": (1, 1), "NW": (-1, 1), "SE": (1, -1), "SW": (-1, -1)}
#: The corner of a quadrant at which its query point stands, by the direction of sight.
TOWARDS = {"SW": "NE", "NE": "SW", "SE": "NW", "NW": "SE"}


def _thinned(rows: DataFrame, keys: list[str]) -> DataFrame:
    """Keeps the rows (u, v) of each key that none beats; equal coordinates are one row already."""
    before = Window.partitionBy(*keys).orderBy(F.desc("v"), F.desc("u")).rowsBetween(Window.unboundedPreceding, -1)
    return rows.withColumn("_run", F.max("u").over(before)).where("_run is null or u > _run").drop("_run")


def dominant_points(hits: DataFrame, corner: str = "NE") -> DataFrame:
    """qid, ord, x, y: in order from the largest y (for a corner: from the farthest y) on; equal points are one.

    Of points with one u only the farthest in v can stay, which Spark finds before it shuffles. The rest is thinned
    within stretches of u, as many as the input has partitions, and then among what is left.
    """
    a, b = CORNERS[corner]
    rows = hits.groupBy("qid", (F.col("x") * a).alias("u")).agg(F.max(F.col("y") * b).alias("v"))
    rows = _thinned(rows.withColumn("_part", F.spark_partition_id()), ["qid", "_part"])
    rows = _thinned(rows.drop("_part"), ["qid"])
    return rows.select("qid", F.row_number().over(Window.partitionBy("qid").orderBy(F.desc("v"))).cast("long").alias("ord"), (F.col("u") * a).alias("x"), (F.col("v") * b).alias("y"))


def quadrant(queries: DataFrame, direction: str) -> DataFrame:
    """queries: (qid, qx, qy) -> the rectangle in which a direction looks."""
    x, y = F.col("qx"), F.col("qy")
    none = F.lit(None)
    east, north = direction[1] == "E", direction[0] == "N"
    return queries.select("qid", *((v if keep else none.cast(dict(queries.dtypes)[c])).alias(n) for n, v, keep, c in (("x0", x, east, "qx"), ("x1", x, not east, "qx"), ("y0", y, north, "qy"), ("y1", y, not north, "qy"))))


def visible_points(hits: DataFrame, direction: str) -> DataFrame:
    """hits: the points of quadrant(). A point is visible if no other lies between it and the query point.

    That is the staircase towards the query point: looking SW, the dominant points of the quadrant's NE corner.
    """
    return dominant_points(hits, TOWARDS[direction]).select("qid", F.lit(direction).alias("direction"), "x", "y")
