"""A baseline: running totals over a coarse grid of cells, corrected by the points in cells that a rectangle cuts.

A stand-in for tables of all rectangles, which take space quadratic in the points: here the square of the cells.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from planegrid.operators.rangejoin import points_in
from planegrid.operators.scan import _all
from planegrid.plans.storage import cut

MOST = 1024


def extrema_in(points: DataFrame, rects: DataFrame, cells: int = 32) -> DataFrame:
    """qid, lo, hi: least and largest weights of the cells strictly inside a rectangle, and of the points in those that it cuts."""
    if cells > MOST:
        raise ValueError(f"at most {MOST} cells a side")
    box = points.agg(*(f(c).cast("double").alias(f"{c}{k}") for c in ("x", "y") for k, f in ((0, F.min), (1, F.max)))).first()
    cx, cy = _of("x", box.x0, box.x1, cells), _of("y", box.y0, box.y1, cells)
    cube = cut(points.groupBy(cx.alias("i"), cy.alias("j")).agg(F.min("w").alias("a"), F.max("w").alias("b")))
    side = lambda c, b0, b1: F.greatest(F.lit(-1), F.least(F.lit(cells), F.floor((F.col(c).cast("double") - b0) / max(b1 - b0, 1e-300) * cells))).cast("int")
    spans = rects.where("x0 <= x1 and y0 <= y1").select("qid", (side("x0", box.x0, box.x1) + 1).alias("i0"), (side("x1", box.x0, box.x1) - 1).alias("i1"), (side("y0", box.y0, box.y1) + 1).alias("j0"), (side("y1", box.y0, box.y1) - 1).alias("j1"))
    rows = spans.where("i0 <= i1 and j0 <= j1").withColumn("i", F.explode(F.sequence("i0", "i1"))).withColumn("j", F.explode(F.sequence("j0", "j1")))
    whole = rows.join(cube, ["i", "j"]).select("qid", "a", "b")
    cutoff = points_in(points, rects).join(spans, "qid").where(~(cx.between(F.col("i0"), F.col("i1")) & cy.between(F.col("j0"), F.col("j1"))))
    found = whole.union(cutoff.select("qid", "w", "w")).groupBy("qid").agg(F.min("a").alias("lo"), F.max("b").alias("hi"))
    return _all(rects, found).select("qid", "lo", "hi")


def _of(c: str, low: float, high: float, cells: int):
    return F.least(F.floor((F.col(c).cast("double") - low) / max(high - low, 1e-300) * cells), F.lit(cells - 1)).cast("int")


def sums_in(points: DataFrame, rects: DataFrame, cells: int = 32) -> DataFrame:
    """qid, cnt, s of the weights."""
    if cells > MOST:
        raise ValueError(f"at most {MOST} cells a side")
    box = points.agg(*(f(c).cast("double").alias(f"{c}{k}") for c in ("x", "y") for k, f in ((0, F.min), (1, F.max)))).first()
    cx, cy = _of("x", box.x0, box.x1, cells), _of("y", box.y0, box.y1, cells)
    axis = points.sparkSession.range(cells)
    each = points.groupBy(cx.alias("i"), cy.alias("j")).agg(F.count("*").alias("n"), F.sum("w").alias("s"))
    full = axis.select(F.col("id").cast("int").alias("i")).crossJoin(axis.select(F.col("id").cast("int").alias("j"))).join(each, ["i", "j"], "left").fillna(0)  # cells * cells rows, fixed
    up = Window.partitionBy("i").orderBy("j").rowsBetween(Window.unboundedPreceding, 0)
    over = Window.partitionBy("j").orderBy("i").rowsBetween(Window.unboundedPreceding, 0)
    cube = full.withColumns({"n": F.sum("n").over(up), "s": F.sum("s").over(up)}).withColumns({"n": F.sum("n").over(over), "s": F.sum("s").over(over)})
    cube = cut(cube)
    # whole cells lie strictly between the cells of the sides
    side = lambda c, b0, b1: F.greatest(F.lit(-1), F.least(F.lit(cells), F.floor((F.col(c).cast("double") - b0) / max(b1 - b0, 1e-300) * cells))).cast("int")
    spans = rects.where("x0 <= x1 and y0 <= y1").select("qid", "x0", "x1", "y0", "y1", side("x0", box.x0, box.x1).alias("a"), (side("x1", box.x0, box.x1) - 1).alias("b"), side("y0", box.y0, box.y1).alias("c"), (side("y1", box.y0, box.y1) - 1).alias("d"))
    corners = F.array(*(F.struct(F.col(i).alias("i"), F.col(j).alias("j"), F.lit(sign).alias("sign")) for i, j, sign in (("b", "d", 1), ("a", "d", -1), ("b", "c", -1), ("a", "c", 1))))
    whole = spans.where("b > a and d > c").select("qid", F.explode(corners).alias("e")).select("qid", "e.i", "e.j", "e.sign").join(cube, ["i", "j"])
    whole = whole.select("qid", (F.col("n") * F.col("sign")).alias("n"), (F.col("s") * F.col("sign")).alias("s"))
    cutoff = points_in(points, rects).join(spans.select("qid", "a", "b", "c", "d"), "qid").where(~((cx > F.col("a")) & (cx <= F.col("b")) & (cy > F.col("c")) & (cy <= F.col("d"))))
    found = whole.union(cutoff.select("qid", F.lit(1).cast("long"), "w")).groupBy("qid").agg(F.sum("n").alias("cnt"), F.sum("s").alias("s"))
    return _all(rects, found).select("qid", F.coalesce("cnt", F.lit(0)).alias("cnt"), F.when(F.col("cnt") > 0, F.col("s")).alias("s"))
