"""Dominant points by descending the tree, all rectangles and all branches of a level at once.

The cover's nodes and the points in the leaves at its ends stand in order of y. A node is kept if its point that is
farthest in x lies farther than that of every node before it; then it holds a dominant point, so a level never keeps
more nodes than there are dominant points. Kept nodes give way to their children, until leaves give way to points. The
other corners turn the axes: they look at nodes from the other end of y, or at a node's first point instead of its last.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from planegrid.operators import staircase, ytree
from planegrid.operators.index import PointIndex
from planegrid.operators.ytree import YTree
from planegrid.plans.storage import settle


def _farthest(tree: YTree, rows: DataFrame, j: int, a: int, b: int) -> DataFrame:
    """Nodes (qid, node, lo, hi) of level j with lvl, top (place in y, the corner's end first) and far (x-rank towards the corner)."""
    at = F.col("hi") - 1 if a > 0 else F.col("lo")
    rows = rows.withColumn("_i", at % tree.block).withColumn("_at", tree.number(j, F.col("node"), F.floor(at / tree.block)))
    rows = tree.levels[j].meet(rows, "_at", ["xrs"])
    top = F.shiftleft(F.col("node") + 1, tree.low(j)) if b > 0 else -F.shiftleft("node", tree.low(j))
    return rows.select("qid", F.lit(j).alias("lvl"), "node", "lo", "hi", top.alias("top"), (F.expr("xrs[cast(_i as int)]") * a).alias("far"))


def _kept(rows: DataFrame) -> DataFrame:
    before = Window.partitionBy("qid").orderBy(F.desc("top"), "lvl").rowsBetween(Window.unboundedPreceding, -1)
    return settle(rows.withColumn("_run", F.max("far").over(before)).where("_run is null or far > _run").drop("_run"))


def dominant_ranks(tree: YTree, bounds: DataFrame, corner: str = "NE", trace: list[int] | None = None) -> DataFrame:
    """(qid, xr, yr) of the points that none beats towards the corner, in ranks. trace: gets the number of nodes kept on each level."""
    a, b = staircase.CORNERS[corner]
    whole, ends = ytree.cover(tree, bounds)
    none = F.lit(0).cast("long")
    place = lambda yr: yr + 1 if b > 0 else -yr
    as_point = lambda rows: rows.select("qid", F.lit(tree.depth + 1).alias("lvl"), none.alias("node"), none.alias("lo"), none.alias("hi"), place(F.col("yr")).alias("top"), (F.col("xr") * a).alias("far"))
    points = as_point(ytree._leaf_points(tree, ends))
    active = _kept(reduce(DataFrame.union, [_farthest(tree, whole.where(F.col("lvl") == j).drop("lvl"), j, a, b) for j in range(1, tree.depth + 1)], points))
    every = F.sequence(F.lit(0).cast("long"), F.lit(tree.fan - 1).cast("long"))
    for j in range(1, tree.depth):
        if trace is not None:
            trace.append(active.where(F.col("lvl") <= tree.depth).count())
        here = active.where(F.col("lvl") == j).select("qid", "node", "lo", "hi")
        active = _kept(active.where(F.col("lvl") != j).union(_farthest(tree, ytree._children(tree, here, j, every, ["qid"]), j + 1, a, b)))
    leaves = active.where(F.col("lvl") == tree.depth).withColumn("_at", F.col("node"))
    found = tree.levels[-1].meet(leaves, "_at", ["xrs", "yrs"]).select("qid", F.expr("explode(slice(arrays_zip(xrs, yrs), cast(lo + 1 as int), cast(hi - lo as int)))").alias("e"))
    found = as_point(found.select("qid", F.col("e.xrs").alias("xr"), F.col("e.yrs").alias("yr")))
    last = _kept(found.union(active.where(F.col("lvl") > tree.depth)))
    return last.select("qid", (F.col("far") * a).alias("xr"), (F.col("top") - 1 if b > 0 else -F.col("top")).alias("yr"))


def dominant_points(index: PointIndex, rects: DataFrame, corner: str = "NE", trace: list[int] | None = None) -> DataFrame:
    """qid, ord, x, y, from the farthest y on; points that agree in both coordinates are one.

    Ranks order ties towards one diagonal only; towards the other corners more points may come out of the descent than
    are dominant, never fewer, so the values themselves have the last word.
    """
    found = dominant_ranks(index.tree, index.bounds(rects), corner, trace)
    return staircase.dominant_points(index.located(found), corner)


def visible_points(index: PointIndex, eyes: DataFrame, direction: str) -> DataFrame:
    """eyes: (qid, qx, qy); as staircase.visible_points(), on the index."""
    found = dominant_points(index, staircase.quadrant(eyes, direction), staircase.TOWARDS[direction])
    return found.select("qid", F.lit(direction).alias("direction"), "x", "y")
