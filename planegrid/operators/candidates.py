"""Frequent values with the threshold fixed when the index is built.

Every aligned run of 2**h blocks of a node holds the values that more than alpha of its entries have, fewer than
1 / alpha of them. A value that frequent in a union is that frequent in one of the parts, so candidates of a rectangle are those of
the runs inside its cover and the values at the ends of the cover's intervals. Each is then counted in a grid of its
value's points alone.
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from planegrid.operators import blocks, scan, ytree
from planegrid.operators.blocks import Blocks
from planegrid.operators.valuegrids import ValueGrids
from planegrid.plans.storage import fresh_path, settle


def build(tree: ytree.YTree, num: int, den: int, path: str | None = None) -> list[Blocks]:
    """For every level, by a run's first block (node, h, w): values with more than num / den of the run's entries."""
    out, total = [], -(-tree.n // tree.block)
    path = path or fresh_path(tree.levels[0].rows.sparkSession, "lists")
    high = max(1, total.bit_length())
    heights = F.explode(F.sequence(F.lit(0), F.lit(high))).alias("h")
    for j, level in enumerate(tree.levels):
        each = level.rows.select("node", "blk", F.explode("vals").alias("w")).groupBy("node", "blk", "w").agg(F.count("*").alias("f"))
        idx = F.expr("shiftright(blk, h)").alias("idx")
        runs = each.select("node", "w", "f", "blk", heights).groupBy("node", "h", idx, "w").agg(F.sum("f").alias("f"))
        sizes = level.rows.select("node", "n", "blk", heights).groupBy("node", "h", idx).agg(F.sum("n").alias("n"))
        kept = runs.join(sizes, ["node", "h", "idx"]).where(F.col("f") * den > F.col("n") * num)
        out.append(blocks.save(kept.select(tree.number(j, F.col("node"), F.expr("shiftleft(idx, h)")).alias("gblk"), "h", "w"), total, f"{path}/{j}"))
    return out


def values_for(tree: ytree.YTree, lists: list[Blocks], bounds: DataFrame) -> DataFrame:
    """(qid, w): every value that may have more than the threshold in a rectangle, and some that don't."""
    whole, ends = ytree.cover(tree, bounds)
    parts = [ytree._leaf_points(tree, ends).select("qid", "w")]
    for j in range(1, tree.depth + 1):
        touched, inner = ytree.pieces(tree, whole.where(F.col("lvl") == j), j)
        parts.append(touched.select("qid", F.explode("part.w").alias("w")))
        parts.append(lists[j].meet(inner.select("qid", "h", "at"), "at", ["h", "w"], "_run").where("h = h_run").select("qid", F.col("w_run").alias("w")))
    return settle(reduce(DataFrame.union, parts).distinct())


def majority_fixed(tree: ytree.YTree, lists: list[Blocks], grids: ValueGrids, bounds: DataFrame, num: int, den: int) -> DataFrame:
    """qid, w, freq, cnt of the values with more than num / den, which is not below the threshold of the lists."""
    freq = grids.count(bounds, values_for(tree, lists, bounds))
    cnt = ytree.count_in(tree, bounds)
    return freq.join(cnt, "qid").where(F.col("freq") * den > F.col("cnt") * num).select("qid", "w", "freq", "cnt")


def unverified(tree: ytree.YTree, lists: list[Blocks], bounds: DataFrame) -> DataFrame:
    """A baseline: the candidates as they are, without counting; holds all answers and some more."""
    return values_for(tree, lists, bounds)


def precision(candidates: DataFrame, found: DataFrame, rects: DataFrame) -> DataFrame:
    """qid, candidates, right: how many unverified answers there are, and how many of them hold."""
    every = candidates.groupBy("qid").agg(F.count("*").alias("candidates"))
    good = found.groupBy("qid").agg(F.count("*").alias("right"))
    zero = lambda c: F.coalesce(c, F.lit(0)).alias(c)
    return scan._all(rects, every).join(good, "qid", "left").select("qid", zero("candidates"), zero("right"))
