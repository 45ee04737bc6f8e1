"""Every statistic by one pass over the points in the rectangles; the exact check of the indexed forms.

All functions take hits (rows of rangejoin.points_in, with qid, x, y, w) and, where a rectangle without points has an
answer, rects. Values are exact integers; averages and variances come from exact totals.
"""

from __future__ import annotations

from decimal import Decimal

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from planegrid.plans.storage import cut


def _all(rects: DataFrame, found: DataFrame) -> DataFrame:
    return rects.select("qid").join(found, "qid", "left")


def count_in(hits: DataFrame, rects: DataFrame) -> DataFrame:
    return _all(rects, hits.groupBy("qid").agg(F.count("*").alias("cnt"))).select("qid", F.coalesce("cnt", F.lit(0)).alias("cnt"))


def report_in(hits: DataFrame) -> DataFrame:
    return hits.select("qid", "x", "y", "w")


def moments_in(hits: DataFrame, rects: DataFrame) -> DataFrame:
    """qid, cnt, s, avg, var, std (population)."""
    wide = "decimal(38,0)"
    found = hits.groupBy("qid").agg(F.count("*").alias("cnt"), F.sum("w").alias("s"), F.sum(F.col("w").cast("decimal(19,0)") * F.col("w")).cast(wide).alias("s2"))
    return finish_moments(_all(rects, found))


def finish_moments(found: DataFrame) -> DataFrame:
    """found: qid, cnt, s, s2, exact."""
    n, s, s2 = (F.col(c).cast("double") for c in ("cnt", "s", "s2"))
    var = F.greatest((n * s2 - s * s) / (n * n), F.lit(0.0))
    some = F.col("cnt") > 0
    return found.select(
        "qid", F.coalesce("cnt", F.lit(0)).cast("long").alias("cnt"), F.when(some, F.col("s")).cast("long").alias("s"), F.when(some, F.round(s / n, 6)).alias("avg"), F.when(some, F.round(var, 4)).alias("var"), F.when(some, F.round(F.sqrt(var), 4)).alias("std")
    )


def group_in(hits: DataFrame, rects: DataFrame, merge: Column, identity: Column) -> DataFrame:
    """merge: an aggregate over w of a commutative group or semigroup, such as bit_xor, a sum modulo p, min, bit_or."""
    return _all(rects, hits.groupBy("qid").agg(merge.alias("val"))).select("qid", F.coalesce("val", identity).alias("val"))


def extrema_in(hits: DataFrame, rects: DataFrame) -> DataFrame:
    """qid, lo, hi and the points where they are, the smallest by (x, y) on ties."""
    least, most = F.min(F.struct("w", "x", "y")), F.min(F.struct((-F.col("w")).alias("w"), "x", "y"))
    found = hits.groupBy("qid").agg(least.alias("a"), most.alias("b"))
    return _all(rects, found).select("qid", F.col("a.w").alias("lo"), F.col("a.x").alias("lo_x"), F.col("a.y").alias("lo_y"), (-F.col("b.w")).alias("hi"), F.col("b.x").alias("hi_x"), F.col("b.y").alias("hi_y"))


def topk_values(hits: DataFrame, k: int, largest: bool = False) -> DataFrame:
    """qid, ord, w, x, y: the k smallest or largest weights, ties by (x, y)."""
    order = [F.desc("w") if largest else F.asc("w"), "x", "y"]
    return hits.withColumn("ord", F.row_number().over(Window.partitionBy("qid").orderBy(*order)).cast("long")).where(F.col("ord") <= k).select("qid", "ord", "w", "x", "y")


def frequencies(hits: DataFrame) -> DataFrame:
    """qid, w, freq, cnt: values are counted first, so what is added up for a rectangle is its distinct values."""
    each = hits.groupBy("qid", "w").agg(F.count("*").alias("freq"))
    return each.join(each.groupBy("qid").agg(F.sum("freq").alias("cnt")), "qid")


def majority_in(hits: DataFrame, alpha: str, inclusive: bool = False) -> DataFrame:
    """Values with more than (inclusive: at least) alpha of a rectangle's points; alpha is a decimal text."""
    a = Decimal(alpha)
    scale = 10 ** max(0, -a.as_tuple().exponent)
    left, right = F.col("freq") * F.lit(scale), F.col("cnt") * F.lit(int(a * scale))
    return frequencies(hits).where(left >= right if inclusive else left > right)


def topk_frequent(hits: DataFrame, k: int) -> DataFrame:
    """qid, ord, w, freq: the k most frequent values, ties by the smaller value; k = 1 is the mode."""
    order = Window.partitionBy("qid").orderBy(F.desc("freq"), "w")
    return frequencies(hits).withColumn("ord", F.row_number().over(order).cast("long")).where(F.col("ord") <= k).select("qid", "ord", "w", "freq")


def _runs(hits: DataFrame) -> DataFrame:
    """qid, w, cnt and the ranks (from, to] that the value's points take in sorted order.

    A rectangle's values are dealt over range partitions; running totals are taken within each and then over them, so
    no task meets all of a rectangle's values.
    """
    each = hits.groupBy("qid", "w").agg(F.count("*").alias("freq"))
    placed = cut(each.repartitionByRange("qid", "w").withColumn("_part", F.spark_partition_id()))
    parts = placed.groupBy("qid", "_part").agg(F.sum("freq").alias("_n"))
    every = Window.partitionBy("qid")
    before = F.sum("_n").over(every.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1))
    parts = parts.select("qid", "_part", F.coalesce(before, F.lit(0)).alias("_before"), F.sum("_n").over(every).alias("cnt"))
    inside = F.sum("freq").over(Window.partitionBy("qid", "_part").orderBy("w").rowsBetween(Window.unboundedPreceding, 0))
    rows = placed.join(parts, ["qid", "_part"]).withColumn("to", F.col("_before") + inside)
    return rows.select("qid", "w", "cnt", "to", (F.col("to") - F.col("freq")).alias("from"))


def kth_in(hits: DataFrame, wanted: DataFrame) -> DataFrame:
    """wanted: (qid, k); the k-th smallest weight, null outside 1..cnt."""
    runs = _runs(hits).select("qid", "w", "from", "to")
    found = wanted.join(runs, "qid").where("k > `from` and k <= `to`").select("qid", "k", "w")
    return wanted.join(found, ["qid", "k"], "left")


def quantiles_in(hits: DataFrame, rects: DataFrame, shares: list[str]) -> DataFrame:
    """qid, p, w: the value of rank ceil(p * cnt), at least 1; p = 0.5 is the lower median."""
    p = F.explode(F.array(*(F.lit(Decimal(s)).cast("decimal(9,8)") for s in shares)))
    asked = rects.select("qid", p.alias("p"))
    runs = _runs(hits)
    k = F.greatest(F.ceil(F.col("p") * F.col("cnt")).cast("long"), F.lit(1))
    found = asked.join(runs, "qid").withColumn("k", k).where("k > `from` and k <= `to`").select("qid", "p", "w")
    return asked.join(found, ["qid", "p"], "left").select("qid", F.col("p").cast("double").alias("p"), "w")


def top_fraction(hits: DataFrame, share: str) -> DataFrame:
    """The ceil(share * cnt) points with the largest weights, ties by (x, y).

    The least weight that is needed follows from the values' counts; only points of that weight are ordered, and only
    as many as are missing are taken.
    """
    runs = _runs(hits)
    wanted = F.ceil(F.lit(Decimal(share)) * F.col("cnt")).cast("long")
    edge = runs.withColumn("above", F.col("cnt") - F.col("to")).where((F.col("above") < wanted) & (F.col("cnt") - F.col("from") >= wanted))
    edge = edge.select("qid", F.col("w").alias("_least"), (wanted - F.col("above")).alias("_missing"))
    rows = hits.select("qid", "x", "y", "w").join(edge, "qid")
    over = rows.where("w > _least").select("qid", "x", "y", "w")
    tied = rows.where("w = _least").withColumn("ord", F.row_number().over(Window.partitionBy("qid").orderBy("x", "y"))).where("ord <= _missing")
    return over.union(tied.select("qid", "x", "y", "w"))


def count_values(hits: DataFrame, rects: DataFrame, w0: int, w1: int) -> DataFrame:
    return count_in(hits.where(F.col("w").between(w0, w1)), rects)


def neighbours(hits: DataFrame, rects: DataFrame, w: int, strict: bool = False) -> DataFrame:
    """qid, succ, pred: the least weight from w on and the largest up to it; strict leaves w itself out."""
    up, down = (F.col("w") > w, F.col("w") < w) if strict else (F.col("w") >= w, F.col("w") <= w)
    return _all(rects, hits.groupBy("qid").agg(F.min(F.when(up, F.col("w"))).alias("succ"), F.max(F.when(down, F.col("w"))).alias("pred"))).select("qid", "succ", "pred")


def distinct_values(hits: DataFrame, rects: DataFrame) -> DataFrame:
    found = hits.groupBy("qid").agg(F.count_distinct("w").alias("n"))
    return _all(rects, found).select("qid", F.coalesce("n", F.lit(0)).alias("n"))
