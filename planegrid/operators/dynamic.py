"""Grids that change: an append-only log of inserts, deletes and new weights over a base.

A log row is (seq, op, pid, x, y, w), op being insert, delete or set; of a point's rows the last by seq holds. Group
statistics (counts, sums) add signed rows: what a point was counts off, what it is counts on, so a base's answer is
corrected by the log alone. Minima, quantiles and staircases have no inverse; they are answered on the points that are
alive, where the base is met by an anti-join with the log's points.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def latest(log: DataFrame, upto: int | None = None) -> DataFrame:
    """The row of each point that holds at a place of the log; a repeated batch changes nothing."""
    rows = log if upto is None else log.where(F.col("seq") <= upto)
    last = rows.groupBy("pid").agg(F.max(F.struct("seq", "op", "x", "y", "w")).alias("r"))
    return last.select("pid", "r.*")


def alive(base: DataFrame, log: DataFrame, upto: int | None = None) -> DataFrame:
    """base (pid, x, y, w) with the log's changes applied; set keeps the coordinates that it doesn't give."""
    new = latest(log, upto)
    kept = base.join(new.select("pid"), "pid", "left_anti").select("pid", "x", "y", "w")
    changed = new.where("op != 'delete'").join(base.select("pid", F.col("x").alias("bx"), F.col("y").alias("by")), "pid", "left")
    return kept.union(changed.select("pid", F.coalesce("x", "bx"), F.coalesce("y", "by"), "w"))


def signed(base: DataFrame, log: DataFrame, upto: int | None = None) -> DataFrame:
    """(x, y, w, sign) of the points that the log touches: as they were in the base and as they are."""
    new = latest(log, upto)
    touched = base.join(new.select("pid"), "pid", "left_semi").select("x", "y", "w", F.lit(-1).alias("sign"))
    is_now = new.where("op != 'delete'").join(base.select("pid", F.col("x").alias("bx"), F.col("y").alias("by")), "pid", "left")
    return touched.union(is_now.select(F.coalesce("x", "bx"), F.coalesce("y", "by"), "w", F.lit(1)))


def corrected_sums(base_answer: DataFrame, changes: DataFrame) -> DataFrame:
    """base_answer (qid, cnt, s) of a base or its index, and changes: hits of signed() with qid. Exact."""
    delta = changes.groupBy("qid").agg(F.sum("sign").alias("dn"), F.sum(F.col("w") * F.col("sign")).alias("ds"))
    both = base_answer.join(delta, "qid", "left").select("qid", (F.col("cnt") + F.coalesce("dn", F.lit(0))).alias("cnt"), (F.coalesce("s", F.lit(0)) + F.coalesce("ds", F.lit(0))).alias("s"))
    return both.select("qid", F.col("cnt").cast("long").alias("cnt"), F.when(F.col("cnt") > 0, F.col("s")).cast("long").alias("s"))


def tiers(sizes: list[int], factor: int = 4) -> list[list[int]]:
    """Segments, oldest first, that a compaction joins: neighbours until each is more than factor times all after it."""
    groups: list[list[int]] = []
    for size in sizes:
        groups.append([size])
        while len(groups) > 1 and sum(groups[-2]) <= factor * sum(groups[-1]):
            last = groups.pop()
            groups[-1] += last
    return groups


def compacted(segments: DataFrame) -> DataFrame:
    """One log in place of several: each point's last row."""
    order = Window.partitionBy("pid").orderBy(F.desc("seq"))
    return segments.withColumn("_n", F.row_number().over(order)).where("_n = 1").select("seq", "op", "pid", "x", "y", "w")
