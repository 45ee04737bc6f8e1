"""A changing grid as indexed segments: a base and batches of changes, each with an index of its own.

A batch becomes signed points: what a point was counts off, what it is counts on. Its points with either sign are
indexed apart, so nothing that is stored is ever rewritten. Counts and sums add up over segments with their signs.
Minima and maxima have no inverse: every segment gives its few least points of both signs, which settle the answer up
to where the shortest of these lists ends; rectangles for which that is too early ask for more. Neighbouring segments
are joined when they have grown alike, and points that came and went between them vanish.

A batch has a number; one that comes again changes nothing.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from planegrid.operators import dynamic, ytree
from planegrid.operators import index as point_index
from planegrid.operators.index import PointIndex
from planegrid.plans.storage import fresh_path, settle, stored


@dataclass
class Segment:
    """rows: (pid, x, y, w, sign), stored; sides: the sign and index of the points with it."""

    rows: DataFrame
    size: int
    sides: list[tuple[int, PointIndex]]


@dataclass
class Store:
    """segments[0] is the base. numbers: of the batches that are in."""

    bits: int
    block: int
    segments: list[Segment] = field(default_factory=list)
    numbers: set[int] = field(default_factory=set)

    def _segment(self, rows: DataFrame) -> Segment:
        rows = stored(rows.select("pid", "x", "y", "w", F.col("sign").cast("int").alias("sign")), fresh_path(rows.sparkSession, "segment"))
        sizes = {r.sign: r["count"] for r in rows.groupBy("sign").count().collect()}
        return Segment(rows, sum(sizes.values()), [(sign, point_index.build(rows.where(F.col("sign") == sign).select("x", "y", "w"), self.bits, self.block)) for sign in sorted(sizes)])

    def living(self) -> DataFrame:
        """(pid, x, y, w) of the points that are there now."""
        every = reduce(DataFrame.union, [s.rows for s in self.segments])
        return every.groupBy("pid", "x", "y", "w").agg(F.sum("sign").alias("n")).where("n > 0").select("pid", "x", "y", "w")

    def append(self, number: int, log: DataFrame) -> Segment | None:
        """log: a batch of changes (seq, op, pid, x, y, w), see the module dynamic. None if the batch is in already."""
        if number in self.numbers:
            return None
        new = settle(dynamic.latest(log))
        # of each segment only the points that the batch names
        touched = reduce(DataFrame.union, [s.rows.join(new.select("pid"), "pid", "left_semi") for s in self.segments])
        was = settle(touched.groupBy("pid", "x", "y", "w").agg(F.sum("sign").alias("n")).where("n > 0").select("pid", "x", "y", "w"))
        is_now = new.where("op != 'delete'").join(was.select("pid", F.col("x").alias("bx"), F.col("y").alias("by")), "pid", "left")
        is_now = is_now.select("pid", F.coalesce("x", "bx").alias("x"), F.coalesce("y", "by").alias("y"), "w", F.lit(1).alias("sign"))
        found = self._segment(was.select("pid", "x", "y", "w", F.lit(-1).alias("sign")).union(is_now))
        self.segments.append(found)
        self.numbers.add(number)
        return found

    def compact(self, factor: int = 4) -> int:
        """Joins neighbours until each segment is more than factor times all after it; the number of points written."""
        groups, at, out, written = dynamic.tiers([s.size for s in self.segments], factor), 0, [], 0
        for group in groups:
            part = self.segments[at : at + len(group)]
            at += len(group)
            if len(part) > 1:
                net = reduce(DataFrame.union, [s.rows for s in part]).groupBy("pid", "x", "y", "w").agg(F.sum("sign").alias("sign")).where("sign != 0")
                part = [self._segment(net)]
                written += part[0].size
            out += part
        self.segments = out
        return written

    def sums(self, rects: DataFrame) -> DataFrame:
        """qid, cnt, s."""
        parts = []
        for sign, index in (x for s in self.segments for x in s.sides):
            found = ytree.moments_in(index.tree, index.bounds(rects))
            parts.append(found.select("qid", (F.col("cnt") * sign).alias("cnt"), (F.coalesce("s", F.lit(0)) * sign).alias("s")))
        total = reduce(DataFrame.union, parts).groupBy("qid").agg(F.sum("cnt").alias("cnt"), F.sum("s").alias("s"))
        return total.select("qid", F.col("cnt").cast("long").alias("cnt"), F.when(F.col("cnt") > 0, F.col("s")).cast("long").alias("s"))

    def least(self, rects: DataFrame, largest: bool = False, start: int = 4) -> DataFrame:
        """qid, w, x, y: the point with the least (or largest) weight, ties by (x, y); no row in an empty rectangle."""
        key = F.struct((-F.col("w") if largest else F.col("w")).alias("w"), "x", "y").alias("key")
        open_, k, done = settle(rects), start, []
        while not open_.isEmpty():
            lists = []
            for n, (sign, index) in enumerate(x for s in self.segments for x in s.sides):
                top = index.located(ytree.topk_in(index.tree, index.bounds(open_), k, largest))
                lists.append(top.select("qid", F.lit(n).alias("list"), key, F.lit(sign).alias("sign")))
            every = settle(reduce(DataFrame.union, lists))
            # a full list may go on after its last key
            ends = every.groupBy("qid", "list").agg(F.count("*").alias("n"), F.max("key").alias("last")).where(F.col("n") >= k).groupBy("qid").agg(F.min("last").alias("until"))
            net = every.groupBy("qid", "key").agg(F.sum("sign").alias("n")).join(ends, "qid", "left")
            found = settle(net.where("n > 0 and (until is null or key <= until)").groupBy("qid").agg(F.min("key").alias("key")))
            done.append(found)
            open_ = settle(open_.join(found, "qid", "left_anti").join(ends, "qid", "left_semi"))
            k *= 4
        return reduce(DataFrame.union, done).select("qid", ((-F.col("key.w")) if largest else F.col("key.w")).alias("w"), "key.x", "key.y")


def start(base: DataFrame, bits: int = 4, block: int = 256) -> Store:
    """base: (pid, x, y, w)."""
    store = Store(bits, block)
    store.segments.append(store._segment(base.select("pid", "x", "y", "w", F.lit(1).alias("sign"))))
    return store
