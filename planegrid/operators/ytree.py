"""A tree over the y-ranks of a grid, as one stored table of packed blocks for each level.

A node is a prefix of the y-rank; its points stand in x-order. A block holds `block` of them: the next digit of each
as bit planes, how often each digit occurred in the node before the block, the weights, and running totals. Nodes of
at most `block` points are leaves, where points are looked at one by one. A rectangle's y-interval is covered by whole
nodes, at most 2 * fanout of them on a level, each with the interval of places that the x-interval takes there; the
places in a child follow from counting digits at both ends.

Levels are Parquet files in the order of their blocks. A batch of rectangles goes down level by level; its few rows
meet the blocks that they ask for, and no level is shuffled. Totals over many blocks run in two steps (superblocks,
then blocks inside), so no window meets all blocks of a large node.
"""

from __future__ import annotations

import json
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from planegrid.functions import bits as bit_sql
from planegrid.operators import blocks
from planegrid.operators.blocks import Blocks
from planegrid.operators.rankspace import positions
from planegrid.operators.scan import finish_moments
from planegrid.plans.storage import cut, fresh_path, settle

SUPER = 4096
#: Bits of the size of a node whose points and blocks may meet in one task.
ALONE = 20
WIDE = "decimal(38,0)"


@dataclass
class YTree:
    """levels[j]: blocks of level j; the last level holds leaves. dyads[j]: extrema of aligned runs of blocks."""

    n: int
    bits: int
    block: int
    leaf_bits: int
    levels: list[Blocks]
    dyads: list[Blocks]
    path: str

    @property
    def depth(self) -> int:
        return len(self.levels) - 1

    @property
    def fan(self) -> int:
        return 1 << self.bits

    def low(self, j: int) -> int:
        """Bits of the y-rank below a node of level j."""
        return self.leaf_bits + (self.depth - j) * self.bits

    def shift(self, j: int) -> int:
        """Bits of the y-rank below the digit that level j stores."""
        return self.low(j) - self.bits

    def number(self, j: int, node: Column, blk: Column) -> Column:
        """A block's number on its level: nodes are full but for the last one."""
        return (node * F.lit(1 << max(0, self.low(j) - self.block.bit_length() + 1)) + blk).cast("long")


def shape(n: int, bits: int, block: int) -> tuple[int, int]:
    """Depth and leaf bits for n points."""
    height = max(1, (n - 1).bit_length())
    leaf = min(height, block.bit_length() - 1)
    return max(1, -(-(height - leaf) // bits)), leaf


def running(blocks: DataFrame, names: dict[str, str]) -> DataFrame:
    """Adds for each name the total of its column over the node's earlier blocks."""
    blocks = blocks.withColumn("_super", F.floor(F.col("blk") / SUPER))
    totals = blocks.groupBy("node", "_super").agg(*(F.sum(c).alias(f"_{c}") for c in names.values()))
    before = Window.partitionBy("node").orderBy("_super").rowsBetween(Window.unboundedPreceding, -1)
    totals = totals.select("node", "_super", *(F.coalesce(F.sum(f"_{c}").over(before), F.lit(0)).alias(f"_{c}") for c in names.values()))
    inside = Window.partitionBy("node", "_super").orderBy("blk").rowsBetween(Window.unboundedPreceding, -1)
    out = blocks.join(totals, ["node", "_super"])
    return out.withColumns({name: F.coalesce(F.sum(c).over(inside), F.lit(0)) + F.col(f"_{c}") for name, c in names.items()}).drop("_super", *(f"_{c}" for c in names.values()))


def _level(tree: YTree, ranked: DataFrame, j: int, depth: int) -> DataFrame:
    """The blocks of level j: gblk, node, blk and what they hold."""
    block, fan = tree.block, tree.fan
    low = tree.leaf_bits + (depth - j) * tree.bits
    rows = ranked.select(F.shiftright("yr", low).alias("node"), "xr", "yr", "w")
    alone = min(low, max(1, (tree.n - 1).bit_length())) <= ALONE
    if j == 0:
        rows = rows.withColumn("pos", F.col("xr"))
    elif alone:  # one shuffle by node serves the places, the blocks and their running totals
        rows = rows.withColumn("pos", (F.row_number().over(Window.partitionBy("node").orderBy("xr")) - 1).cast("long"))
    else:
        rows = positions(rows, ["node", "xr"], "_at").withColumn("pos", F.col("_at") - F.col("node") * (1 << low))
    rows = rows.withColumn("d", F.shiftright("yr", low - tree.bits).bitwiseAND(F.lit(fan - 1)) if j < depth else F.lit(0).cast("long"))
    square = F.col("w").cast("decimal(19,0)") * F.col("w")
    each = [F.sort_array(F.collect_list(F.struct("pos", "d", "w", "xr", "yr"))).alias("e"), F.count("*").alias("n"), F.sum(F.col("w").cast(WIDE)).alias("_s"), F.sum(square).cast(WIDE).alias("_q"),
            F.min(F.struct("w", "xr")).alias("least"), F.min(F.struct((-F.col("w")).alias("w"), "xr")).alias("most")]
    names = {"psum": "_s", "psum2": "_q"}
    if j < depth:
        each += [F.count_if(F.col("d") == c).alias(f"_d{c}") for c in range(fan)]
        names |= {f"_b{c}": f"_d{c}" for c in range(fan)}
    made = rows.groupBy("node", F.floor(F.col("pos") / block).alias("blk")).agg(*each)
    made = made.select(*(c for c in made.columns if c != "e"), F.col("e.d").alias("digits"), F.col("e.w").alias("vals"), F.col("e.xr").alias("xrs"), F.col("e.yr").alias("yrs"))
    if alone:
        before = Window.partitionBy("node").orderBy("blk").rowsBetween(Window.unboundedPreceding, -1)
        made = made.withColumns({name: F.coalesce(F.sum(c).over(before), F.lit(0)) for name, c in names.items()})
    else:
        made = running(cut(made), names)
    columns = ["node", "blk", "n", F.col("psum").cast(WIDE).alias("psum"), F.col("psum2").cast(WIDE).alias("psum2"), "least", "most", "vals", "xrs"]
    if j < depth:
        columns += [bit_sql.packed("digits", tree.bits).alias("planes"), F.array(*(f"_b{c}" for c in range(fan))).alias("before")]
    else:
        columns += ["yrs"]
    ratio = max(0, low - block.bit_length() + 1)
    return made.select((F.col("node") * (1 << ratio) + F.col("blk")).cast("long").alias("gblk"), *columns)


def build(ranked: DataFrame, bits: int = 4, block: int = 256, extrema: bool = True, path: str | None = None) -> YTree:
    """ranked: (xr, yr, w) of rank_space(). bits: of a digit, so the fan-out is 2**bits; block: entries, a power of two from 64 on.

    The levels are written below path; load() reads them again in any session.
    """
    if block < 64 or block & (block - 1):
        raise ValueError("block must be a power of two, 64 at least")
    path = path or fresh_path(ranked.sparkSession, "ytree")
    n = ranked.count()
    depth, leaf = shape(n, bits, block)
    tree = YTree(n, bits, block, leaf, [], [], path)
    total = -(-n // block)
    for j in range(depth + 1):
        level = blocks.save(_level(tree, ranked, j, depth), total, f"{path}/level-{j}")
        tree.levels.append(level)
        if extrema:
            high = max(1, total.bit_length())
            runs = level.rows.select("node", "blk", "least", "most", F.explode(F.sequence(F.lit(0), F.lit(high))).alias("h"))
            runs = runs.groupBy("node", "h", F.expr("shiftright(blk, h)").alias("idx")).agg(F.min("least").alias("least"), F.min("most").alias("most"), F.min("blk").alias("blk"))
            # a run lies with its first block
            ratio = max(0, leaf + (depth - j) * bits - block.bit_length() + 1)
            tree.dyads.append(blocks.save(runs.withColumn("gblk", (F.col("node") * (1 << ratio) + F.col("blk")).cast("long")).drop("blk"), total, f"{path}/dyads-{j}"))
    about = {"n": n, "bits": bits, "block": block, "leaf_bits": leaf, "levels": [x.about for x in tree.levels], "dyads": [x.about for x in tree.dyads]}
    ranked.sparkSession.createDataFrame([(json.dumps(about),)], "about string").coalesce(1).write.parquet(f"{path}/about")  # last, so a reader sees whole trees only
    return tree


def load(spark: SparkSession, path: str) -> YTree:
    """A stored tree."""
    about = json.loads(spark.read.parquet(f"{path}/about").first().about)
    parts = {name: [blocks.load(spark, x) for x in about.pop(name)] for name in ("levels", "dyads")}
    return YTree(**about, **parts, path=path)


def _ends(tree: YTree, rows: DataFrame, j: int, columns: list[str]) -> DataFrame:
    """rows (node, lo, hi), lo < hi, with the columns of the blocks that hold the last entry before lo and before hi, and the entries to take there.

    Where lo is 0, the first block stands in, of which no entry is taken.
    """
    for side in ("lo", "hi"):
        blk = F.floor(F.greatest(F.col(side) - 1, F.lit(0)) / tree.block)
        rows = rows.withColumn(f"_at_{side}", tree.number(j, F.col("node"), blk)).withColumn(f"off_{side}", (F.col(side) - blk * tree.block).cast("long"))
        rows = tree.levels[j].meet(rows, f"_at_{side}", columns, f"_{side}").drop(f"_at_{side}")
    return rows


def _children(tree: YTree, rows: DataFrame, j: int, digits: Column, keep: list[str]) -> DataFrame:
    """rows (node, lo, hi, keep) of level j: the non-empty children (node, lo, hi, keep) with one of the digits, an array."""
    rows = _ends(tree, rows, j, ["planes", "before"]).withColumn("c", F.explode(digits))
    place = lambda side: F.expr(f"before_{side}[cast(c as int)] + {bit_sql.rank(f'planes_{side}', tree.bits, 'c', f'off_{side}')}").alias(side)
    return rows.select(*keep, (F.col("node") * tree.fan + F.col("c")).alias("node"), place("lo"), place("hi")).where("lo < hi")


def cover(tree: YTree, bounds: DataFrame) -> tuple[DataFrame, DataFrame]:
    """bounds: (qid, xlo, xhi, ylo, yhi) in ranks, half open.

    Returns whole nodes (qid, lvl, node, lo, hi), disjoint and by y together the interval but for its ends, and the
    leaves at the ends (qid, node, lo, hi, ylo, yhi), in which y has to be looked at.
    """
    zero = F.lit(0).cast("long")
    open_ = bounds.where("xlo < xhi and ylo < yhi").select("qid", "ylo", "yhi", zero.alias("node"), F.col("xlo").alias("lo"), F.col("xhi").alias("hi"))
    found = []
    for j in range(tree.depth):
        step = 1 << tree.shift(j)
        base = F.col("node") * (tree.fan * step)
        first = F.greatest(F.floor((F.col("ylo") - base) / step), F.lit(0))
        last = F.least(F.floor((F.col("yhi") - 1 - base) / step), F.lit(tree.fan - 1))
        digits = F.when(first <= last, F.sequence(first, last)).otherwise(F.array().cast("array<bigint>"))
        rows = _children(tree, open_, j, digits, ["qid", "ylo", "yhi"])
        rows = settle(rows.withColumn("whole", (F.col("node") * step >= F.col("ylo")) & ((F.col("node") + 1) * step <= F.col("yhi"))))
        found.append(rows.where("whole").select("qid", F.lit(j + 1).alias("lvl"), "node", "lo", "hi"))
        open_ = rows.where("not whole").drop("whole")
    return settle(reduce(DataFrame.union, found)), open_.select("qid", "node", "lo", "hi", "ylo", "yhi")


def _leaf_points(tree: YTree, ends: DataFrame) -> DataFrame:
    """(qid, xr, yr, w) of the rectangles' points in the leaves at the ends; a leaf is one block."""
    rows = tree.levels[-1].meet(ends.withColumn("_at", F.col("node")), "_at", ["vals", "xrs", "yrs"])
    rows = rows.select("qid", "ylo", "yhi", F.expr("explode(slice(arrays_zip(xrs, yrs, vals), cast(lo + 1 as int), cast(hi - lo as int)))").alias("e"))
    return rows.where("e.yrs >= ylo and e.yrs < yhi").select("qid", F.col("e.xrs").alias("xr"), F.col("e.yrs").alias("yr"), F.col("e.vals").alias("w"))


def count_in(tree: YTree, bounds: DataFrame) -> DataFrame:
    whole, ends = cover(tree, bounds)
    parts = whole.select("qid", (F.col("hi") - F.col("lo")).alias("n")).union(_leaf_points(tree, ends).select("qid", F.lit(1).cast("long")))
    return bounds.select("qid").join(parts.groupBy("qid").agg(F.sum("n").alias("cnt")), "qid", "left").select("qid", F.coalesce("cnt", F.lit(0)).alias("cnt"))


def moments_in(tree: YTree, bounds: DataFrame) -> DataFrame:
    """qid, cnt, s, avg, var, std: differences of running totals at both ends of every whole node, and the leaves' points."""
    whole, ends = cover(tree, bounds)
    parts = [_leaf_points(tree, ends).select("qid", F.lit(1).cast("long").alias("cnt"), F.col("w").cast(WIDE).alias("s"), (F.col("w").cast("decimal(19,0)") * F.col("w")).cast(WIDE).alias("s2"))]
    for j in range(1, tree.depth + 1):
        rows = _ends(tree, whole.where(F.col("lvl") == j), j, ["psum", "psum2", "vals"])
        upto = lambda side, total, term: f"{total}_{side} + aggregate(slice(vals_{side}, 1, cast(off_{side} as int)), cast(0 as {WIDE}), (a, v) -> cast(a + {term} as {WIDE}))"
        between = lambda total, term: F.expr(f"cast({upto('hi', total, term)} - ({upto('lo', total, term)}) as {WIDE})")
        parts.append(rows.select("qid", (F.col("hi") - F.col("lo")).alias("cnt"), between("psum", "v").alias("s"), between("psum2", "cast(v as decimal(19,0)) * v").alias("s2")))
    found = reduce(DataFrame.union, parts).groupBy("qid").agg(F.sum("cnt").alias("cnt"), F.sum("s").alias("s"), F.sum("s2").alias("s2"))
    return finish_moments(bounds.select("qid").join(found, "qid", "left"))


def pieces(tree: YTree, rows: DataFrame, j: int) -> tuple[DataFrame, DataFrame]:
    """Whole nodes (qid, node, lo, hi) of level j, their entries taken apart.

    First (qid, part): (w, xr) of the entries of the one or two blocks at the ends, as far as they lie inside. Second
    (qid, node, h, idx, at): aligned runs of 2**h blocks that make up the blocks between, none of which lies in a
    larger one; at is the number of a run's first block.
    """
    rows = rows.select("qid", "node", "lo", "hi", F.floor(F.col("lo") / tree.block).alias("b0"), F.floor((F.col("hi") - 1) / tree.block).alias("b1"))
    touched = rows.withColumn("blk", F.explode(F.array_distinct(F.array("b0", "b1")))).withColumn("_at", tree.number(j, F.col("node"), F.col("blk")))
    touched = tree.levels[j].meet(touched, "_at", ["vals", "xrs"])
    start = F.greatest(F.col("lo") - F.col("blk") * tree.block, F.lit(0))
    stop = F.least(F.col("hi") - F.col("blk") * tree.block, F.lit(tree.block))
    zipped = F.transform(F.arrays_zip("vals", "xrs"), lambda e: F.struct(e["vals"].alias("w"), e["xrs"].alias("xr")))
    touched = touched.select("qid", F.slice(zipped, (start + 1).cast("int"), (stop - start).cast("int")).alias("part"))
    inner = rows.where("b1 - b0 > 1").select("qid", "node", (F.col("b0") + 1).alias("a"), F.col("b1").alias("z"))
    inner = inner.withColumn("h", F.explode(F.sequence(F.lit(0), F.floor(F.log2(F.col("z") - F.col("a"))).cast("int"))))
    inner = inner.withColumn("idx", F.expr("explode(array_distinct(array(shiftright(a + shiftleft(1L, h) - 1, h), shiftright(z, h) - 1)))"))
    inside = "shiftleft(idx, h) >= a and shiftleft(idx + 1, h) <= z"
    alone = "shiftleft(shiftright(idx, 1), h + 1) < a or shiftleft(shiftright(idx, 1) + 1, h + 1) > z"
    return touched, inner.where(f"{inside} and ({alone})").select("qid", "node", "h", "idx", tree.number(j, F.col("node"), F.expr("shiftleft(idx, h)")).alias("at"))


def runs_of(tree: YTree, inner: DataFrame, j: int, columns: list[str]) -> DataFrame:
    """inner (h, at, ...) with the columns of its runs of blocks on level j."""
    return tree.dyads[j].meet(inner, "at", ["h", *columns], "_run").where("h = h_run").drop("h_run")


def _negated(s: Column) -> Column:
    return F.struct((-s["w"]).alias("w"), s["xr"].alias("xr"))


def extrema_in(tree: YTree, bounds: DataFrame) -> DataFrame:
    """qid, lo, lo_xr, hi, hi_xr: least and largest weights with the first x-rank that has them; of every whole node the
    parts of two blocks at its ends, and aligned runs of the blocks between.
    """
    whole, ends = cover(tree, bounds)
    point = F.struct("w", "xr")
    parts = [_leaf_points(tree, ends).select("qid", point.alias("least"), _negated(point).alias("most"))]
    for j in range(1, tree.depth + 1):
        touched, inner = pieces(tree, whole.where(F.col("lvl") == j), j)
        parts.append(touched.select("qid", F.array_min("part").alias("least"), F.array_min(F.transform("part", _negated)).alias("most")))
        parts.append(runs_of(tree, inner, j, ["least", "most"]).select("qid", F.col("least_run").alias("least"), F.col("most_run").alias("most")))
    found = reduce(DataFrame.union, parts).groupBy("qid").agg(F.min("least").alias("a"), F.min("most").alias("b"))
    return bounds.select("qid").join(found, "qid", "left").select("qid", F.col("a.w").alias("lo"), F.col("a.xr").alias("lo_xr"), (-F.col("b.w")).alias("hi"), F.col("b.xr").alias("hi_xr"))


def topk_in(tree: YTree, bounds: DataFrame, k: int, largest: bool = False) -> DataFrame:
    """qid, ord, w, xr: the k smallest or largest weights, ties by the x-rank.

    Every run of blocks knows its extreme entry. Of a rectangle's runs and single entries only the k with the least
    stay; runs that stay are split in two, until single blocks are opened. So at most k runs are open at a time.
    """
    name, sign = ("most", -1) if largest else ("least", 1)
    turn = lambda s: _negated(s) if largest else s
    whole, ends = cover(tree, bounds)
    none = F.lit(None)
    columns = ["qid", "key", "j", "node", "h", "idx", "at"]
    as_row = lambda df: df.select("qid", "key", *(none.cast(t).alias(c) for c, t in (("j", "int"), ("node", "long"), ("h", "int"), ("idx", "long"), ("at", "long"))))
    parts = [as_row(_leaf_points(tree, ends).select("qid", turn(F.struct("w", "xr")).alias("key")))]
    for j in range(1, tree.depth + 1):
        touched, inner = pieces(tree, whole.where(F.col("lvl") == j), j)
        parts.append(as_row(touched.select("qid", F.explode("part").alias("e")).select("qid", turn(F.col("e")).alias("key"))))
        parts.append(runs_of(tree, inner, j, [name]).select("qid", F.col(f"{name}_run").alias("key"), F.lit(j).alias("j"), "node", "h", "idx", "at"))
    order = Window.partitionBy("qid").orderBy("key", F.col("j").isNotNull())
    least = lambda df: settle(df.withColumn("_n", F.row_number().over(order)).where(F.col("_n") <= k).drop("_n"))
    now = least(reduce(DataFrame.union, [p.select(columns) for p in parts]))
    while not (open_ := now.where("j is not null")).isEmpty():
        parts = [now.where("j is null")]
        for j in range(1, tree.depth + 1):
            here = open_.where(F.col("j") == j)
            blk = here.where("h = 0").select("qid", F.col("at"))
            opened = tree.levels[j].meet(blk, "at", ["vals", "xrs"]).select("qid", F.explode(F.arrays_zip("vals", "xrs")).alias("e"))
            parts.append(as_row(opened.select("qid", turn(F.struct(F.col("e.vals").alias("w"), F.col("e.xrs").alias("xr"))).alias("key"))))
            halves = here.where("h > 0").select("qid", "node", (F.col("h") - 1).alias("h"), F.explode(F.array(F.col("idx") * 2, F.col("idx") * 2 + 1)).alias("idx"))
            halves = halves.select("qid", "node", "h", "idx", tree.number(j, F.col("node"), F.expr("shiftleft(idx, h)")).alias("at"))
            parts.append(runs_of(tree, halves, j, [name]).select("qid", F.col(f"{name}_run").alias("key"), F.lit(j).alias("j"), "node", "h", "idx", "at"))
        now = least(reduce(DataFrame.union, [p.select(columns) for p in parts]))
    place = F.row_number().over(Window.partitionBy("qid").orderBy("key")).cast("long")
    return now.select("qid", place.alias("ord"), (F.col("key.w") * sign).alias("w"), F.col("key.xr").alias("xr"))


def successor_in(tree: YTree, bounds: DataFrame, w: int, strict: bool = False) -> DataFrame:
    """qid, succ: the least weight from w on, or above it, without a tree over values: a baseline.

    A run of blocks whose least weight is enough offers it; one whose largest isn't is out; others are split, unless
    what they hold can't be less than an offer.
    """
    enough = (lambda c: c > w) if strict else (lambda c: c >= w)
    whole, ends = cover(tree, bounds)
    values = [_leaf_points(tree, ends).select("qid", "w")]
    open_ = []
    for j in range(1, tree.depth + 1):
        touched, inner = pieces(tree, whole.where(F.col("lvl") == j), j)
        values.append(touched.select("qid", F.explode("part.w").alias("w")))
        open_.append(runs_of(tree, inner, j, ["least", "most"]).select("qid", F.lit(j).alias("j"), "node", "h", "idx", "at", "least_run", "most_run"))
    best = settle(reduce(DataFrame.union, values).where(enough(F.col("w"))).groupBy("qid").agg(F.min("w").alias("succ")))
    now = settle(reduce(DataFrame.union, open_))
    while not now.isEmpty():
        least, most = F.col("least_run.w"), -F.col("most_run.w")
        best = settle(best.union(now.where(enough(least)).select("qid", least)).groupBy("qid").agg(F.min("succ").alias("succ")))
        now = now.join(best, "qid", "left").where(~enough(least) & enough(most))
        parts, opened = [], []
        for j in range(1, tree.depth + 1):
            here = now.where(F.col("j") == j)
            opened.append(tree.levels[j].meet(here.where("h = 0").select("qid", "at"), "at", ["vals"]).select("qid", F.explode("vals").alias("w")))
            halves = here.where("h > 0").select("qid", "j", "node", (F.col("h") - 1).alias("h"), F.explode(F.array(F.col("idx") * 2, F.col("idx") * 2 + 1)).alias("idx"))
            halves = halves.withColumn("at", tree.number(j, F.col("node"), F.expr("shiftleft(idx, h)")))
            parts.append(runs_of(tree, halves, j, ["least", "most"]).select("qid", "j", "node", "h", "idx", "at", "least_run", "most_run"))
        best = settle(best.union(reduce(DataFrame.union, opened).where(enough(F.col("w")))).groupBy("qid").agg(F.min("succ").alias("succ")))
        now = settle(reduce(DataFrame.union, parts))
    return bounds.select("qid").join(best, "qid", "left").select("qid", "succ")


def report_in(tree: YTree, bounds: DataFrame) -> DataFrame:
    """qid, xr, yr, w of all points: whole nodes give way to their non-empty children down to the leaves, so what is read follows the answer's size."""
    whole, ends = cover(tree, bounds)
    every = F.sequence(F.lit(0).cast("long"), F.lit(tree.fan - 1).cast("long"))
    here = whole.where("lvl = 1").select("qid", "node", "lo", "hi")
    for j in range(1, tree.depth):
        below = _children(tree, here, j, every, ["qid"])
        here = settle(below.select("qid", "node", "lo", "hi").union(whole.where(F.col("lvl") == j + 1).select("qid", "node", "lo", "hi")))
    rows = tree.levels[-1].meet(here.withColumn("_at", F.col("node")), "_at", ["vals", "xrs", "yrs"])
    rows = rows.select("qid", F.expr("explode(slice(arrays_zip(xrs, yrs, vals), cast(lo + 1 as int), cast(hi - lo as int)))").alias("e"))
    return _leaf_points(tree, ends).union(rows.select("qid", "e.xrs", "e.yrs", "e.vals"))


def access(tree: YTree, places: DataFrame) -> DataFrame:
    """places (xr): adds yr, the entry of the sequence of y-ranks in x-order, read digit by digit down the tree."""
    rows = places.select("xr", F.lit(0).cast("long").alias("node"), F.col("xr").alias("pos"))
    for j in range(tree.depth):
        rows = rows.withColumn("_at", tree.number(j, F.col("node"), F.floor(F.col("pos") / tree.block))).withColumn("off", F.col("pos") % tree.block)
        rows = tree.levels[j].meet(rows, "_at", ["planes", "before"])
        digit = " | ".join(f"shiftleft(shiftright(planes[{k}][cast(off div 64 as int)], cast(off % 64 as int)) & 1L, {k})" for k in range(tree.bits))
        rows = rows.withColumn("d", F.expr(digit))
        rows = rows.select("xr", (F.col("node") * tree.fan + F.col("d")).alias("node"), F.expr(f"before[cast(d as int)] + {bit_sql.rank('planes', tree.bits, 'd', 'off')}").alias("pos"))
    rows = tree.levels[-1].meet(rows.withColumn("_at", F.col("node")), "_at", ["yrs"])
    return rows.select("xr", F.expr("yrs[cast(pos as int)]").alias("yr"))


def sequence_rank(tree: YTree, asked: DataFrame, lvl: int = 1) -> DataFrame:
    """asked (c, i): adds r, how often the symbol c, a node of level lvl, is among the first i entries of the sequence."""
    rows = asked.where("i > 0").select(F.col("c").alias("symbol"), "i", F.lit(0).cast("long").alias("node"), F.lit(0).cast("long").alias("lo"), F.col("i").alias("hi"))
    for j in range(lvl):
        digit = F.expr(f"shiftright(symbol, {tree.bits * (lvl - 1 - j)}) & {tree.fan - 1}L")
        rows = settle(_children(tree, rows, j, F.array(digit), ["symbol", "i"]))
    return asked.join(rows.select(F.col("symbol").alias("c"), "i", "hi"), ["c", "i"], "left").select("c", "i", F.coalesce("hi", F.lit(0)).alias("r"))


def sequence_select(tree: YTree, asked: DataFrame, lvl: int = 1) -> DataFrame:
    """asked (c, j): adds place, where the symbol c, a node of level lvl, occurs for the j-th time; -1 for j = 0, null if it doesn't.

    The place in the node leads to the place in the node above, level by level: the block there in which the digit
    occurs so often is found among the first blocks of superblocks, then among a superblock's blocks.
    """
    rows = asked.where("j > 0").select("c", "j", F.col("c").alias("node"), F.col("j").alias("nth"))
    for j in range(lvl - 1, -1, -1):
        rows = rows.withColumns({"d": F.expr(f"node & {tree.fan - 1}L"), "node": F.shiftright("node", tree.bits)})
        rows = settle(climb(tree, rows, j).withColumn("nth", F.col("pos") + 1).select("c", "j", "node", "nth"))
    return asked.join(rows.select("c", "j", "nth"), ["c", "j"], "left").select("c", "j", F.when(F.col("j") == 0, F.lit(-1).cast("long")).otherwise(F.col("nth") - 1).alias("place"))


def climb(tree: YTree, rows: DataFrame, j: int) -> DataFrame:
    """rows (node, d, nth, ...): adds pos, the place in the node of level j of the nth (from 1) entry with digit d; rows without one go.

    Blocks are searched by halving: at every step the running count of the block in the middle tells which half.
    """
    most = max(0, tree.low(j) - tree.block.bit_length() + 1)
    rows = rows.withColumn("_b", F.lit(0).cast("long"))
    last = F.floor((F.least(F.lit(tree.n) - F.shiftleft("node", tree.low(j)), F.lit(1 << tree.low(j))) - 1) / tree.block)
    for step in range(min(most, max(0, (-(-tree.n // tree.block) - 1).bit_length())) - 1, -1, -1):
        # the largest block number with fewer than nth entries before it, bit by bit
        tried = F.least(F.col("_b") + (1 << step), last).cast("long")
        rows = rows.withColumn("_try", tried).withColumn("_at", tree.number(j, F.col("node"), tried))
        rows = tree.levels[j].meet(rows, "_at", ["before"]).drop("_at")
        rows = settle(rows.withColumn("_b", F.when(F.expr("before[cast(d as int)] < nth"), F.col("_try")).otherwise(F.col("_b"))).drop("_try", "before"))
    rows = rows.where(F.col("node") * (1 << tree.low(j)) < tree.n).withColumn("_at", tree.number(j, F.col("node"), F.col("_b")))
    rows = tree.levels[j].meet(rows, "_at", ["planes", "before", "n"]).withColumn("_left", F.expr("nth - before[cast(d as int)]"))
    rows = rows.withColumn("pos", F.expr(f"_b * {tree.block} + {bit_sql.select('planes', tree.bits, 'd', '_left', 'n')}"))
    return rows.where("pos is not null").drop("_at", "_b", "_left", "planes", "before", "n")
