"""A tree over the values of a grid's points, each node a grid of its own: quantiles, value ranges, frequent values, neighbours.

On level v the points are laid out by the first v digits of their value's rank, and within such a group by x; and once
more by y. A group's points then stand together in both orders, so all groups of a level make one grid, and a rectangle
of a group is a rectangle of that grid. How often each digit occurs before a place in either order moves a rectangle
from a group to its child; the tree over y-ranks of the next level counts what it holds there.
"""

from __future__ import annotations

from dataclasses import dataclass
from decimal import Decimal
from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from planegrid.functions import bits as bit_sql
from planegrid.operators import blocks, ytree
from planegrid.operators.blocks import Blocks
from planegrid.operators.index import PointIndex
from planegrid.operators.rankspace import keys_of, positions
from planegrid.operators.valuegrids import ValueGrids
from planegrid.plans.storage import cut, fresh_path, settle, stored


@dataclass
class ValueTree:
    """values: (w, wr). splits[v]: digit blocks of level v in both orders; starts[v], trees[v]: of the layout of level v. grids: one for each value."""

    bits: int
    block: int
    depth: int
    values: DataFrame
    splits: list[tuple[Blocks, Blocks]]
    starts: list[DataFrame]
    trees: list[ytree.YTree]
    grids: ValueGrids | None = None


def _split(rows: DataFrame, at: str, bits: int, block: int, n: int, path: str) -> Blocks:
    """(gblk, planes, before): the digits d in the order of at."""
    fan = 1 << bits
    each = [F.count_if(F.col("d") == c).alias(f"_d{c}") for c in range(fan)]
    made = rows.groupBy(F.floor(F.col(at) / block).alias("blk")).agg(F.sort_array(F.collect_list(F.struct(F.col(at).alias("p"), "d"))).alias("e"), *each)
    made = cut(made.select(F.lit(0).cast("long").alias("node"), "blk", F.col("e.d").alias("digits"), *(f"_d{c}" for c in range(fan))))
    made = ytree.running(made, {f"_b{c}": f"_d{c}" for c in range(fan)})
    return blocks.save(made.select(F.col("blk").alias("gblk"), bit_sql.packed("digits", bits).alias("planes"), F.array(*(f"_b{c}" for c in range(fan))).alias("before")), -(-n // block), path)


def build(ranked: DataFrame, bits: int = 4, block: int = 256, path: str | None = None) -> ValueTree:
    """ranked: (xr, yr, w) of rank_space()."""
    path = path or fresh_path(ranked.sparkSession, "value-tree")
    values = stored(positions(ranked.select("w").distinct(), ["w"], "wr"), f"{path}/values")
    m, n = values.count(), ranked.count()
    depth = max(1, -(-max(1, (m - 1).bit_length()) // bits))
    tree = ValueTree(bits, block, depth, values, [], [], [])
    rows = ranked.join(values, "w").select("xr", "yr", "w", "wr")
    for v in range(depth + 1):
        low = bits * (depth - v)
        laid = rows.select("xr", "yr", "w", F.shiftright("wr", low).alias("g"), "wr")
        laid = positions(laid, ["g", "xr"], "X")
        laid = cut(positions(laid, ["g", "yr"], "Y"))
        tree.starts.append(stored(laid.groupBy("g").agg(F.min("X").alias("start")), f"{path}/starts-{v}"))
        tree.trees.append(ytree.build(laid.select(F.col("X").alias("xr"), F.col("Y").alias("yr"), "w"), bits, block, extrema=False, path=f"{path}/tree-{v}"))
        if v < depth:
            digit = laid.withColumn("d", F.shiftright("wr", low - bits).bitwiseAND(F.lit((1 << bits) - 1)))
            tree.splits.append(tuple(_split(digit, at, bits, block, n, f"{path}/split-{v}-{at}") for at in "XY"))
    # the last layout keeps each value's points together: it is the grids of the values
    pairs = laid.select("X", "Y", F.struct("w", F.col("xr").alias("r")).alias("by_x"), F.struct("w", F.col("yr").alias("r")).alias("by_y"))
    tree.grids = ValueGrids(n, keys_of(pairs, "by_x", "X", n, path), keys_of(pairs, "by_y", "Y", n, path), tree.trees[-1])
    return tree


def _counted(tree: ValueTree, rows: DataFrame, split: Blocks, at: str, name: str) -> DataFrame:
    """rows (c, at): adds how often digit c occurs before place at."""
    rows = rows.withColumn("_at", F.floor(F.greatest(F.col(at) - 1, F.lit(0)) / tree.block)).withColumn("_off", (F.col(at) - F.col("_at") * tree.block).cast("long"))
    rows = split.meet(rows, "_at", ["planes", "before"])
    return rows.withColumn(name, F.expr(f"before[cast(c as int)] + {bit_sql.rank('planes', tree.bits, 'c', '_off')}")).drop("_at", "_off", "planes", "before")


def _children(tree: ValueTree, v: int, front: DataFrame, digits: DataFrame) -> DataFrame:
    """front (id, g, X0, X1, Y0, Y1) and digits (id, c): the rectangle in each child's layout, (id, c, g, X0, ...)."""
    xs, ys = tree.splits[v]
    rows = front.join(digits, "id").join(tree.starts[v].withColumnRenamed("start", "S"), "g")
    for axis, split in (("X", xs), ("Y", ys)):
        for at in (f"{axis}0", f"{axis}1", "S"):
            rows = _counted(tree, rows, split, at, f"_{axis}{at}")
    child = F.col("g") * (1 << tree.bits) + F.col("c")
    # a child without points has no start, and no rectangle
    rows = rows.withColumn("g", child).join(tree.starts[v + 1], "g")
    place = lambda axis, k: (F.col("start") + F.col(f"_{axis}{axis}{k}") - F.col(f"_{axis}S")).alias(f"{axis}{k}")
    return settle(rows.select("id", "c", "g", place("X", 0), place("X", 1), place("Y", 0), place("Y", 1)))


def _sizes(tree: ValueTree, v: int, rows: DataFrame) -> DataFrame:
    """rows (id, c, X0, ...) of layout v: adds cnt, the points in each rectangle."""
    fan = 1 << tree.bits
    bounds = settle(rows.select((F.col("id") * fan + F.col("c")).alias("qid"), F.col("X0").alias("xlo"), F.col("X1").alias("xhi"), F.col("Y0").alias("ylo"), F.col("Y1").alias("yhi")))
    cnt = ytree.count_in(tree.trees[v], bounds).select(F.floor(F.col("qid") / fan).alias("id"), (F.col("qid") % fan).alias("c"), "cnt")
    return rows.join(cnt, ["id", "c"])


def _start(bounds: DataFrame) -> DataFrame:
    return bounds.select("id", F.lit(0).cast("long").alias("g"), F.col("xlo").alias("X0"), F.col("xhi").alias("X1"), F.col("ylo").alias("Y0"), F.col("yhi").alias("Y1"))


def kth(tree: ValueTree, asked: DataFrame) -> DataFrame:
    """asked (id, k, xlo, xhi, ylo, yhi), ids from 0 on: (id, w), the k-th smallest weight; no row outside 1..cnt.

    Level by level: count each child, take the first digit whose running count reaches k, go on with what k has left.
    """
    every = asked.select("id", F.explode(F.sequence(F.lit(0), F.lit((1 << tree.bits) - 1))).alias("c")).withColumn("c", F.col("c").cast("long"))
    front = settle(_start(asked).join(asked.select("id", "k").where("k >= 1"), "id"))
    for v in range(tree.depth):
        sizes = _sizes(tree, v + 1, _children(tree, v, front.drop("k"), every)).join(front.select("id", "k"), "id")
        upto = F.sum("cnt").over(Window.partitionBy("id").orderBy("c"))
        sizes = sizes.withColumn("upto", upto).where("upto >= k and upto - cnt < k")
        front = settle(sizes.select("id", "g", "X0", "X1", "Y0", "Y1", (F.col("k") - F.col("upto") + F.col("cnt")).alias("k")))
    return front.join(tree.values, F.col("g") == F.col("wr")).select("id", "w")


def below(tree: ValueTree, asked: DataFrame) -> DataFrame:
    """asked (id, r, xlo, ...), r a value rank: (id, n), the points whose value's rank is below r."""
    fan = 1 << tree.bits
    front = settle(_start(asked).join(asked.select("id", "r"), "id"))
    found: list[DataFrame] = []
    for v in range(tree.depth):
        digit = F.shiftright("r", tree.bits * (tree.depth - 1 - v))
        digit = digit.bitwiseAND(F.lit(fan - 1)) if v else F.least(digit, F.lit(fan))
        digits = front.select("id", F.explode(F.sequence(F.lit(0).cast("long"), digit)).alias("c")).where(F.col("c") < fan)
        rows = settle(_children(tree, v, front.select("id", "g", "X0", "X1", "Y0", "Y1"), digits).join(front.select("id", "r", digit.alias("d")), "id"))
        found.append(_sizes(tree, v + 1, rows.where("c < d").select("id", "c", "X0", "X1", "Y0", "Y1")).select("id", F.col("cnt").alias("n")))
        front = settle(rows.where("c = d").select("id", "g", "X0", "X1", "Y0", "Y1", "r"))
    total = reduce(DataFrame.union, found).groupBy("id").agg(F.sum("n").alias("n"))
    return asked.select("id").join(total, "id", "left").select("id", F.coalesce("n", F.lit(0)).alias("n"))


def value_rank(tree: ValueTree, w: int, closed: bool) -> int:
    """Values below w, or up to w if closed."""
    return tree.values.where(F.col("w") <= w if closed else F.col("w") < w).count()


def numbered(bounds: DataFrame, extra: DataFrame | None = None) -> DataFrame:
    """bounds (qid, ...) with id, so that several questions can be asked of one rectangle. extra: (qid, ...)."""
    rows = bounds if extra is None else bounds.join(extra, "qid")
    return settle(rows.withColumn("id", F.monotonically_increasing_id()))


def kth_in(tree: ValueTree, bounds: DataFrame, wanted: DataFrame) -> DataFrame:
    """wanted (qid, k): qid, k, w."""
    asked = numbered(bounds, wanted)
    return asked.join(kth(tree, asked), "id", "left").select("qid", "k", "w")


def count_values(tree: ValueTree, bounds: DataFrame, w0: int, w1: int) -> DataFrame:
    asked = numbered(bounds)
    low, high = (below(tree, asked.withColumn("r", F.lit(r).cast("long"))) for r in (value_rank(tree, w0, False), value_rank(tree, w1, True)))
    return asked.join(low.withColumnRenamed("n", "a"), "id").join(high.withColumnRenamed("n", "b"), "id").select("qid", (F.col("b") - F.col("a")).alias("cnt"))


def neighbours(tree: ValueTree, bounds: DataFrame, w: int, strict: bool = False) -> DataFrame:
    """qid, succ, pred: the value after those below w is the next one, that of the last up to w the one before."""
    asked = numbered(bounds)
    out = asked.select("qid", "id")
    for name, closed, step in (("succ", strict, 1), ("pred", not strict, 0)):
        n = below(tree, asked.withColumn("r", F.lit(value_rank(tree, w, closed)).cast("long")))
        found = kth(tree, asked.join(n.select("id", (F.col("n") + step).alias("k")), "id"))
        out = out.join(found.withColumnRenamed("w", name), "id", "left")
    return out.select("qid", "succ", "pred")


def majority_in(tree: ValueTree, bounds: DataFrame, alpha: str, inclusive: bool = False) -> DataFrame:
    """qid, w, freq, cnt: a value with enough points covers one of the equally spaced ranks; each value met is counted."""
    a = Decimal(alpha)
    scale = 10 ** max(0, -a.as_tuple().exponent)
    num = int(a * scale)
    cnt = settle(ytree.count_in(tree.trees[0], bounds).where("cnt > 0"))
    # the least count that is enough; such a run of equal values holds a multiple of it
    step = F.expr(f"(cnt * {num} + {scale} - 1) div {scale}") if inclusive else F.expr(f"cnt * {num} div {scale} + 1")
    probes = cnt.select("qid", F.greatest(step, F.lit(1)).alias("s"), "cnt").where("s <= cnt").select("qid", F.explode(F.sequence("s", "cnt", "s")).alias("k"))
    met = kth_in(tree, bounds, probes).where("w is not null").select("qid", "w").distinct()
    freq = tree.grids.count(bounds, met).join(cnt, "qid")
    left, right = F.col("freq") * F.lit(scale), F.col("cnt") * F.lit(num)
    return freq.where(left >= right if inclusive else left > right).select("qid", "w", "freq", "cnt")


def quantiles_in(tree: ValueTree, bounds: DataFrame, shares: list[str]) -> DataFrame:
    """qid, p, w: the value of rank ceil(p * cnt), at least 1; p = 0.5 is the lower median. Null in an empty rectangle."""
    cnt = ytree.count_in(tree.trees[0], bounds)
    p = F.explode(F.array(*(F.lit(Decimal(s)).cast("decimal(9,8)") for s in shares))).alias("p")
    asked = settle(cnt.select("qid", "cnt", p).withColumn("k", F.greatest(F.ceil(F.col("p") * F.col("cnt")).cast("long"), F.lit(1))))
    found = kth_in(tree, bounds, asked.select("qid", "k").distinct())
    return asked.join(found, ["qid", "k"], "left").select("qid", F.col("p").cast("double").alias("p"), "w")


def top_fraction(tree: ValueTree, index: PointIndex, bounds: DataFrame, share: str) -> DataFrame:
    """qid, x, y, w: the ceil(share * cnt) points with the largest weights, ties by (x, y).

    The least weight that is needed is a quantile; points above it are reported, of those with it the first ones.
    """
    cnt = ytree.count_in(index.tree, bounds).where("cnt > 0")
    asked = settle(cnt.withColumn("need", F.ceil(F.lit(Decimal(share)) * F.col("cnt")).cast("long")).withColumn("k", F.col("cnt") - F.col("need") + 1))
    edge = settle(kth_in(tree, bounds, asked.select("qid", "k")).join(asked.select("qid", "need"), "qid").select("qid", F.col("w").alias("least"), "need"))
    rows = ytree.report_in(index.tree, bounds).join(edge, "qid").where("w >= least")
    rows = rows.withColumn("_n", F.row_number().over(Window.partitionBy("qid").orderBy(F.desc("w"), "xr"))).where("_n <= need")
    return index.located(rows.select("qid", "xr")).select("qid", "x", "y", "w")


#: Points that are read as fast as a rank is asked for: a rank takes some hundred blocks, one for each level and digit.
CLOSEST = 4096


def topk_frequent(tree: ValueTree, index: PointIndex, bounds: DataFrame, k: int, closest: int = CLOSEST, trace: list[int] | None = None) -> DataFrame:
    """qid, ord, w, freq: the k most frequent values, ties by the smaller value; k = 1 is the mode.

    Ranks at a spacing are asked for their values, and each value met is counted. A value that wasn't met has fewer
    points than the spacing; so once k values have at least as many, they are the answer. Until then the spacing is
    halved, and only ranks between the earlier ones are new. Rectangles that come down to a spacing below closest
    have all their points reported instead, as that reads less. trace: gets the number of ranks asked for in each round.
    """
    open_ = settle(ytree.count_in(index.tree, bounds).where("cnt > 0").withColumn("s", F.expr("shiftleft(1L, cast(floor(log2(cnt)) as int))")).withColumn("first", F.lit(True)))
    known = settle(open_.select("qid", F.lit(0).cast("long").alias("w"), F.lit(0).cast("long").alias("freq")).where("false"))
    order = Window.partitionBy("qid").orderBy(F.desc("freq"), "w")
    while not (probed := open_.where(F.col("s") >= closest)).isEmpty():
        # after the first round the even multiples are known
        ranks = probed.select("qid", F.explode(F.expr("if(first, sequence(s, cnt, s), if(s <= cnt, sequence(s, cnt, 2 * s), array()))")).alias("k"))
        if trace is not None:
            trace.append(ranks.count())
        met = kth_in(tree, bounds, ranks).where("w is not null").select("qid", "w").distinct()
        known = settle(known.union(tree.grids.count(bounds, met.join(known, ["qid", "w"], "left_anti"))))
        kth_best = known.withColumn("_n", F.row_number().over(order)).where(F.col("_n") == k).select("qid", F.col("freq").alias("best"))
        going = probed.join(kth_best, "qid", "left").where("s > 1 and (best is null or best < s)").select("qid", "cnt", F.expr("s div 2").alias("s"), F.lit(False).alias("first"))
        open_ = settle(going.union(open_.where(F.col("s") < closest).select("qid", "cnt", "s", "first")))
    rest = open_.select("qid")
    done = known.join(rest, "qid", "left_anti")
    counted = ytree.report_in(index.tree, bounds.join(rest, "qid")).groupBy("qid", "w").agg(F.count("*").alias("freq"))
    found = done.select("qid", "w", "freq").union(counted.select("qid", "w", "freq"))
    return found.withColumn("ord", F.row_number().over(order).cast("long")).where(F.col("ord") <= k).select("qid", "ord", "w", "freq")
