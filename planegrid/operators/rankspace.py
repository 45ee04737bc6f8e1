"""Dense ranks of a large table, without a window over all of it.

Rows are range-partitioned by the order; each partition numbers its own rows, and what lies before a partition follows
from one count for each of them. The bounds of rectangles become ranks by going down a tree of sorted keys: a block of
first keys tells which block below to open, until a block of keys gives the rank.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from planegrid.operators import blocks
from planegrid.operators.blocks import Blocks
from planegrid.plans.storage import cut, settle


def positions(rows: DataFrame, order: list[str], name: str) -> DataFrame:
    """rows with name: 0, 1, ... in the order of the columns. Rows that agree in them are numbered in any order.

    Such rows are told apart for the partitioning, so that many of them don't meet in one partition.
    """
    placed = cut(rows.withColumn("_salt", F.monotonically_increasing_id()).repartitionByRange(*order, "_salt").drop("_salt").withColumn("_part", F.spark_partition_id()))
    sizes = placed.groupBy("_part").agg(F.count("*").alias("_n"))
    before = F.coalesce(F.sum("_n").over(Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    starts = sizes.select("_part", before.alias("_before"))  # one row for each partition
    own = F.row_number().over(Window.partitionBy("_part").orderBy(*order)) - 1
    return placed.withColumn("_own", own).join(F.broadcast(starts), "_part").withColumn(name, (F.col("_before") + F.col("_own")).cast("long")).drop("_part", "_own", "_before")


def rank_space(points: DataFrame) -> DataFrame:
    """points (x, y, w) with pid, xr and yr: ranks in the orders (x, y, w) and (y, x, w), each a permutation of 0..n-1.

    Points that agree in all three columns are interchangeable; pid tells them apart and is the rank in x.
    """
    one = positions(points.select("x", "y", "w"), ["x", "y", "w"], "xr")
    return positions(one.withColumn("pid", F.col("xr")), ["y", "x", "w", "xr"], "yr")


@dataclass
class Keys:
    """The sorted coordinates of one axis, in blocks; above them the blocks' first keys, again in blocks, up to one block.

    levels[0] holds the keys themselves.
    """

    n: int
    size: int
    levels: list[Blocks]


def keys_of(ranked: DataFrame, key: str, rank: str, n: int, path: str, size: int = 1024) -> Keys:
    """The keys of an axis by rank."""
    out, rows, total = Keys(n, size, []), ranked.select(F.col(rank).alias("r"), F.col(key).alias("v")), n
    while True:
        made = rows.groupBy(F.floor(F.col("r") / size).alias("gblk")).agg(F.sort_array(F.collect_list("v")).alias("keys"))
        total = -(-total // size)
        out.levels.append(blocks.save(made, total, f"{path}/{key}-keys-{len(out.levels)}"))
        if total <= 1:
            return out
        rows = out.levels[-1].rows.select(F.col("gblk").alias("r"), F.col("keys")[0].alias("v"))


def ranks_of(bounds: DataFrame, keys: Keys) -> DataFrame:
    """bounds (id, v, closed, ...): adds r, the keys below v, or up to v if closed. v is not null."""
    rows = bounds.withColumn("_at", F.lit(0).cast("long"))
    for level in reversed(keys.levels):
        rows = level.meet(rows, "_at", ["keys"])
        inside = F.size(F.filter("keys", lambda k: (k < F.col("v")) | (F.col("closed") & (k == F.col("v")))))
        rows = rows.withColumn("r", F.col("_at") * keys.size + inside).drop("keys", "_at")
        # the last block whose first key counts; before the first one nothing does
        rows = rows.withColumn("_at", F.greatest(F.col("r") - 1, F.lit(0)))
    return rows.drop("_at")


def map_rects(rects: DataFrame, xkeys: Keys, ykeys: Keys) -> DataFrame:
    """rects (qid, x0, x1, y0, y1) as half-open ranks (qid, xlo, xhi, ylo, yhi); an empty rectangle has lo >= hi."""
    out = settle(rects.select("qid", "x0", "x1", "y0", "y1"))
    whole = {"xlo": 0, "xhi": xkeys.n, "ylo": 0, "yhi": ykeys.n}
    sides = [("x", 0, "xlo"), ("x", 1, "xhi"), ("y", 0, "ylo"), ("y", 1, "yhi")]
    found = out.select("qid")
    for axis, keys in (("x", xkeys), ("y", ykeys)):
        asked = F.array(*(F.struct(F.lit(name).alias("name"), F.col(f"{axis}{k}").alias("v"), F.lit(bool(k)).alias("closed")) for a, k, name in sides if a == axis))
        rows = out.select("qid", F.explode(asked).alias("b")).select("qid", "b.*").where("v is not null")
        names = [name for a, _, name in sides if a == axis]
        ranks = ranks_of(rows, keys).groupBy("qid").agg(*(F.max(F.when(F.col("name") == name, F.col("r"))).alias(name) for name in names))
        found = found.join(ranks, "qid", "left")
    return settle(found.select("qid", *(F.coalesce(F.col(c), F.lit(v)).cast("long").alias(c) for c, v in whole.items())))
