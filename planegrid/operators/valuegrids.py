"""A grid for each value, to count how many points of a value a rectangle holds.

Points are laid out by value and, within a value, by x, and once more by y; a value's points then stand together in
both orders, so one tree over the layout holds all values' grids. A rectangle's side is found among the sorted pairs of
value and rank.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from planegrid.operators import ytree
from planegrid.operators.rankspace import Keys, keys_of, positions, ranks_of
from planegrid.operators.ytree import YTree
from planegrid.plans.storage import cut, fresh_path, settle


@dataclass
class ValueGrids:
    """xkeys, ykeys: pairs (w, rank) in the order of the layout."""

    n: int
    xkeys: Keys
    ykeys: Keys
    tree: YTree

    def places(self, asked: DataFrame) -> DataFrame:
        """asked (id, w, xlo, xhi, ylo, yhi): bounds (qid = id, xlo, ...) of each rectangle in the layout of the value's grid."""
        out = settle(asked)
        found = out.select(F.col("id").alias("qid"))
        for axis, keys in (("x", self.xkeys), ("y", self.ykeys)):
            sides = F.array(*(F.struct(F.lit(f"{axis}{s}").alias("name"), F.struct("w", F.col(f"{axis}{s}").alias("r")).alias("v"), F.lit(False).alias("closed")) for s in ("lo", "hi")))
            rows = ranks_of(out.select("id", F.explode(sides).alias("b")).select("id", "b.*"), keys)
            both = rows.groupBy(F.col("id").alias("qid")).agg(*(F.max(F.when(F.col("name") == f"{axis}{s}", F.col("r"))).alias(f"{axis}{s}") for s in ("lo", "hi")))
            found = found.join(both, "qid")
        return settle(found)

    def count(self, bounds: DataFrame, values: DataFrame) -> DataFrame:
        """bounds (qid, xlo, ...), values (qid, w): (qid, w, freq), also where freq is 0."""
        asked = settle(values.join(bounds, "qid").withColumn("id", F.monotonically_increasing_id()))
        freq = ytree.count_in(self.tree, self.places(asked.select("id", "w", "xlo", "xhi", "ylo", "yhi")))
        return asked.select("id", "qid", "w").join(freq.select(F.col("qid").alias("id"), F.col("cnt").alias("freq")), "id").select("qid", "w", "freq")


def build(ranked: DataFrame, bits: int = 4, block: int = 256, path: str | None = None) -> ValueGrids:
    """ranked: (xr, yr, w) of rank_space()."""
    path = path or fresh_path(ranked.sparkSession, "value-grids")
    laid = positions(ranked.select("xr", "yr", "w"), ["w", "xr"], "X")
    laid = cut(positions(laid, ["w", "yr"], "Y"))
    n = laid.count()
    pairs = laid.select("X", "Y", F.struct("w", F.col("xr").alias("r")).alias("by_x"), F.struct("w", F.col("yr").alias("r")).alias("by_y"))
    tree = ytree.build(laid.select(F.col("X").alias("xr"), F.col("Y").alias("yr"), "w"), bits, block, extrema=False, path=f"{path}/tree")
    return ValueGrids(n, keys_of(pairs, "by_x", "X", n, path), keys_of(pairs, "by_y", "Y", n, path), tree)
