"""A grid's stored index: the tree over y-ranks, the sorted keys of both axes, and the points in x-order."""

from __future__ import annotations

import json
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from planegrid.operators import blocks, ytree
from planegrid.operators.blocks import Blocks
from planegrid.operators.rankspace import Keys, keys_of, map_rects, rank_space
from planegrid.operators.ytree import YTree
from planegrid.plans.storage import fresh_path, stored

#: Points of a block of the table in x-order.
SIZE = 1024


@dataclass
class PointIndex:
    """ranked: (x, y, w, pid, xr, yr). points: the same by blocks of xr."""

    path: str
    n: int
    ranked: DataFrame
    points: Blocks
    xkeys: Keys
    ykeys: Keys
    tree: YTree

    def bounds(self, rects: DataFrame) -> DataFrame:
        """rects in half-open ranks, for the tree."""
        return map_rects(rects, self.xkeys, self.ykeys)

    def located(self, rows: DataFrame, suffix: str = "", xr: str = "xr") -> DataFrame:
        """rows with x, y and w of the point with x-rank xr; rows without one go. Columns of these names are replaced."""
        rows = rows.drop(*(f"{c}{suffix}" for c in "xyw")).withColumns({"_at": F.floor(F.col(xr) / SIZE), "_i": (F.col(xr) % SIZE).cast("int")})
        rows = self.points.meet(rows, "_at", ["xs", "ys", "ws"])
        return rows.withColumns({f"{c}{suffix}": F.expr(f"{c}s[_i]") for c in "xyw"}).drop("_at", "_i", "xs", "ys", "ws")


def build(points: DataFrame, bits: int = 4, block: int = 256, path: str | None = None) -> PointIndex:
    """points: (x, y, w). Written below path; load() reads it again."""
    spark = points.sparkSession
    path = path or fresh_path(spark, "index")
    ranked = stored(rank_space(points), f"{path}/ranked")
    n = ranked.count()
    e = F.sort_array(F.collect_list(F.struct("xr", "x", "y", "w")))
    rows = ranked.groupBy(F.floor(F.col("xr") / SIZE).alias("gblk")).agg(e.alias("e")).select("gblk", *(F.col(f"e.{c}").alias(f"{c}s") for c in "xyw"))
    found = PointIndex(path, n, ranked, blocks.save(rows, -(-n // SIZE), f"{path}/points"), keys_of(ranked, "x", "xr", n, path), keys_of(ranked, "y", "yr", n, path), ytree.build(ranked, bits, block, path=f"{path}/tree"))
    about = {"n": n, "schema": ranked.schema.json(), "points": found.points.about} | {name: {"size": k.size, "levels": [x.about for x in k.levels]} for name, k in (("xkeys", found.xkeys), ("ykeys", found.ykeys))}
    spark.createDataFrame([(json.dumps(about),)], "about string").coalesce(1).write.parquet(f"{path}/about")  # last, so a reader sees whole indexes only
    return found


def load(spark: SparkSession, path: str) -> PointIndex:
    from pyspark.sql.types import StructType

    about = json.loads(spark.read.parquet(f"{path}/about").first().about)
    keys = {name: Keys(about["n"], about[name]["size"], [blocks.load(spark, x) for x in about[name]["levels"]]) for name in ("xkeys", "ykeys")}
    ranked = spark.read.schema(StructType.fromJson(json.loads(about["schema"]))).parquet(f"{path}/ranked")
    return PointIndex(path, about["n"], ranked, blocks.load(spark, about["points"]), **keys, tree=ytree.load(spark, f"{path}/tree"))
