"""Connected components of a large edge table, by alternating star contraction.

Every round hangs a node's larger neighbours on its smallest one, then a node's smaller neighbours on the
smallest of them. Rounds are logarithmic in practice, each is written to the shared checkpoint folder, and only
a round's checksum comes to the driver.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import runtime


def _hang_larger(edges: DataFrame) -> DataFrame:
    """edges: (u, v), u > v. Each node's larger neighbours hang on the least of its neighbours and itself."""
    both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select(F.col("u").alias("v"), F.least("u", "m").alias("m"))
    return edges.join(least, "v").select("u", F.col("m").alias("v")).distinct()


def _hang_smaller(edges: DataFrame) -> DataFrame:
    """Each node and its smaller neighbours hang on the least of these."""
    least = edges.groupBy("u").agg(F.min("v").alias("m"))
    moved = edges.join(least, "u").where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(least.select("u", F.col("m").alias("v"))).distinct()


def _sum(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())


def components(edges: DataFrame) -> DataFrame:
    """Rows (node, component): the smallest id reachable, for each node of edges (a, b) that isn't smallest itself."""
    now = runtime.cut(edges.where("a != b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct())
    seen = _sum(now)
    while True:
        now = runtime.cut(_hang_smaller(_hang_larger(now)))
        if seen == (seen := _sum(now)):
            return now.select(F.col("u").alias("node"), F.col("v").alias("component"))


def of_few(edges: DataFrame, most: int = 100_000) -> DataFrame:
    """components() of a checkpointed table; up to `most` edges are joined on the driver, without shuffles."""
    if edges.count() > most:
        return components(edges)
    least: dict[int, int] = {}

    def end(x: int) -> int:
        while (up := least.setdefault(x, x)) != x:
            least[x] = x = least[up]
        return x

    for a, b in edges.select("a", "b").collect():
        a, b = end(a), end(b)
        least[max(a, b)] = min(a, b)
    return edges.sparkSession.createDataFrame([(x, end(x)) for x in list(least) if end(x) != x], "node long, component long")
