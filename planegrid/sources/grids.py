"""The point grids of the workloads: two ordered coordinates and a weight for each point.

Every grid is given twice, as a DataFrame (x, y, w) and as SQL text of the same rows. Money counts in cents and
times in microseconds, so that all sums are of integers.
"""

from __future__ import annotations

from dataclasses import dataclass
from datetime import datetime, timedelta

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from planegrid.operators.rangejoin import Box, box_of, points_in


@dataclass(frozen=True)
class Grid:
    """table: SQL source; x, y, w: Spark expressions; sql: (x, y, w) for DuckDB, where they differ.

    raw: for x and y the table's column and how the coordinate follows from it (same, whole, cents, micros), so that
    bounds can be put to the column itself and reach the scan; None where it doesn't follow from one column.
    """

    table: str
    x: str
    y: str
    w: str
    sql: tuple[str, str, str] | None = None
    raw: tuple[tuple[str, str] | None, tuple[str, str] | None] = (None, None)


def _cents(c: str) -> str:
    return f"cast(cast({c} as decimal(18,2)) * 100 as bigint)"


def _micros(c: str) -> tuple[str, str]:
    return f"unix_micros(cast({c} as timestamp))", f"epoch_us({c})"


GRIDS = {
    "L": Grid("lineitem", "cast(l_quantity as bigint)", _cents("l_extendedprice"), _cents("l_discount"), raw=(("l_quantity", "whole"), ("l_extendedprice", "cents"))),
    "S": Grid("lineitem", _micros("l_shipdate")[0], "l_partkey", "cast(l_quantity as bigint)", (_micros("l_shipdate")[1], "l_partkey", "cast(l_quantity as bigint)"), raw=(("l_shipdate", "micros"), ("l_partkey", "same"))),
    "O": Grid("orders", _micros("o_orderdate")[0], _cents("o_totalprice"), "o_custkey", (_micros("o_orderdate")[1], _cents("o_totalprice"), "o_custkey"), raw=(("o_orderdate", "micros"), ("o_totalprice", "cents"))),
    "E": Grid("events", _micros("ts")[0], "user_id", _cents("value"), (_micros("ts")[1], "user_id", _cents("value")), raw=(("ts", "micros"), ("user_id", "same"))),
    "P": Grid("part", "cast(p_size as bigint)", _cents("p_retailprice"), "cast(regexp_extract(p_brand, '([0-9]+)', 1) as bigint)", raw=(("p_size", "same"), ("p_retailprice", "cents"))),
    "D": Grid("documents", "n_chars", "doc_id", "case lang when 'de' then 0 when 'en' then 1 when 'es' then 2 else 3 end", ("n_chars", "doc_id", "case lang when 'de' then 0 when 'en' then 1 when 'es' then 2 else 3 end"), raw=(("n_chars", "same"), ("doc_id", "same"))),
    "V": Grid("embeddings", "cast(embedding[0] as double)", "cast(embedding[1] as double)", "cast(label as bigint)", ("cast(embedding[1] as double)", "cast(embedding[2] as double)", "cast(label as bigint)")),
}
#: Customers by their number of orders and balance: a grid from two tables.
CUSTOMER_SQL = f"""select cast(n as bigint) as x, {_cents("c_acctbal")} as y, cast(c_nationkey as bigint) as w
    from customer join (select o_custkey, count(*) as n from orders group by o_custkey) o on c_custkey = o_custkey"""


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _limits(column: str, kind: str, low, high) -> Column:
    """A condition on the column itself that holds wherever its coordinate is between low and high; it may hold beyond."""
    c, out = F.col(column), F.lit(True)
    slack = {"same": 0, "whole": 1.0, "cents": 1.0}
    for bound, sign in ((low, -1), (high, 1)):
        if bound is None:
            continue
        if kind == "micros":
            # a day of slack covers any session time zone
            at = datetime(1970, 1, 1) + timedelta(microseconds=min(max(int(bound), -62_000_000_000_000_000), 253_000_000_000_000_000)) + sign * timedelta(days=1)
            value = F.expr(f"timestamp_ntz '{at.isoformat(sep=' ')}'")
        elif kind == "cents":
            value = F.lit((float(bound) + sign * slack[kind]) / 100)
        else:
            value = F.lit(bound + sign * slack[kind])
        out = out & (c >= value if sign < 0 else c <= value)
    return out


def points(spark: SparkSession, sf_dir: str, grid: str, box: Box | None = None) -> DataFrame:
    """(x, y, w) of a grid; a point without one of them is left out, as SQL comparisons would.

    box: points outside needn't be read; its sides are put to the table's own columns, where the scan can use them.
    """
    if grid == "C":
        orders = table(spark, sf_dir, "orders").groupBy("o_custkey").agg(F.count("*").alias("n"))
        customers = table(spark, sf_dir, "customer")
        if box:
            customers = customers.where(_limits("c_acctbal", "cents", box.y0, box.y1))
        rows = customers.join(orders, F.col("c_custkey") == F.col("o_custkey"))
        return rows.select(F.col("n").alias("x"), F.expr(_cents("c_acctbal")).alias("y"), F.col("c_nationkey").cast("bigint").alias("w"))
    g = GRIDS[grid]
    rows = table(spark, sf_dir, g.table)
    for raw, axis in zip(g.raw, "xy"):
        if box and raw:
            rows = rows.where(_limits(*raw, getattr(box, f"{axis}0"), getattr(box, f"{axis}1")))
    return rows.select(F.expr(g.x).alias("x"), F.expr(g.y).alias("y"), F.expr(g.w).cast("bigint").alias("w"))


def hits(spark: SparkSession, sf_dir: str, grid: str, rects: DataFrame, cells: int | None = None) -> DataFrame:
    """(x, y, w, rects' columns) of the grid's points in each rectangle; only what the batch spans is read."""
    box = box_of(rects)
    return points_in(points(spark, sf_dir, grid, box), rects, box=box, **({"cells": cells} if cells else {}))


def sql(grid: str) -> str:
    if grid == "C":
        return CUSTOMER_SQL
    g = GRIDS[grid]
    x, y, w = g.sql or (g.x, g.y, g.w)
    return f"select {x} as x, {y} as y, cast({w} as bigint) as w from {g.table}"


def normalised(df: DataFrame, x: Column, y: Column, w: Column, keep_nulls: bool = False) -> DataFrame:
    """Any table as a grid: rows with a null or NaN coordinate are refused unless they may be dropped; -0.0 becomes 0.0."""
    rows = df.select(x.alias("x"), y.alias("y"), w.alias("w"))
    for c in ("x", "y"):
        if dict(rows.dtypes)[c] in ("double", "float"):
            rows = rows.withColumn(c, F.when(F.isnan(c), F.lit(None)).otherwise(F.col(c) + F.lit(0.0)))
    return rows if keep_nulls else rows.where("x is not null and y is not null")
