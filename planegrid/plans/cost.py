"""What structures and queries cost: published bounds as formulas, measured sizes, and the choice between index and scan."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from planegrid.operators.ytree import YTree


def _lg(x: float) -> float:
    return max(1.0, math.log2(max(x, 2)))


@dataclass(frozen=True)
class Size:
    """n points, values below top of which kinds are distinct, universe of a coordinate, fan-out, trade-off t, threshold alpha, outputs d or k."""

    n: int
    kinds: int
    top: int
    universe: int
    fan: int = 2
    t: float = 1.0
    alpha: float = 0.5
    out: int = 1


def bounds(p: Size) -> list[tuple[str, str, float, float]]:
    """(method, kind, steps, bits) without constants; bits leave out coordinates and weights."""
    n, m = p.n, min(p.n, p.kinds)
    ln, lm, lt, lu = _lg(n), _lg(m), _lg(p.top), _lg(p.universe)
    base, lll, levels = n * ln, _lg(ln), _lg(m) / _lg(p.fan)
    value_bits = base * levels + n * lm
    return [
        ("count", "static", ln, base),
        ("report", "static", (p.out + 1) * ln, base),
        ("dominance", "static", (p.out + 1) * ln, base),
        ("visibility", "static", (p.out + 1) * ln, base),
        ("dominance", "dynamic", (p.out + 1) * lu * ln / lll, n * lu),
        ("moments", "static", min(p.t * lt, ln) * p.t * lt * ln, base * (1 + 1 / p.t)),
        ("moments", "dynamic", lu * ln * (1 + min(p.t * lt, lu) * p.t * lt / lll), n * lu * (1 + 1 / p.t)),
        ("moments", "update", lu * ln, 0.0),
        ("semigroup", "update", lu * (ln + p.t * lt), 0.0),
        ("extrema", "static", min(p.t * lm, ln) * p.t * ln, base * (1 + 1 / p.t)),
        ("extrema", "dense samples", min(p.t * lm, ln) * ln, 3 * base + base / p.t),
        ("top values", "static", p.t * lm * ln + p.out * p.t * lm * _lg(p.out), base),
        ("majority", "threshold at build", p.t * lm * ln * ln / p.alpha, n * ((2 + 1 / p.t) * ln + lm)),
        ("quantile", "static", p.fan * ln * levels, value_bits),
        ("quantile", "optimal counter", p.fan * ln * levels / lll, value_bits),
        ("value range count", "static", p.fan * ln * levels, value_bits),
        ("majority", "threshold at query", p.fan * ln * levels / p.alpha, value_bits),
        ("mode", "static", 4 / p.alpha * p.fan * ln * levels, value_bits),
        ("neighbours", "static", p.fan * ln * levels, value_bits),
        ("quantile", "dynamic", p.fan * lu * ln * lt / _lg(p.fan) / lll, n * lu * lt / _lg(p.fan)),
        ("count", "baseline, linear space", ln / lll, base),
        ("report", "baseline, fast", lll + p.out, base * math.sqrt(ln)),
        ("report", "baseline, succinct", p.out * ln / lll, base),
        ("dominance", "baseline, dynamic", ln * ln + p.out, base * ln),
        ("moments", "baseline, groups", ln, base * ln),
        ("extrema", "baseline, full table", 1.0, float(n) * n * ln),
        ("quantile", "baseline, y-tree", p.fan * ln**3 / lll, n * ln / _lg(p.fan) * (lt + ln)),
        ("majority", "baseline, y-tree", p.fan * ln * ln / p.alpha, n * (1 + _lg(1 / p.alpha)) * ln / _lg(p.fan) * (lt + ln)),
        ("neighbours", "baseline, y-tree", p.fan * ln * lu, n * ln / _lg(p.fan) * ln + n * lt),
    ]


def bounds_table(spark: SparkSession, p: Size) -> DataFrame:
    return spark.createDataFrame(bounds(p), "method string, kind string, steps double, bits double")


def least_bits(n: int, universe: int) -> float:
    """log2 of the number of sets of n points in a square universe."""
    cells = float(universe) ** 2
    return (math.lgamma(cells + 1) - math.lgamma(n + 1) - math.lgamma(cells - n + 1)) / math.log(2)


def space_report(tree: YTree) -> DataFrame:
    """(lvl, component, bits, bound): what each level stores; planes are bound by one digit for each point."""
    parts = []
    for j, level in enumerate(tree.levels):
        rows = level.rows.select(F.lit(j).alias("lvl"), "n", (F.size("vals") * 64).cast("long").alias("vals"), *([F.expr("cast(aggregate(planes, 0L, (a, p) -> a + size(p) * 64) as bigint)").alias("planes"), (F.size("before") * 64).cast("long").alias("before")] if j < tree.depth else []))
        for c in ("planes", "before", "vals") if j < tree.depth else ("vals",):
            parts.append(rows.groupBy("lvl").agg(F.lit(c).alias("component"), F.sum(c).alias("bits"), (F.sum("n") * (tree.bits if c == "planes" else 64)).alias("bound")))
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out


def estimate(tree: YTree, rects: int) -> dict[str, float]:
    """Block reads of the index, and blocks that a scan reads for the whole batch."""
    return {"index": rects * (2 * tree.depth * 2 + 4), "scan": -(-tree.n // tree.block)}


def choose(tree: YTree | None, rects: int, path: str = "auto") -> str:
    """index or scan: what reads fewer blocks, unless path says so or there is no index."""
    if path != "auto":
        return path
    if tree is None:
        return "scan"
    cost = estimate(tree, rects)
    return "index" if cost["index"] < cost["scan"] else "scan"
