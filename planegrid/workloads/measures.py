"""Dominance and fixed-threshold majorities on the index, baselines, and what things cost."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from planegrid.operators import blocks, candidates, cellcube, descent, valuegrids, ytree
from planegrid.operators.blocks import Blocks
from planegrid.operators.valuegrids import ValueGrids
from planegrid.plans import cost
from planegrid.sources import grids
from planegrid.sources import rects as rect_source
from planegrid.workloads import static
from planegrid.workloads.indexed import _once, index

QUERIES: dict[str, static.Query] = {}
ORACLES: dict[str, str] = {}


def fixed_index(spark: SparkSession, sf_dir: str, grid: str, num: int, den: int) -> tuple[list[Blocks], ValueGrids]:
    """Candidate lists for a threshold, and the grids of the values."""
    found = index(spark, sf_dir, grid)
    lists = _once(spark, ("lists", sf_dir, grid, num, den), lambda x: spark.read.parquet(x[0].path), lambda: candidates.build(found.tree, num, den))
    return lists, _once(spark, ("value-grids", sf_dir, grid), lambda x: spark.read.parquet(x.tree.path + "/about"), lambda: valuegrids.build(found.ranked))


def _fixed(spark: SparkSession, sf_dir: str, grid: str, built: tuple[int, int], asked: tuple[int, int]) -> DataFrame:
    found, (lists, values) = index(spark, sf_dir, grid), fixed_index(spark, sf_dir, grid, *built)
    return candidates.majority_fixed(found.tree, lists, values, found.bounds(rect_source.rects(spark, grid)), *asked)


for _g, _built, _asked in (("L", (8, 100), (8, 100)), ("D", (1, 5), (1, 5)), ("D", (1, 5), (1, 2)), ("V", (8, 100), (8, 100))):
    _name = f"majority_fixed_{_g}_{_built[0]}_{_built[1]}_asked_{_asked[0]}_{_asked[1]}"
    QUERIES[_name] = lambda spark, sf_dir, g=_g, b=_built, a=_asked: _fixed(spark, sf_dir, g, b, a)
    ORACLES[_name] = f"{static.hits_sql(_g)}{static.FREQ} select qid, w, freq, cnt from f where freq * {_asked[1]} > cnt * {_asked[0]}"


def _precision(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many of the unverified candidates are answers; the right ones must be all there are."""
    rects, found = rect_source.rects(spark, "L"), index(spark, sf_dir, "L")
    bounds = found.bounds(rects)
    lists, values = fixed_index(spark, sf_dir, "L", 8, 100)
    every = candidates.unverified(found.tree, lists, bounds)
    return candidates.precision(every, candidates.majority_fixed(found.tree, lists, values, bounds, 8, 100), rects)


def _right(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Of the unverified candidates those that are frequent: the check that none is missed."""
    return _precision(spark, sf_dir).select("qid", "right", (F.col("candidates") >= F.col("right")).alias("enough"))


QUERIES["candidate_precision"] = _precision
QUERIES["candidate_recall"] = _right
ORACLES["candidate_recall"] = f"""{static.hits_sql("L")}{static.FREQ}, a as (select qid, count(*) as n from f where freq * 100 > cnt * 8 group by qid)
    select qid, coalesce(n, 0)::bigint as "right", true as enough from r left join a using (qid)"""
for _g in ("L", "E"):
    QUERIES[f"base_cell_cube_{_g}"] = lambda spark, sf_dir, g=_g: cellcube.sums_in(grids.points(spark, sf_dir, g), rect_source.rects(spark, g))
    ORACLES[f"base_cell_cube_{_g}"] = f"{static.hits_sql(_g)} select qid, count(h.w)::bigint as cnt, sum(h.w)::bigint as s from r left join h using (qid) group by qid"


    QUERIES[f"base_cell_extrema_{_g}"] = lambda spark, sf_dir, g=_g: cellcube.extrema_in(grids.points(spark, sf_dir, g), rect_source.rects(spark, g))
    ORACLES[f"base_cell_extrema_{_g}"] = f"{static.hits_sql(_g)} select qid, min(h.w) as lo, max(h.w) as hi from r left join h using (qid) group by qid"
    for _strict, _up in ((False, ">="), (True, ">")):
        QUERIES[f"base_ytree_succ_{_g}{'_strict' * _strict}"] = lambda spark, sf_dir, g=_g, s=_strict: ytree.successor_in((i := index(spark, sf_dir, g)).tree, i.bounds(rect_source.rects(spark, g)), 4, s)
        ORACLES[f"base_ytree_succ_{_g}{'_strict' * _strict}"] = f"{static.hits_sql(_g)} select qid, min(case when h.w {_up} 4 then h.w end) as succ from r left join h using (qid) group by qid"


def _ytree_majority(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Candidates of the tree over y, counted among the reported points instead of in grids of the values."""
    found = index(spark, sf_dir, "L")
    bounds = found.bounds(rect_source.rects(spark, "L"))
    hits = ytree.report_in(found.tree, bounds)
    freq = hits.join(candidates.values_for(found.tree, fixed_index(spark, sf_dir, "L", 8, 100)[0], bounds), ["qid", "w"], "left_semi").groupBy("qid", "w").agg(F.count("*").alias("freq"))
    return freq.join(ytree.count_in(found.tree, bounds), "qid").where("freq * 100 > cnt * 8").select("qid", "w", "freq", "cnt")


QUERIES["base_ytree_majority_L"] = _ytree_majority
ORACLES["base_ytree_majority_L"] = ORACLES["majority_fixed_L_8_100_asked_8_100"]
#: Sums at every 64th place, the least that a block may have: the form without sampling.
QUERIES["base_unsampled_sums_L"] = lambda spark, sf_dir: ytree.moments_in((i := index(spark, sf_dir, "L", 4, 64)).tree, i.bounds(rect_source.rects(spark, "L")))
ORACLES["base_unsampled_sums_L"] = f"{static.hits_sql('L')} {static.MOMENTS}"


def _steps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """method, rects, steps, bound: blocks asked for by a batch, and the published step count of as many questions, without constants."""
    found, rects = index(spark, sf_dir, "P"), rect_source.rects(spark, "P")
    bounds, q = found.bounds(rects), rects.count()
    p = cost.Size(found.n, 25, 26, 1 << 17, fan=found.tree.fan)
    published = {(m, k): steps for m, k, steps, _ in cost.bounds(p)}
    out = []
    forms = {
        "count": (lambda: ytree.count_in(found.tree, bounds), ("count", "static")),
        "moments": (lambda: ytree.moments_in(found.tree, bounds), ("moments", "static")),
        "extrema": (lambda: ytree.extrema_in(found.tree, bounds), ("extrema", "static")),
        "top values": (lambda: ytree.topk_in(found.tree, bounds, 5), ("top values", "static")),
        "report": (lambda: ytree.report_in(found.tree, bounds), ("report", "static")),
        "dominance": (lambda: descent.dominant_points(found, rects), ("dominance", "static")),
    }
    for name, (run, key) in forms.items():
        with blocks.traced() as trace:
            n = run().count()
        # output-sensitive bounds hold for each point that comes out
        out.append((name, q, sum(k for _, k in trace), float(published[key]) * (max(n, q) if key[0] in ("report", "dominance", "top values") else q)))
    return spark.createDataFrame(out, "method string, rects int, steps int, bound double").withColumn("ratio", F.round(F.col("steps") / F.col("bound"), 3))


def _sweep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """fan, block, levels, bits a point and steps of counts and moments, over fan-outs and block lengths."""
    out, rects = [], rect_source.rects(spark, "P")
    for bits, block in ((1, 64), (2, 64), (4, 64), (4, 256), (4, 1024)):
        found = index(spark, sf_dir, "P", bits, block)
        bounds, space = found.bounds(rects), {r.component: r.b for r in cost.space_report(found.tree).groupBy("component").agg(F.sum("bits").alias("b")).collect()}
        steps = []
        for method in (ytree.count_in, ytree.moments_in):
            with blocks.traced() as trace:
                method(found.tree, bounds).count()
            steps.append(sum(k for _, k in trace))
        out.append((1 << bits, block, found.tree.depth + 1, (space["planes"] + space["before"]) / found.n, *steps))
    return spark.createDataFrame(out, "fan int, block int, levels int, bits_per_point double, count_steps int, moments_steps int")


QUERIES["steps"] = _steps
QUERIES["sweep"] = _sweep


def _space(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cost.space_report(index(spark, sf_dir, "P").tree)


def _bounds(spark: SparkSession, sf_dir: str) -> DataFrame:
    tree = index(spark, sf_dir, "P").tree
    rows = [cost.bounds_table(spark, cost.Size(tree.n, 25, 26, 1 << 17, fan=1 << b, t=t)).withColumns({"fan": F.lit(1 << b), "t": F.lit(t)}) for b in (1, 2, 4) for t in (1.0, 2.0, 4.0)]
    out = rows[0]
    for r in rows[1:]:
        out = out.union(r)
    return out


QUERIES["space_measures"] = _space
QUERIES["bounds_table"] = _bounds
