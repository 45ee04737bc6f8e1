"""The questions that the index answers, and its parts; checked by the same SQL as the scans.

Questions of a name path_* leave the choice between index and scan to the estimate of what each reads.
"""

from __future__ import annotations

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from planegrid.operators import descent, scan, staircase, valuetree, ytree
from planegrid.operators import index as point_index
from planegrid.operators.index import PointIndex
from planegrid.operators.rankspace import rank_space
from planegrid.plans import cost
from planegrid.plans.storage import folder
from planegrid.sources import grids
from planegrid.sources import rects as rect_source
from planegrid.workloads import static

QUERIES: dict[str, static.Query] = {}
ORACLES: dict[str, str] = {}
_BUILT: dict[tuple, object] = {}


def _once(spark: SparkSession, key: tuple, there, make):
    """make(), once for a session and key, and again if there() finds that its files have gone."""
    key = (spark.sparkContext.applicationId, folder(spark), *key)
    if key in _BUILT:
        try:
            there(_BUILT[key])
            return _BUILT[key]
        except AnalysisException:
            pass
    _BUILT[key] = make()
    return _BUILT[key]


def index(spark: SparkSession, sf_dir: str, grid: str, bits: int = 4, block: int = 256) -> PointIndex:
    """The grid's stored index."""
    return _once(spark, ("points", sf_dir, grid, bits, block), lambda x: spark.read.parquet(f"{x.path}/about"), lambda: point_index.build(grids.points(spark, sf_dir, grid), bits, block))


def value_index(spark: SparkSession, sf_dir: str, grid: str, bits: int = 4, block: int = 256) -> valuetree.ValueTree:
    ranked = index(spark, sf_dir, grid, bits, block).ranked
    return _once(spark, ("values", sf_dir, grid, bits, block), lambda x: spark.read.parquet(x.trees[-1].path + "/about"), lambda: valuetree.build(ranked, bits, block))


def add(name: str, grid: str, method, select: str, bits: int = 4, block: int = 256) -> None:
    """method: of the index and rects; select: over the SQL tables g, r and h."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return method(index(spark, sf_dir, grid, bits, block), rect_source.rects(spark, grid))

    QUERIES[name] = run
    ORACLES[name] = f"{static.hits_sql(grid)} {select}"


def extrema(found: PointIndex, rects: DataFrame) -> DataFrame:
    """Least and largest weights with their points."""
    rows = ytree.extrema_in(found.tree, found.bounds(rects))
    some = found.located(found.located(rows.where("lo is not null"), "_lo", "lo_xr"), "_hi", "hi_xr")
    return rows.select("qid", "lo", "hi").join(some.select("qid", F.col("x_lo").alias("lo_x"), F.col("y_lo").alias("lo_y"), F.col("x_hi").alias("hi_x"), F.col("y_hi").alias("hi_y")), "qid", "left")


def topk(found: PointIndex, rects: DataFrame, k: int, largest: bool) -> DataFrame:
    return found.located(ytree.topk_in(found.tree, found.bounds(rects), k, largest)).select("qid", "ord", "w", "x", "y")


def report(found: PointIndex, rects: DataFrame) -> DataFrame:
    return found.located(ytree.report_in(found.tree, found.bounds(rects)).select("qid", "xr")).select("qid", "x", "y", "w")


for _g in ("L", "P", "E", "V"):
    add(f"index_count_{_g}", _g, lambda i, r: ytree.count_in(i.tree, i.bounds(r)), static.COUNT)
for _g in ("L", "E", "S"):
    add(f"index_moments_{_g}", _g, lambda i, r: ytree.moments_in(i.tree, i.bounds(r)), static.MOMENTS)
    add(f"index_extrema_{_g}", _g, extrema, static.EXTREMA)
for _bits, _block in ((1, 64), (2, 256), (4, 1024)):
    add(f"index_moments_P_fan{1 << _bits}_block{_block}", "P", lambda i, r: ytree.moments_in(i.tree, i.bounds(r)), static.MOMENTS, _bits, _block)
for _g in ("E", "S", "L"):
    for _largest in (False, True):
        _order = "w desc, x, y" if _largest else "w, x, y"
        add(f"index_topk_{_g}{'_largest' * _largest}", _g, lambda i, r, b=_largest: topk(i, r, 5, b), f"select qid, o as ord, w, x, y from (select *, row_number() over (partition by qid order by {_order}) as o from h) where o <= 5")
for _g in ("P", "L"):
    add(f"index_report_{_g}", _g, report, "select qid, x, y, w from h")
for _g in ("L", "P", "O"):
    add(f"index_dominant_{_g}", _g, lambda i, r: descent.dominant_points(i, r), static._dominant(1, 1))
for _c, (_a, _b) in staircase.CORNERS.items():
    add(f"index_dominant_corner_{_c.lower()}_P", "P", lambda i, r, c=_c: descent.dominant_points(i, r, c), static._dominant(_a, _b))
for _g in static.EYES:
    for _d in ("SW", "NE", "SE", "NW"):
        QUERIES[f"index_visible_{_d.lower()}_{_g}"] = lambda spark, sf_dir, g=_g, d=_d: descent.visible_points(index(spark, sf_dir, g), static.eyes(spark, g), d)
        ORACLES[f"index_visible_{_d.lower()}_{_g}"] = static.ORACLES[f"visible_{_d.lower()}_{_g}"]

_COUNTS = {"index": lambda spark, sf_dir, g, r: ytree.count_in((i := index(spark, sf_dir, g)).tree, i.bounds(r)), "scan": lambda spark, sf_dir, g, r: scan.count_in(grids.hits(spark, sf_dir, g, r), r)}
_MOMENTS = {"index": lambda spark, sf_dir, g, r: ytree.moments_in((i := index(spark, sf_dir, g)).tree, i.bounds(r)), "scan": lambda spark, sf_dir, g, r: scan.moments_in(grids.hits(spark, sf_dir, g, r), r)}


def by_path(forms: dict, spark: SparkSession, sf_dir: str, grid: str, rects: DataFrame, path: str = "auto") -> DataFrame:
    """The answer by the index, by the scan, or by the one that is estimated to read less. All give the same rows."""
    return forms[cost.choose(index(spark, sf_dir, grid).tree, rects.count(), path)](spark, sf_dir, grid, rects)


def thousands() -> dict[str, static.Query]:
    """Counts and moments of a thousand rectangles over grid L by either path; not among the queries, as both give the same rows."""
    rects = lambda spark: rect_source.spread(spark, 1000, (1, 50), (90_000, 10_500_000))
    return {f"{p}_{w}_1000_L": lambda spark, sf_dir, f=f, p=p: by_path(f, spark, sf_dir, "L", rects(spark), p) for p in ("index", "scan") for w, f in (("count", _COUNTS), ("moments", _MOMENTS))}


for _path in ("auto", "index", "scan"):
    for _what, _forms, _select in (("count", _COUNTS, static.COUNT), ("moments", _MOMENTS, static.MOMENTS)):
        QUERIES[f"path_{_path}_{_what}_L"] = lambda spark, sf_dir, f=_forms, p=_path: by_path(f, spark, sf_dir, "L", rect_source.rects(spark, "L"), p)
        ORACLES[f"path_{_path}_{_what}_L"] = f"{static.hits_sql('L')} {_select}"

_RANKED = f"with g as ({grids.sql('P')}), a as (select *, row_number() over (order by x, y, w) - 1 as xr from g), b as (select *, row_number() over (order by y, x, w, xr) - 1 as yr from a)"
QUERIES["rank_space_points"] = lambda spark, sf_dir: rank_space(grids.points(spark, sf_dir, "P")).select("x", "y", "w", "xr", "yr")
ORACLES["rank_space_points"] = f"{_RANKED} select x, y, w, xr, yr from b"
QUERIES["map_rects"] = lambda spark, sf_dir: index(spark, sf_dir, "P").bounds(rect_source.rects(spark, "P"))
ORACLES["map_rects"] = f"""with g as ({grids.sql("P")}), r as ({rect_source.sql("P")}) select qid, (select count(*) from g where x < x0) as xlo, (select count(*) from g where x <= x1) as xhi,
    (select count(*) from g where y < y0) as ylo, (select count(*) from g where y <= y1) as yhi from r"""
QUERIES["sequence_access"] = lambda spark, sf_dir: ytree.access((i := index(spark, sf_dir, "P", 2, 256)).tree, i.ranked.select("xr"))
ORACLES["sequence_access"] = f"{_RANKED} select xr, yr from b"


def ranked_symbols(spark: SparkSession, sf_dir: str, lvl: int) -> DataFrame:
    """Ranks of symbols of a level at 40 places from 0 to the table's size, and selections from 0 to half of it; symbols are the first four nodes of the level."""
    found = index(spark, sf_dir, "P", 2, 256)
    at = lambda parts: F.expr(f"id * {found.n}L div {parts}")
    every = spark.range(40).crossJoin(spark.range(4).withColumnRenamed("id", "c"))
    ranks = ytree.sequence_rank(found.tree, every.select("c", at(39).alias("i")), lvl).select(F.lit("rank").alias("what"), "c", F.col("i").alias("arg"), F.col("r").alias("answer"))
    picked = ytree.sequence_select(found.tree, every.select("c", at(78 * 4 ** (lvl - 1)).alias("j")).distinct(), lvl)
    return ranks.union(picked.select(F.lit("select"), "c", "j", "place"))


for _lvl in (1, 2):
    QUERIES["sequence_rank_select" + f"_level_{_lvl}" * (_lvl > 1)] = lambda spark, sf_dir, v=_lvl: ranked_symbols(spark, sf_dir, v)
    ORACLES["sequence_rank_select" + f"_level_{_lvl}" * (_lvl > 1)] = f"""{_RANKED}, n as (select count(*) as n from b),
        t as (select case when n <= 256 then 8 + 2 else 8 + 2 * greatest(ceil((ceil(log2(n)) - 8) / 2.0), 1) end as top from n),
        s as (select xr, yr >> (t.top - {2 * _lvl})::int as c from b, t), o as (select c, xr, row_number() over (partition by c order by xr) as j from s),
        q as (select c, id * n // 39 as i, id * n // {78 * 4 ** (_lvl - 1)} as j from range(40) a(id), range(4) b(c), n)
        select 'rank' as what, q.c, q.i as arg, (select count(*) from s where s.c = q.c and s.xr < q.i) as answer from q
        union all select 'select', q.c, q.j, case when q.j = 0 then -1 else o.xr end from (select distinct c, j from q) q left join o on o.c = q.c and o.j = q.j"""


def covered(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The cover's nodes and the leaves at its ends hold together what the rectangle holds; as intervals of y-ranks they are disjoint."""
    found = index(spark, sf_dir, "P")
    tree = found.tree
    whole, ends = ytree.cover(tree, found.bounds(rect_source.rects(spark, "P")))
    edge = lambda node: F.expr(f"shiftleft({node}, cast({tree.leaf_bits} + {tree.bits} * ({tree.depth} - lvl) as int))")
    leaf = lambda node: F.expr(f"shiftleft({node}, {tree.leaf_bits})")
    spans = whole.select("qid", edge("node").alias("a"), edge("node + 1").alias("b")).union(ends.select("qid", F.greatest(leaf("node"), F.col("ylo")), F.least(leaf("node + 1"), F.col("yhi"))))
    before = F.max("b").over(Window.partitionBy("qid").orderBy("a").rowsBetween(Window.unboundedPreceding, -1))
    met = spans.withColumn("before", before).groupBy("qid").agg(F.count_if(F.col("before") > F.col("a")).alias("overlaps"))
    points = whole.select("qid", (F.col("hi") - F.col("lo")).alias("n")).union(ytree._leaf_points(tree, ends).select("qid", F.lit(1).cast("long")))
    return points.groupBy("qid").agg(F.sum("n").alias("points")).join(met, "qid").select("qid", "points", "overlaps")


QUERIES["cover_nodes"] = covered
ORACLES["cover_nodes"] = f"{static.hits_sql('P')} select qid, count(*)::bigint as points, 0::bigint as overlaps from h group by qid"


def add_value(name: str, grid: str, method, select: str, bits: int = 4, block: int = 256) -> None:
    """method: of the value tree, the point index and the rectangles' ranks."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        found = index(spark, sf_dir, grid, bits, block)
        return method(value_index(spark, sf_dir, grid, bits, block), found, found.bounds(rect_source.rects(spark, grid)))

    QUERIES[name] = run
    ORACLES[name] = f"{static.hits_sql(grid)} {select}"


def _quantiles_sql(shares: list[str]) -> str:
    return f"{static.RUNS}, c as (select distinct qid, cnt from f), a as (select qid, unnest([{', '.join(f'{s}' if '.' in s else f'{s}.0' for s in shares)}])::decimal(9,8) as p from r) select a.qid, a.p::double as p, k.w from a left join c on a.qid = c.qid left join k on k.qid = a.qid and greatest(ceil(a.p * c.cnt), 1) > k.s and greatest(ceil(a.p * c.cnt), 1) <= k.t"


_SHARES = ["0.1", "0.25", "0.5", "0.9", "1"]
for _g in ("P", "E"):
    add_value(f"index_kth_{_g}", _g, lambda t, i, b: valuetree.kth_in(t, b, static._ranks(b)), static._KTH)
    add_value(f"index_quantiles_{_g}", _g, lambda t, i, b: valuetree.quantiles_in(t, b, _SHARES), _quantiles_sql(_SHARES))
    add_value(f"index_top_fraction_{_g}", _g, lambda t, i, b: valuetree.top_fraction(t, i, b, "0.1"), "select qid, x, y, w from (select *, row_number() over (partition by qid order by w desc, x, y) as o, count(*) over (partition by qid) as n from h) where o <= ceil(0.1 * n)")
    for _k, _name in ((1, "mode"), (3, "topk_frequent")):
        add_value(f"index_{_name}_{_g}", _g, lambda t, i, b, k=_k, c=64 if _g == "P" else valuetree.CLOSEST: valuetree.topk_frequent(t, i, b, k, c), f"{static.FREQ} select qid, o as ord, w, freq from (select *, row_number() over (partition by qid order by freq desc, w) as o from f) where o <= {_k}")
add_value("index_median_L", "L", lambda t, i, b: valuetree.quantiles_in(t, b, ["0.5"]).select("qid", "w"), "select qid, quantile_disc(h.w, 0.5)::bigint as w from r left join h using (qid) group by qid")
for _bits in (1, 2):
    add_value(f"index_kth_P_fan{1 << _bits}", "P", lambda t, i, b: valuetree.kth_in(t, b, static._ranks(b)), static._KTH, _bits)
add_value("index_count_values_P", "P", lambda t, i, b: valuetree.count_values(t, b, 5, 11), "select qid, count(h.qid)::bigint as cnt from r left join (select * from h where w between 5 and 11) h using (qid) group by qid")
for _strict, _up, _down in ((False, ">=", "<="), (True, ">", "<")):
    add_value(f"index_neighbours_P{'_strict' * _strict}", "P", lambda t, i, b, s=_strict: valuetree.neighbours(t, b, 12, s), f"select qid, min(case when h.w {_up} 12 then h.w end) as succ, max(case when h.w {_down} 12 then h.w end) as pred from r left join h using (qid) group by qid")
for _alpha, _inc in (("0.5", False), ("0.05", False), ("0.2", True)):
    for _g in ("P", "D"):
        add_value(f"index_majority_{_g}_{_alpha.replace('.', '')}{'_inclusive' * _inc}", _g, lambda t, i, b, a=_alpha, c=_inc: valuetree.majority_in(t, b, a, c), f"{static.FREQ} select qid, w, freq, cnt from f where freq::decimal(38,8) {'>=' if _inc else '>'} {_alpha} * cnt")
