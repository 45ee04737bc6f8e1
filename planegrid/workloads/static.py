"""The questions on static grids: each a query by the scan and the SQL that must give the same rows."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from planegrid.operators import scan, staircase
from planegrid.sources import grids
from planegrid.sources import rects as rect_source

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def hits_sql(grid: str) -> str:
    return f"""with g as ({grids.sql(grid)}), r as ({rect_source.sql(grid)}),
        h as (select r.qid, g.x, g.y, g.w from r join g on g.x between r.x0 and r.x1 and g.y between r.y0 and r.y1)"""


def add(name: str, grid: str, query: Callable[[DataFrame, DataFrame], DataFrame], select: str) -> None:
    """query: of hits and rects; select: over the SQL tables g, r and h."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        rects = rect_source.rects(spark, grid)
        return query(grids.hits(spark, sf_dir, grid, rects), rects)

    QUERIES[name] = run
    ORACLES[name] = f"{hits_sql(grid)} {select}"


COUNT = "select qid, count(h.qid)::bigint as cnt from r left join h using (qid) group by qid"
MOMENTS = """, m as (select qid, count(h.w)::bigint as n, sum(h.w)::bigint as s, sum(h.w::hugeint * h.w)::hugeint as q from r left join h using (qid) group by qid)
    , v as (select qid, n, s, case when n > 0 then greatest((n::double * q::double - s::double * s::double) / (n::double * n::double), 0) end as var from m)
    select qid, n as cnt, s, round(s::double / nullif(n, 0), 6) as avg, round(var, 4) as var, round(sqrt(var), 4) as std from v"""
EXTREMA = """select qid, a.w as lo, a.x as lo_x, a.y as lo_y, -b.w as hi, b.x as hi_x, b.y as hi_y from r left join
    (select qid, min({'w': w, 'x': x, 'y': y}) as a, min({'w': -w, 'x': x, 'y': y}) as b from h group by qid) using (qid)"""
FREQ = ", f as (select qid, w, count(*)::bigint as freq, (sum(count(*)) over (partition by qid))::bigint as cnt from h group by qid, w)"
RUNS = FREQ + ", u as (select *, (sum(freq) over (partition by qid order by w))::bigint as t from f), k as (select *, t - freq as s from u)"


def _dominant(a: int, b: int, table: str = "h") -> str:
    return f"""select qid, (row_number() over (partition by qid order by {b} * y desc))::bigint as ord, x, y from (
        select *, max({a} * x) over (partition by qid order by {b} * y desc, {a} * x desc rows between unbounded preceding and 1 preceding) as m from (select distinct qid, x, y from {table})) where m is null or {a} * x > m"""


for _g in ("L", "O"):
    add(f"count_rect_{_g}" if _g != "L" else "count_rect", _g, scan.count_in, COUNT)
    add(f"dominant_rect_{_g}" if _g != "L" else "dominant_rect", _g, lambda h, r: staircase.dominant_points(h), _dominant(1, 1))
add("report_rect", "L", lambda h, r: scan.report_in(h), "select qid, x, y, w from h")
add("dominant_worst_combo", "C", lambda h, r: staircase.dominant_points(h, "NW"), _dominant(-1, 1))
for _c, (_a, _b) in staircase.CORNERS.items():
    add(f"dominant_corner_{_c.lower()}", "P", lambda h, r, c=_c: staircase.dominant_points(h, c), _dominant(_a, _b))
for _g, _n in (("L", "sum_rect"), ("S", "avg_rect"), ("E", "var_rect"), ("C", "moments_customers")):
    add(_n, _g, scan.moments_in, MOMENTS)
add("group_xor_rect", "O", lambda h, r: scan.group_in(h, r, F.bit_xor("w"), F.lit(0)), "select qid, coalesce(bit_xor(h.w), 0)::bigint as val from r left join h using (qid) group by qid")
add("group_mod_rect", "O", lambda h, r: scan.group_in(h, r, F.sum("w") % 97, F.lit(0)), "select qid, coalesce(sum(h.w) % 97, 0)::bigint as val from r left join h using (qid) group by qid")
add("semigroup_or_rect", "O", lambda h, r: scan.group_in(h, r, F.bit_or("w"), F.lit(0)), "select qid, coalesce(bit_or(h.w), 0)::bigint as val from r left join h using (qid) group by qid")
for _g, _n in (("E", "min_max_rect"), ("S", "argmin_rect"), ("V", "extrema_intensity")):
    add(_n, _g, scan.extrema_in, EXTREMA)
add("topk_values_rect", "E", lambda h, r: scan.topk_values(h, 5), "select qid, o as ord, w, x, y from (select *, row_number() over (partition by qid order by w, x, y) as o from h) where o <= 5")
add("topk_largest_rect", "S", lambda h, r: scan.topk_values(h, 3, True), "select qid, o as ord, w, x, y from (select *, row_number() over (partition by qid order by w desc, x, y) as o from h) where o <= 3")
for _g, _alpha, _inc in (("L", "0.08", False), ("L", "0.5", False), ("L", "0.2", True), ("D", "0.5", False), ("D", "0.2", False), ("D", "0.5", True), ("V", "0.08", False), ("V", "0.1", True)):
    add(f"majority_rect_{_g}_{_alpha.replace('.', '')}{'_inclusive' * _inc}", _g, lambda h, r, a=_alpha, i=_inc: scan.majority_in(h, a, i), f"{FREQ} select qid, w, freq, cnt from f where freq::decimal(38,8) {'>=' if _inc else '>'} {_alpha} * cnt")
for _g in ("L", "D", "V"):
    add(f"mode_rect_{_g}", _g, lambda h, r: scan.topk_frequent(h, 1), f"{FREQ} select qid, o as ord, w, freq from (select *, row_number() over (partition by qid order by freq desc, w) as o from f) where o <= 1")
    add(f"topk_frequent_rect_{_g}", _g, lambda h, r: scan.topk_frequent(h, 3), f"{FREQ} select qid, o as ord, w, freq from (select *, row_number() over (partition by qid order by freq desc, w) as o from f) where o <= 3")


def _ranks(rects: DataFrame) -> DataFrame:
    return rects.select("qid", F.explode(F.array(*(F.lit(k).cast("long") for k in (0, 1, 7, 100, 100_000)))).alias("k"))


_KTH = f"{RUNS} select a.qid, a.k, k.w from (select qid, unnest([0, 1, 7, 100, 100000])::bigint as k from r) a left join k on k.qid = a.qid and a.k > k.s and a.k <= k.t"
for _g in ("E", "S"):
    add(f"kth_rect_{_g}", _g, lambda h, r: scan.kth_in(h, _ranks(r)), _KTH)
    _shares = ["0.1", "0.25", "0.5", "0.9", "1"]
    _sql = f"{RUNS}, c as (select distinct qid, cnt from f), a as (select qid, unnest([0.1, 0.25, 0.5, 0.9, 1.0])::decimal(9,8) as p from r) select a.qid, a.p::double as p, k.w from a left join c on a.qid = c.qid left join k on k.qid = a.qid and greatest(ceil(a.p * c.cnt), 1) > k.s and greatest(ceil(a.p * c.cnt), 1) <= k.t"
    add(f"quantiles_rect_{_g}", _g, lambda h, r, s=tuple(_shares): scan.quantiles_in(h, r, list(s)), _sql)
add("median_rect", "L", lambda h, r: scan.quantiles_in(h, r, ["0.5"]).select("qid", "w"), "select qid, quantile_disc(h.w, 0.5)::bigint as w from r left join h using (qid) group by qid")
add("top_fraction_rect", "E", lambda h, r: scan.top_fraction(h, "0.1"), "select qid, x, y, w from (select *, row_number() over (partition by qid order by w desc, x, y) as o, count(*) over (partition by qid) as n from h) where o <= ceil(0.1 * n)")
add("count_value_range_rect", "E", lambda h, r: scan.count_values(h, r, 1_000, 5_000), "select qid, count(h.qid)::bigint as cnt from r left join (select * from h where w between 1000 and 5000) h using (qid) group by qid")
for _g, _w in (("E", 4_000), ("O", 700)):
    for _strict in (False, True):
        _up, _down = (">", "<") if _strict else (">=", "<=")
        add(f"neighbours_rect_{_g}{'_strict' * _strict}", _g, lambda h, r, w=_w, s=_strict: scan.neighbours(h, r, w, s), f"select qid, min(case when h.w {_up} {_w} then h.w end) as succ, max(case when h.w {_down} {_w} then h.w end) as pred from r left join h using (qid) group by qid")
add("array_intensity_stats", "V", scan.moments_in, MOMENTS)
add("array_intensity_quantiles", "V", lambda h, r: scan.quantiles_in(h, r, ["0.25", "0.5", "0.75"]), f"{RUNS}, c as (select distinct qid, cnt from f), a as (select qid, unnest([0.25, 0.5, 0.75])::decimal(9,8) as p from r) select a.qid, a.p::double as p, k.w from a left join c on a.qid = c.qid left join k on k.qid = a.qid and greatest(ceil(a.p * c.cnt), 1) > k.s and greatest(ceil(a.p * c.cnt), 1) <= k.t")
add("distinct_values_rect", "E", scan.distinct_values, "select qid, count(distinct h.w)::bigint as n from r left join h using (qid) group by qid")

#: Query points by grid, for visibility.
EYES = {"P": [(1, 25, 95_000), (2, 10, 93_000), (3, 100, 0)], "O": [(1, 900000000000000, 20_000_000), (2, 850000000000000, 30_000_000)]}


def eyes(spark: SparkSession, grid: str) -> DataFrame:
    return spark.createDataFrame(EYES[grid], "qid bigint, qx bigint, qy bigint")


def visible(spark: SparkSession, sf_dir: str, grid: str, direction: str) -> DataFrame:
    return staircase.visible_points(grids.hits(spark, sf_dir, grid, staircase.quadrant(eyes(spark, grid), direction)), direction)


for _g in EYES:
    for _d, (_a, _b) in {"SW": (1, 1), "NE": (-1, -1), "SE": (-1, 1), "NW": (1, -1)}.items():
        _name = f"visible_{_d.lower()}_{_g}"
        QUERIES[_name] = lambda spark, sf_dir, g=_g, d=_d: visible(spark, sf_dir, g, d)
        _rows = ", ".join(map(str, EYES[_g]))
        ORACLES[_name] = f"""with g as ({grids.sql(_g)}), q as (select * from (values {_rows}) t(qid, qx, qy)),
            h as (select q.qid::bigint as qid, g.x, g.y from q join g on {_a} * g.x <= {_a} * q.qx and {_b} * g.y <= {_b} * q.qy)
            select qid, '{_d}' as direction, x, y from ({_dominant(_a, _b)})"""
    QUERIES[f"visible_all_{_g}"] = lambda spark, sf_dir, g=_g: visible(spark, sf_dir, g, "SW").union(visible(spark, sf_dir, g, "NE")).union(visible(spark, sf_dir, g, "SE")).union(visible(spark, sf_dir, g, "NW"))
    ORACLES[f"visible_all_{_g}"] = " union all ".join(f"select * from ({ORACLES[f'visible_{d}_{_g}']})" for d in ("sw", "ne", "se", "nw"))
