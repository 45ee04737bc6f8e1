"""Questions after updates, and on event time."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from planegrid.operators import dynamic, scan, segments, staircase
from planegrid.operators.rangejoin import points_in
from planegrid.plans.storage import fresh_path
from planegrid.sources import grids
from planegrid.sources import rects as rect_source
from planegrid.streaming import rect_counts
from planegrid.workloads import static
from planegrid.workloads.indexed import _once

QUERIES: dict[str, static.Query] = {}
ORACLES: dict[str, str] = {}


def events(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, ...]:
    """The first four fifths of the events as base; batches of changes: the rest as inserts, then deletes and heavier weights by the id's last digit."""
    g = grids.GRIDS["E"]
    rows = grids.table(spark, sf_dir, "events").select(F.col("event_id").alias("pid"), F.expr(g.x).alias("x"), F.expr(g.y).alias("y"), F.expr(g.w).alias("w"))
    n = rows.count()
    base, late = rows.where(F.col("pid") < 0.8 * n), rows.where(F.col("pid") >= 0.8 * n)
    row = lambda df, seq, op, x, w: df.select(seq.cast("long").alias("seq"), F.lit(op).alias("op"), "pid", x.alias("x"), (F.col("y") if op == "insert" else F.lit(None).cast("long")).alias("y"), w.alias("w"))
    none = F.lit(None).cast("long")
    inserts = row(late, F.col("pid"), "insert", F.col("x"), F.col("w"))
    deletes = row(base.where("pid % 10 = 3"), F.col("pid") + n, "delete", none, none)
    heavier = row(base.where("pid % 10 = 7"), F.col("pid") + 2 * n, "set", none, F.col("w") + 100)
    return base, inserts, deletes, heavier


def base_and_log(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    """The base and the whole log, in which one batch comes twice."""
    base, inserts, deletes, heavier = events(spark, sf_dir)
    return base, inserts.union(deletes).union(heavier).union(inserts)


def store(spark: SparkSession, sf_dir: str, compacted: bool) -> segments.Store:
    """The same as a base and three batches, the first of which comes again; made once for a session."""

    def make() -> segments.Store:
        base, *batches = events(spark, sf_dir)
        found = segments.start(base, block=1024)
        for number in (0, 1, 0, 2):
            found.append(number, batches[number])
        if compacted:
            found.compact()
        return found

    return _once(spark, ("segments", sf_dir, compacted), lambda x: [spark.read.parquet(f"{i.path}/about") for s in x.segments for _, i in s.sides], make)


_ALIVE = f"""select x, y, w from (select event_id as pid, x, y, case when pid % 10 = 7 and pid < 0.8 * n then w + 100 else w end as w, n from
    (select event_id, {grids.GRIDS["E"].sql[0]} as x, user_id as y, {grids.GRIDS["E"].w} as w from events), (select count(*) as n from events)) where not (pid % 10 = 3 and pid < 0.8 * n)"""


def _hits_sql() -> str:
    return f"with g as ({_ALIVE}), r as ({rect_source.sql('E')}), h as (select r.qid, g.x, g.y, g.w from r join g on g.x between r.x0 and r.x1 and g.y between r.y0 and r.y1)"


def _changed_sums(spark: SparkSession, sf_dir: str) -> DataFrame:
    base, log = base_and_log(spark, sf_dir)
    rects = rect_source.rects(spark, "E")
    before = scan.moments_in(points_in(base, rects), rects).select("qid", "cnt", "s")
    return dynamic.corrected_sums(before, points_in(dynamic.signed(base, log), rects))


QUERIES["dyn_sum_after_updates"] = _changed_sums
ORACLES["dyn_sum_after_updates"] = f"{_hits_sql()} select qid, count(h.w)::bigint as cnt, sum(h.w)::bigint as s from r left join h using (qid) group by qid"
for _name, _method, _select in (
    ("dyn_min_after_updates", lambda h, r: scan.extrema_in(h, r), static.EXTREMA),
    ("dyn_kth_after_updates", lambda h, r: scan.kth_in(h, static._ranks(r)), static._KTH),
    ("dyn_dominant_after_updates", lambda h, r: staircase.dominant_points(h), static._dominant(1, 1)),
    ("dyn_majority_after_updates", lambda h, r: scan.majority_in(h, "0.001", True), f"{static.FREQ} select qid, w, freq, cnt from f where freq::decimal(38,8) >= 0.001 * cnt"),
    ("dyn_topk_frequent_after_updates", lambda h, r: scan.topk_frequent(h, 2), f"{static.FREQ} select qid, o as ord, w, freq from (select *, row_number() over (partition by qid order by freq desc, w) as o from f) where o <= 2"),
    ("dyn_neighbours_after_updates", lambda h, r: scan.neighbours(h, r, 4_000), "select qid, min(case when h.w >= 4000 then h.w end) as succ, max(case when h.w <= 4000 then h.w end) as pred from r left join h using (qid) group by qid"),
):

    def _run(spark: SparkSession, sf_dir: str, method=_method) -> DataFrame:
        rects = rect_source.rects(spark, "E")
        return method(points_in(dynamic.alive(*base_and_log(spark, sf_dir)), rects), rects)

    QUERIES[_name] = _run
    ORACLES[_name] = f"{_hits_sql()} {_select}"


for _compacted in (False, True):
    _when = "compaction" if _compacted else "batches"
    QUERIES[f"dyn_segments_sum_after_{_when}"] = lambda spark, sf_dir, c=_compacted: store(spark, sf_dir, c).sums(rect_source.rects(spark, "E"))
    ORACLES[f"dyn_segments_sum_after_{_when}"] = ORACLES["dyn_sum_after_updates"]
    for _largest in (False, True):
        _name = f"dyn_segments_{'max' if _largest else 'min'}_after_{_when}"
        QUERIES[_name] = lambda spark, sf_dir, c=_compacted, b=_largest: store(spark, sf_dir, c).least(rect_source.rects(spark, "E"), b)
        ORACLES[_name] = f"{_hits_sql()} select qid, w, x, y from (select *, row_number() over (partition by qid order by w {'desc' * _largest}, x, y) as o from h) where o = 1"


def _update_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    """batch, points: signed points that each batch writes; one that comes again writes nothing."""
    base, *batches = events(spark, sf_dir)
    found, out = segments.start(base, block=1024), []
    for at, number in enumerate((0, 1, 0, 2)):
        new = found.append(number, batches[number])
        out.append((at, new.size if new else 0))
    return spark.createDataFrame(out, "batch long, points long")


QUERIES["dyn_update_cost"] = _update_cost
ORACLES["dyn_update_cost"] = """with n as (select count(*) as n from events), e as (select event_id as p, p < 0.8 * n as old from events, n)
    select 0::bigint as batch, count(*) filter (not old)::bigint as points from e union all select 1, count(*) filter (old and p % 10 = 3) from e
    union all select 2, 0 union all select 3, 2 * count(*) filter (old and p % 10 = 7) from e"""


def timed(spark: SparkSession, sf_dir: str) -> DataFrame:
    return grids.table(spark, sf_dir, "events").select(F.col("ts").cast("timestamp").alias("ts"), "user_id", F.expr(grids.GRIDS["E"].w).alias("w"))


_TIMED = f"with e as (select epoch_us(ts) as t, user_id, {grids.GRIDS['E'].w} as w from events)"
_HOUR = 3_600_000_000
QUERIES["op_win_tumbling"] = lambda spark, sf_dir: rect_counts.windowed(timed(spark, sf_dir), "1 hour")
ORACLES["op_win_tumbling"] = f"{_TIMED} select t - t % {_HOUR} as start, count(*)::bigint as cnt, sum(w)::bigint as s from e group by 1"
QUERIES["op_win_sliding"] = lambda spark, sf_dir: rect_counts.windowed(timed(spark, sf_dir), "2 hours", "1 hour")
ORACLES["op_win_sliding"] = f"{_TIMED} select t - t % {_HOUR} - k * {_HOUR} as start, count(*)::bigint as cnt, sum(w)::bigint as s from e, range(2) q(k) group by 1"
QUERIES["op_win_session"] = lambda spark, sf_dir: rect_counts.sessions(timed(spark, sf_dir), "1 hour")
ORACLES["op_win_session"] = f"""{_TIMED}, a as (select *, case when t - lag(t) over w1 < {_HOUR} then 0 else 1 end as f from e window w1 as (partition by user_id order by t)),
    b as (select *, sum(f) over (partition by user_id order by t rows unbounded preceding) as k from a) select user_id, min(t) as start, count(*)::bigint as cnt, sum(w)::bigint as s from b group by user_id, k"""


def streamed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events as files of points, read as a stream."""
    folder = fresh_path(spark, "stream")
    points = grids.points(spark, sf_dir, "E").select("x", "y", "w")
    points.repartition(6).write.parquet(f"{folder}/in")
    return rect_counts.counts_from_files(spark, f"{folder}/in", points.schema, rect_source.rects(spark, "E"), f"{folder}/out", f"{folder}/state")


QUERIES["op_stream_rect_counts"] = streamed
ORACLES["op_stream_rect_counts"] = f"{static.hits_sql('E')} {static.COUNT}"
