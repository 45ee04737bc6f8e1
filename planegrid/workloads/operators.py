"""The operators around the methods: joins, aggregates, windows, sets, functions, sinks."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf

from planegrid.functions import bits as bit_sql
from planegrid.operators import index as point_index
from planegrid.operators import scan, staircase, ytree
from planegrid.plans.storage import fresh_path
from planegrid.sources import grids
from planegrid.sources import rects as rect_source
from planegrid.workloads import static

QUERIES: dict[str, static.Query] = {}
ORACLES: dict[str, str] = {}


def _t(spark: SparkSession, sf_dir: str, *names: str) -> list[DataFrame]:
    return [grids.table(spark, sf_dir, n) for n in names]


def _register(name: str, oracle: str | None):
    def put(f):
        QUERIES[name] = f
        if oracle:
            ORACLES[name] = oracle
        return f

    return put


@_register("op_filter_project_rect", "select l_orderkey, l_linenumber, l_quantity from lineitem where l_quantity between 10 and 12 and l_extendedprice between 10000 and 11000")
def _filtered(spark, sf_dir):
    return _t(spark, sf_dir, "lineitem")[0].where("l_quantity between 10 and 12 and l_extendedprice between 10000 and 11000").select("l_orderkey", "l_linenumber", "l_quantity")


@_register("op_range_join_binned", f"{static.hits_sql('P')} select * from h")
def _binned(spark, sf_dir):
    return grids.hits(spark, sf_dir, "P", rect_source.rects(spark, "P"), 16).select("qid", "x", "y", "w")


_REGION = "select r_name, n_name, count(*)::bigint as n, sum(cast(cast(c_acctbal as decimal(18,2)) * 100 as bigint))::bigint as cents from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey"


def _regions(spark, sf_dir, hint):
    c, n, r = _t(spark, sf_dir, "customer", "nation", "region")
    joined = c.join(n.hint(hint), F.col("c_nationkey") == F.col("n_nationkey")).join(r.hint(hint), F.col("n_regionkey") == F.col("r_regionkey"))
    return joined.withColumn("cents", F.expr("cast(cast(c_acctbal as decimal(18,2)) * 100 as bigint)"))


for _hint, _name in (("broadcast", "op_broadcast_join_regions"), ("merge", "op_shuffle_join_regions")):
    QUERIES[_name] = lambda spark, sf_dir, h=_hint: _regions(spark, sf_dir, h).groupBy("r_name", "n_name").agg(F.count("*").alias("n"), F.sum("cents").alias("cents"))
    ORACLES[_name] = f"{_REGION} group by r_name, n_name"
for _kind, _sql in (("rollup", "rollup(r_name, n_name)"), ("cube", "cube(r_name, n_name)")):
    QUERIES[f"op_{_kind}_stats"] = lambda spark, sf_dir, k=_kind: getattr(_regions(spark, sf_dir, "broadcast"), k)("r_name", "n_name").agg(F.count("*").alias("n"), F.sum("cents").alias("cents"))
    ORACLES[f"op_{_kind}_stats"] = f"{_REGION} group by {_sql}"


@_register("op_grouping_sets_stats", f"{_REGION} group by grouping sets ((r_name), (n_name), ())")
def _sets(spark, sf_dir):
    rows = _regions(spark, sf_dir, "broadcast")
    return rows.groupingSets([[F.col("r_name")], [F.col("n_name")], []], F.col("r_name"), F.col("n_name")).agg(F.count("*").alias("n"), F.sum("cents").alias("cents"))


_PARTIES = """a as (select 'customer' as kind, c_nationkey as k, cast(cast(c_acctbal as decimal(18,2)) * 100 as bigint) as w from customer
    union all select 'supplier', s_nationkey, cast(cast(s_acctbal as decimal(18,2)) * 100 as bigint) from supplier), b as (select kind, k, floor(w / 250000.0)::bigint as band, w from a)"""


def _bands(spark, sf_dir):
    c, s = _t(spark, sf_dir, "customer", "supplier")
    rows = lambda df, kind, p: df.select(F.lit(kind).alias("kind"), F.col(f"{p}_nationkey").alias("k"), F.expr(f"cast(cast({p}_acctbal as decimal(18,2)) * 100 as bigint)").alias("w"))
    return rows(c, "customer", "c").union(rows(s, "supplier", "s")).withColumn("band", F.floor(F.col("w") / 250000.0))


@_register("gis_region_stats", f"with {_PARTIES} select kind, k, band, count(*)::bigint as cnt, sum(w)::bigint as s, min(w) as lo, max(w) as hi from b group by kind, k, band")
def _gis(spark, sf_dir):
    return _bands(spark, sf_dir).groupBy("kind", "k", "band").agg(F.count("*").alias("cnt"), F.sum("w").alias("s"), F.min("w").alias("lo"), F.max("w").alias("hi"))


@_register("gis_region_mode", f"with {_PARTIES}, f as (select kind, k, band, count(*)::bigint as freq from b group by kind, k, band) select kind, k, band, freq from (select *, row_number() over (partition by kind, k order by freq desc, band) as o from f) where o = 1")
def _gis_mode(spark, sf_dir):
    each = _bands(spark, sf_dir).groupBy("kind", "k", "band").agg(F.count("*").alias("freq"))
    order = Window.partitionBy("kind", "k").orderBy(F.desc("freq"), "band")
    return each.withColumn("o", F.row_number().over(order)).where("o = 1").drop("o")


_SPANS = [(1, 1704067200000000, 1704153600000000), (2, 1704100000000000, 1704110000000000), (3, 5, 6)]


@_register("op_interval_join_events", f"select q::bigint as qid, count(e.event_id)::bigint as n from (values {', '.join(map(str, _SPANS))}) t(q, a, b) left join events e on epoch_us(e.ts) >= a and epoch_us(e.ts) < b group by q")
def _intervals(spark, sf_dir):
    spans = spark.createDataFrame(_SPANS, "qid bigint, x0 bigint, x1 bigint").select("qid", "x0", (F.col("x1") - 1).alias("x1"), F.lit(None).cast("bigint").alias("y0"), F.lit(None).cast("bigint").alias("y1"))
    return scan.count_in(grids.hits(spark, sf_dir, "E", spans), spans).withColumnRenamed("cnt", "n")


@_register("op_asof_prev_event", "select p.event_id, max(v.event_id) as prev from events p left join events v on v.user_id = p.user_id and v.event_type = 'view' and v.event_id < p.event_id where p.event_type = 'purchase' group by p.event_id")
def _asof(spark, sf_dir):
    e = _t(spark, sf_dir, "events")[0]
    before = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(before)
    return e.select("event_id", "user_id", "event_type").withColumn("prev", seen).where("event_type = 'purchase'").select("event_id", "prev")


for _how, _name, _not in (("left_semi", "op_semi_nonempty_rects", ""), ("left_anti", "op_anti_empty_rects", "not")):
    QUERIES[_name] = lambda spark, sf_dir, h=_how: rect_source.rects(spark, "P").join(grids.hits(spark, sf_dir, "P", rect_source.rects(spark, "P")).select("qid"), "qid", h).select("qid")
    ORACLES[_name] = f"{static.hits_sql('P')} select qid from r where qid {_not} in (select qid from h)"


@_register("op_distinct_approx_rect", f"{static.hits_sql('E')} select qid, count(distinct w)::bigint as n, true as near from h group by qid")
def _approx(spark, sf_dir):
    """The exact number, and whether the approximate one is within five hundredths of it."""
    hits = grids.hits(spark, sf_dir, "E", rect_source.rects(spark, "E"))
    found = hits.groupBy("qid").agg(F.approx_count_distinct("w", 0.01).alias("about")).join(hits.groupBy("qid").agg(F.count_distinct("w").alias("n")), "qid")
    return found.select("qid", "n", (F.abs(F.col("about") - F.col("n")) <= 0.05 * F.col("n") + 1).alias("near"))


@_register("op_window_staircase", f"with h as (select w as qid, x, y from ({grids.sql('P')})) {static._dominant(1, 1)}")
def _stairs(spark, sf_dir):
    """The dominant points of every weight class, by running maxima."""
    return staircase.dominant_points(grids.points(spark, sf_dir, "P").withColumnRenamed("w", "qid"))


@_register("op_window_rank", f"{static.hits_sql('P')} select qid, x, y, w, rank() over (partition by qid order by w) as r, dense_rank() over (partition by qid order by w) as d from h")
def _ranked(spark, sf_dir):
    by = Window.partitionBy("qid").orderBy("w")
    hits = grids.hits(spark, sf_dir, "P", rect_source.rects(spark, "P"))
    return hits.select("qid", "x", "y", "w", F.rank().over(by).cast("long").alias("r"), F.dense_rank().over(by).cast("long").alias("d"))


@_register("op_window_frames", """select event_id, sum(event_id) over (partition by user_id order by event_id rows between 2 preceding and current row)::bigint as last3,
    count(*) over (partition by user_id order by event_id range between 100 preceding and 100 following)::bigint as around from events""")
def _frames(spark, sf_dir):
    by = Window.partitionBy("user_id").orderBy("event_id")
    return _t(spark, sf_dir, "events")[0].select("event_id", F.sum("event_id").over(by.rowsBetween(-2, 0)).alias("last3"), F.count("*").over(by.rangeBetween(-100, 100)).alias("around"))


@_register("op_topk_per_rect", f"{static.hits_sql('E')} select qid, o as ord, w, x, y from (select *, row_number() over (partition by qid order by w, x, y) as o from h) where o <= 10")
def _topk(spark, sf_dir):
    return scan.topk_values(grids.hits(spark, sf_dir, "E", rect_source.rects(spark, "E")), 10)


_A, _B = "select x, y from ({g}) g where x between 5 and 20", "select x, y from ({g}) g where y between 92000 and 95000"
_SETS = " union all ".join(f"select '{n}' as op, * from (({_A}) {n} ({_B}))" for n in ("union", "intersect", "except")).replace("{g}", grids.sql("P"))


@_register("op_union_intersect_except", _SETS)
def _set_ops(spark, sf_dir):
    p = grids.points(spark, sf_dir, "P").select("x", "y")
    a, b = p.where("x between 5 and 20"), p.where("y between 92000 and 95000")
    name = lambda n, df: df.select(F.lit(n).alias("op"), "x", "y")
    return name("union", a.union(b).distinct()).union(name("intersect", a.intersect(b))).union(name("except", a.subtract(b)))


@_register("op_json_value_grid", "select user_id, sum(cast(json_extract_string(props, '$.k') as bigint))::bigint as k from events group by user_id")
def _json(spark, sf_dir):
    return _t(spark, sf_dir, "events")[0].groupBy("user_id").agg(F.sum(F.get_json_object("props", "$.k").cast("long")).alias("k"))


@_register("op_array_coord_grid", "select vec_id, cast(embedding[1] as double) as x, cast(embedding[2] as double) as y, len(embedding)::bigint as n from embeddings")
def _arrays(spark, sf_dir):
    return _t(spark, sf_dir, "embeddings")[0].select("vec_id", F.element_at("embedding", 1).cast("double").alias("x"), F.element_at("embedding", 2).cast("double").alias("y"), F.size("embedding").cast("long").alias("n"))


@_register("op_map_value_histogram", f"{static.hits_sql('D')}{static.FREQ} select qid, w, freq from f")
def _histogram(spark, sf_dir):
    f = scan.frequencies(grids.hits(spark, sf_dir, "D", rect_source.rects(spark, "D")))
    return f.groupBy("qid").agg(F.map_from_entries(F.collect_list(F.struct("w", "freq"))).alias("m")).select("qid", F.explode("m").alias("w", "freq"))


@_register("op_string_weight_grid", "select p_partkey, cast(regexp_extract(p_brand, '([0-9]+)', 1) as bigint) as brand, upper(p_type) as kind from part")
def _strings(spark, sf_dir):
    return _t(spark, sf_dir, "part")[0].select("p_partkey", F.regexp_extract("p_brand", "([0-9]+)", 1).cast("long").alias("brand"), F.upper("p_type").alias("kind"))


@udtf(returnType="rank bigint")
class ProbeRanks:
    """Ranks at which every value with more than alpha of n entries must be met: multiples of the least such count."""

    def eval(self, n: int, num: int, den: int):
        step = n * num // den + 1
        for rank in range(step, n + 1, step):
            yield (rank,)


_PROBED = """
    with c as (select l_suppkey, count(*)::bigint as n from lineitem group by l_suppkey), s as (select l_suppkey, n, num, n * num // 100 + 1 as step from c, (values (34), (20)) t(num))
    select l_suppkey, n, num, unnest(range(step, n + 1, step))::bigint as rank from s
"""


@_register("op_udtf_probe_ranks", _PROBED)
def _probes(spark, sf_dir):
    """Ranks to probe among each supplier's line items, for values with more than 34 and more than 20 of a hundred."""
    spark.udtf.register("probe_ranks", ProbeRanks)
    counted = _t(spark, sf_dir, "lineitem")[0].groupBy("l_suppkey").agg(F.count("*").alias("n"))
    return spark.sql("select l_suppkey, n, num, rank from {counted} cross join (values (34), (20)) t(num), lateral probe_ranks(n, num, 100)", counted=counted)


@_register("op_bit_pack_rank", "select p_size % 4 as d, count(*)::bigint as n from part group by 1")
def _packed(spark, sf_dir):
    """Digits of all parts packed into planes by blocks, and counted again from the planes."""
    rows = _t(spark, sf_dir, "part")[0].select((F.col("p_partkey") % 16).alias("blk"), F.col("p_partkey").alias("at"), (F.col("p_size") % 4).cast("long").alias("d"))
    blocks = rows.groupBy("blk").agg(F.sort_array(F.collect_list(F.struct("at", "d"))).alias("e")).select(F.col("e.d").alias("digits")).select(F.size("digits").cast("long").alias("off"), bit_sql.packed("digits", 2).alias("planes"))
    asked = blocks.withColumn("d", F.explode(F.sequence(F.lit(0), F.lit(3)))).withColumn("d", F.col("d").cast("long"))
    return asked.groupBy("d").agg(F.sum(F.expr(bit_sql.rank("planes", 2, "d", "off"))).alias("n")).select(F.col("d").cast("int").alias("d"), "n")


_DIGITS = "select p_partkey % 16 as blk, p_partkey as pos, p_size % 4 as d from part"


@_register("op_pandas_udf_rank", f"select blk, count(*)::bigint as n from ({_DIGITS}) where d = 1 group by blk")
def _pandas_rank(spark, sf_dir):
    """How often a digit occurs in a block, by a vectorised Python function: the form for digits that planes don't suit."""

    @F.pandas_udf("bigint")
    def ones(digits: pd.Series) -> pd.Series:
        return digits.map(lambda d: int((np.asarray(d) == 1).sum())).astype("int64")

    rows = _t(spark, sf_dir, "part")[0].select((F.col("p_partkey") % 16).alias("blk"), (F.col("p_size") % 4).cast("long").alias("d"))
    return rows.groupBy("blk").agg(F.collect_list("d").alias("digits")).select("blk", ones("digits").alias("n")).where("n > 0")


@_register("op_udaf_pack", f"select blk, bit_xor(d::bigint << ((pos // 16) % 30 * 2)::int)::bigint as packed from ({_DIGITS}) group by blk")
def _pandas_pack(spark, sf_dir):
    """Digits folded into one word for each block, by a grouped vectorised Python function."""

    @F.pandas_udf("bigint")
    def pack(digit: pd.Series, place: pd.Series) -> int:
        return int(np.bitwise_xor.reduce(digit.to_numpy(np.int64) << (2 * place.to_numpy(np.int64))))

    rows = _t(spark, sf_dir, "part")[0].select((F.col("p_partkey") % 16).alias("blk"), (F.col("p_size") % 4).cast("long").alias("d"), F.expr("p_partkey div 16 % 30").alias("place"))
    return rows.groupBy("blk").agg(pack("d", "place").alias("packed"))


@_register("op_index_roundtrip", f"{static.hits_sql('P')} {static.COUNT}")
def _index_roundtrip(spark, sf_dir):
    """An index that is written, and read again by its path alone."""
    path = point_index.build(grids.points(spark, sf_dir, "P")).path
    found = point_index.load(spark, path)
    return ytree.count_in(found.tree, found.bounds(rect_source.rects(spark, "P")))


@_register("op_sink_roundtrip", f"{grids.sql('P')}")
def _roundtrip(spark, sf_dir):
    path = fresh_path(spark, "sink")
    grids.points(spark, sf_dir, "P").withColumn("part", F.col("x") % 4).repartition("part").sortWithinPartitions("x", "y").write.partitionBy("part").parquet(path)
    return spark.read.parquet(path).select("x", "y", "w")
