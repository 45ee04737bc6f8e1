from planegrid.llm import neardup, quality, runtime
from tests.conftest import SF


def test_few_rows_are_read_by_few_tasks(spark, monkeypatch):
    df = spark.range(100).repartition(40)
    out = runtime.narrow(df)
    assert out.rdd.getNumPartitions() == 1 and {r.id for r in out.collect()} == set(range(100))
    assert runtime.narrow(df.limit(0)).count() == 0
    monkeypatch.setattr(runtime, "NARROW_ROWS", 30)
    assert runtime.narrow(df).rdd.getNumPartitions() == 4 and runtime.narrow(df, 60).count() == 100


def test_small_tables_make_no_tasks_for_every_partition(spark):
    """Tasks for each shuffle partition beyond the first ones: a small table was read by as many tasks as a large one."""
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    conf = {"spark.sql.shuffle.partitions": "20", "spark.sql.adaptive.coalescePartitions.enabled": "false"}
    before = {k: spark.conf.get(k) for k in conf}
    sc = spark.sparkContext
    try:
        for k, v in conf.items():
            spark.conf.set(k, v)
        done = {}
        for name, run in (("quality", lambda: quality.keep_good(docs)), ("neardup", lambda: neardup.without_near_duplicates(docs))):
            sc.setJobGroup(name, name)
            run().count()
            tracker = sc.statusTracker()
            stages = {s for j in tracker.getJobIdsForGroup(name) for s in tracker.getJobInfo(j).stageIds}
            done[name] = sum(i.numCompletedTasks for s in stages if (i := tracker.getStageInfo(s)))
    finally:
        sc._jsc.clearJobGroup()
        for k, v in before.items():
            spark.conf.set(k, v)
    assert done["quality"] < 750 and done["neardup"] < 1250
