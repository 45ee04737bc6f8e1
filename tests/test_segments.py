import random

import pytest

from planegrid.operators import dynamic, scan, segments
from planegrid.operators import index as point_index
from planegrid.operators.rangejoin import points_in
from planegrid.sources import connector
from tests.test_core import rect_table, rows, table


def test_segments_against_a_rebuilt_grid(spark):
    """Sums and extremes after batches of inserts, deletes and new weights, one of which comes again, before and after compaction."""
    rnd = random.Random(6)
    state = {k: (rnd.randrange(12), rnd.randrange(12), rnd.randrange(9)) for k in range(150)}
    base = spark.createDataFrame([(k, *v) for k, v in state.items()], "pid long, x long, y long, w long")
    store, logs, seq = segments.start(base, 2, 64), [], 0
    for _ in range(2):
        log = []
        for _ in range(60):
            seq += 1
            op, pid = rnd.choice(["insert", "delete", "delete", "set"]), rnd.randrange(170)
            if op == "insert" or (op == "set" and pid not in state):
                state[pid] = (rnd.randrange(12), rnd.randrange(12), rnd.randrange(9))
                log.append((seq, "insert", pid, *state[pid]))
            elif op == "delete":
                state.pop(pid, None)
                log.append((seq, op, pid, None, None, None))
            else:
                state[pid] = (*state[pid][:2], rnd.randrange(9))
                log.append((seq, op, pid, *state[pid]))
        logs.append(spark.createDataFrame(log, "seq long, op string, pid long, x long, y long, w long"))
    rects = rect_table(spark, [(1, 3, 11, 2, 9), (2, 0, 20, 0, 20), (3, 30, 40, 0, 1), (4, 5, 5, 0, 12)])
    for number, log in enumerate(logs):
        assert store.append(number, log) is not None
    assert store.append(0, logs[0]) is None
    alive = spark.createDataFrame([(k, *v) for k, v in state.items()], "pid long, x long, y long, w long")
    hits = points_in(alive.drop("pid"), rects)
    want = rows(scan.moments_in(hits, rects).select("qid", "cnt", "s"))
    ends = scan.extrema_in(hits, rects).where("lo is not null")
    for _ in range(2):
        assert rows(store.living()) == sorted(((k, *v) for k, v in state.items()), key=repr)
        assert rows(store.sums(rects)) == want
        assert rows(store.least(rects, start=1)) == rows(ends.select("qid", "lo", "lo_x", "lo_y"))
        assert rows(store.least(rects, True)) == rows(ends.select("qid", "hi", "hi_x", "hi_y"))
        before = len(store.segments)
        store.compact()
    assert before == 1 or len(store.segments) < 3


def test_an_index_is_a_source(spark):
    found = point_index.build(table(spark, [(k % 7, k, k % 3) for k in range(200)]), 2, 64)
    connector.register(spark, found.path)
    read = lambda name: spark.read.format("planegrid").option("table", name).load()
    assert rows(read("levels-0")) == rows(found.tree.levels[0].rows)
    assert rows(read("points").where("chunk = 0")) == rows(found.points.rows) and read("points").where("chunk = 5").count() == 0


def test_points_may_be_none(spark):
    """A grid without points answers every rectangle."""
    index = point_index.build(table(spark, []), 2, 64)
    from planegrid.operators import ytree

    assert rows(ytree.count_in(index.tree, index.bounds(rect_table(spark, [(1, 0, 5, 0, 5)])))) == [(1, 0)]


@pytest.mark.parametrize("sizes", [[100, 30, 9, 2], [10, 10, 1]])
def test_tiers_join_neighbours_only(sizes):
    assert [x for g in dynamic.tiers(sizes) for x in g] == sizes
