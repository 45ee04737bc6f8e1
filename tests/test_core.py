import random
from collections import Counter
from decimal import Decimal

import pytest
from pyspark.sql import functions as F

from planegrid.functions import bits as bit_sql
from planegrid.operators import candidates, cellcube, descent, dynamic, scan, staircase, valuegrids, valuetree, ytree
from planegrid.operators import index as point_index
from planegrid.operators.rangejoin import points_in
from planegrid.operators.rankspace import rank_space
from planegrid.plans import cost
from planegrid.plans.storage import cut
from planegrid.sources import grids
from planegrid.sources import rects as rect_source

MICRO = [(1, 5, 3), (3, 5, 7), (2, 2, 3), (4, 1, 9), (5, 4, 3), (5, 6, 1), (7, 3, 7), (6, 2, 3)]
MICRO_RECTS = [(1, 1, 7, 1, 6), (2, 2, 6, 2, 5), (3, 3, 3, 5, 5), (4, 8, 9, 1, 6)]


def table(spark, rows):
    return spark.createDataFrame(rows, "x bigint, y bigint, w bigint")


def rect_table(spark, rows):
    return spark.createDataFrame(rows, "qid bigint, x0 bigint, x1 bigint, y0 bigint, y1 bigint")


def inside(points, r):
    return [p for p in points if (r[1] is None or p[0] >= r[1]) and (r[2] is None or p[0] <= r[2]) and (r[3] is None or p[1] >= r[3]) and (r[4] is None or p[1] <= r[4])]


def staircase_of(points, a=1, b=1):
    distinct = {(x, y) for x, y, _ in points}
    return sorted((p for p in distinct if not any(a * q[0] >= a * p[0] and b * q[1] >= b * p[1] and q != p for q in distinct)), key=lambda p: -b * p[1])


def rows(df):
    return sorted((tuple(r) for r in df.collect()), key=repr)


@pytest.fixture(scope="module")
def micro(spark):
    return points_in(table(spark, MICRO), rect_table(spark, MICRO_RECTS)), rect_table(spark, MICRO_RECTS)


def test_micro_grid_by_hand(micro):
    hits, rects = micro
    got = {r.qid: r for r in scan.moments_in(hits, rects).collect()}
    assert [(got[q].cnt, got[q].s, got[q].var) for q in (1, 2, 3, 4)] == [(8, 36, 6.75), (4, 16, 3.0), (1, 7, 0.0), (0, None, None)]
    assert rows(scan.quantiles_in(hits, rects, ["0.5"]).select("qid", "w")) == [(1, 3), (2, 3), (3, 7), (4, None)]
    assert rows(scan.topk_frequent(hits, 1).select("qid", "w", "freq")) == [(1, 3, 4), (2, 3, 3), (3, 7, 1)]
    assert [(r.x, r.y) for r in staircase.dominant_points(hits).where("qid = 1").orderBy("ord").collect()] == [(5, 6), (7, 3)]
    assert [(r.x, r.y) for r in staircase.dominant_points(hits).where("qid = 2").orderBy("ord").collect()] == [(3, 5), (5, 4), (6, 2)]
    only = lambda df: rows(df.where("qid = 1").select("w"))
    assert only(scan.majority_in(hits, "0.5")) == [] and only(scan.majority_in(hits, "0.5", True)) == [(3,)] and only(scan.majority_in(hits, "0.2")) == [(3,), (7,)]
    assert [r.succ for r in scan.neighbours(hits, rects, 4).where("qid = 1").collect()] == [7]
    assert [r.succ for r in scan.neighbours(hits, rects, 10).where("qid = 1").collect()] == [None]
    strict = scan.neighbours(hits, rects, 3, True).where("qid = 1").first()
    assert (strict.succ, strict.pred) == (7, 1)


def test_visibility_by_hand(spark):
    eye = spark.createDataFrame([(1, 4, 4)], "qid bigint, qx bigint, qy bigint")
    want = {"SW": {(2, 2), (4, 1)}, "NE": {(5, 4)}, "SE": {(4, 1), (5, 4)}, "NW": {(3, 5)}}
    for d, points in want.items():
        hits = points_in(table(spark, MICRO), staircase.quadrant(eye, d))
        assert {(r.x, r.y) for r in staircase.visible_points(hits, d).collect()} == points


def test_least_counts_are_whole_numbers(spark):
    """Values 1, 2, 3, 3 with a threshold of 0.34: two of four are enough, and rank 2 and 4 are asked for."""
    points = table(spark, [(k, k, w) for k, w in enumerate((1, 2, 3, 3))])
    rects = rect_table(spark, [(1, 0, 9, 0, 9)])
    assert rows(scan.majority_in(points_in(points, rects), "0.34").select("w")) == [(3,)]
    index = point_index.build(points, 1, 64)
    assert rows(valuetree.majority_in(valuetree.build(index.ranked, 1, 64), index.bounds(rects), "0.34").select("w")) == [(3,)]


def random_grid(seed, n, span, values):
    rnd = random.Random(seed)
    points = [(rnd.randrange(-span, span), rnd.randrange(-span, span), rnd.randrange(-values, values)) for _ in range(n)]
    out = []
    for q in range(12):
        (x0, x1), (y0, y1) = (sorted((rnd.randrange(-span - 2, span + 2), rnd.randrange(-span - 2, span + 2))) for _ in range(2))
        out.append((q, *(None if rnd.random() < 0.1 else v for v in (x0, x1, y0, y1))))
    return points, [*out, (50, 5, 4, 0, 9), (51, -span, span, -span, span), (52, 0, 0, 0, 0)]


@pytest.mark.parametrize(("seed", "n", "span", "values", "bits", "block"), [(2, 300, 14, 9, 2, 64)])
def test_index_and_scan_against_brute_force(spark, seed, n, span, values, bits, block):
    points, wanted = random_grid(seed, n, span, values)
    df, rects = cut(table(spark, points)), cut(rect_table(spark, wanted))
    hits = cut(points_in(df, rects))
    index = point_index.build(df, bits, block)
    ranked = index.ranked
    assert sorted(r.xr for r in ranked.collect()) == sorted(r.yr for r in ranked.collect()) == list(range(n))
    bounds, tree = index.bounds(rects), point_index.load(spark, index.path).tree
    held = {r[0]: inside(points, r) for r in wanted}
    count = sorted(((q, len(p)) for q, p in held.items()), key=repr)
    assert rows(scan.count_in(hits, rects)) == count == rows(ytree.count_in(tree, bounds))
    assert rows(ytree.moments_in(tree, bounds)) == rows(scan.moments_in(hits, rects))
    assert {r.qid: r.s for r in ytree.moments_in(tree, bounds).collect()} == {q: sum(w for *_, w in p) if p else None for q, p in held.items()}
    least = sorted(((q, min((w for *_, w in p), default=None), max((w for *_, w in p), default=None)) for q, p in held.items()), key=repr)
    assert rows(ytree.extrema_in(tree, bounds).select("qid", "lo", "hi")) == least == rows(scan.extrema_in(hits, rects).select("qid", "lo", "hi"))
    for largest in (False, True):
        top = sorted(((q, k + 1, w) for q, p in held.items() for k, w in enumerate(sorted((w for *_, w in p), reverse=largest)[:7])), key=repr)
        assert rows(ytree.topk_in(tree, bounds, 7, largest).select("qid", "ord", "w")) == top
    reported = ytree.report_in(tree, bounds).join(ranked, ["xr", "yr"]).groupBy("qid").count()
    assert rows(reported) == sorted(((q, len(p)) for q, p in held.items() if p), key=repr)
    for corner, (a, b) in staircase.CORNERS.items():
        stairs = sorted(((q, x, y) for q, p in held.items() for x, y in staircase_of(p, a, b)), key=repr)
        assert rows(staircase.dominant_points(hits, corner).select("qid", "x", "y")) == stairs
        if corner in ("NE", "NW"):
            assert rows(descent.dominant_points(index, rects, corner).select("qid", "x", "y")) == stairs
    kept: list[int] = []
    found = descent.dominant_ranks(tree, bounds, trace=kept)
    assert all(k <= found.count() for k in kept)
    assert rows(ytree.access(tree, ranked.select("xr")))[:5] == rows(ranked.select("xr", "yr"))[:5]
    lists = candidates.build(tree, 1, 5)
    fixed = candidates.majority_fixed(tree, lists, valuegrids.build(ranked, bits, block), bounds, 1, 5)
    freq = {q: Counter(w for *_, w in p) for q, p in held.items()}
    enough = lambda share, inc: sorted(((q, w, c, len(held[q])) for q, f in freq.items() for w, c in f.items() if (c >= Decimal(share) * len(held[q]) if inc else c > Decimal(share) * len(held[q]))), key=repr)
    assert rows(fixed) == enough("0.2", False)
    values_tree = valuetree.build(ranked, bits, block)
    for share, inc in (("0.5", False), ("0.15", True)):
        assert rows(scan.majority_in(hits, share, inc)) == enough(share, inc)
        assert rows(valuetree.majority_in(values_tree, bounds, share, inc)) == enough(share, inc)
    modes = sorted(((q, k + 1, w, c) for q, f in freq.items() for k, (w, c) in enumerate(sorted(f.items(), key=lambda e: (-e[1], e[0]))[:2])), key=repr)
    assert rows(scan.topk_frequent(hits, 2)) == modes == rows(valuetree.topk_frequent(values_tree, index, bounds, 2, closest=16))
    ks = rects.select("qid", F.explode(F.array(*(F.lit(k).cast("long") for k in (0, 1, 3, 40, 10_000)))).alias("k"))
    kth = sorted(((q, k, sorted(w for *_, w in p)[k - 1] if 1 <= k <= len(p) else None) for q, p in held.items() for k in (0, 1, 3, 40, 10_000)), key=repr)
    assert rows(scan.kth_in(hits, ks)) == kth == rows(valuetree.kth_in(values_tree, bounds, ks))
    near = lambda q, strict: (min((w for *_, w in held[q] if w > 1 or (w == 1 and not strict)), default=None), max((w for *_, w in held[q] if w < 1 or (w == 1 and not strict)), default=None))
    for strict in (False, True):
        want = sorted(((q, *near(q, strict)) for q in held), key=repr)
        assert rows(scan.neighbours(hits, rects, 1, strict)) == want == rows(valuetree.neighbours(values_tree, bounds, 1, strict))
    want = sorted(((q, sum(-1 <= w <= 2 for *_, w in p)) for q, p in held.items()), key=repr)
    assert rows(valuetree.count_values(values_tree, bounds, -1, 2)) == want == rows(scan.count_values(hits, rects, -1, 2))
    closed = cut(rects.where("x0 is not null and x1 is not null and y0 is not null and y1 is not null"))
    sums = sorted(((q, len(p), sum(w for *_, w in p) if p else None) for q, p in held.items() if None not in next(r for r in wanted if r[0] == q)), key=repr)
    assert rows(cellcube.sums_in(df, closed, 5)) == sums


def test_whole_cover_is_disjoint_and_small(spark):
    points, wanted = random_grid(9, 800, 300, 5)
    index = point_index.build(table(spark, points), 2, 64)
    tree, bounds = index.tree, index.bounds(rect_table(spark, wanted))
    whole, ends = ytree.cover(tree, bounds)
    for b in bounds.collect():
        ranks: list[int] = []
        for r in whole.where(F.col("qid") == b.qid).collect():
            low = tree.leaf_bits + (tree.depth - r.lvl) * tree.bits
            ranks += range(r.node << low, min((r.node + 1) << low, tree.n))
        assert len(ranks) == len(set(ranks)) and all(b.ylo <= y < b.yhi for y in ranks)
        assert ends.where(F.col("qid") == b.qid).count() <= 2
    per_level = whole.groupBy("qid", "lvl").count().agg(F.max("count")).first()[0]
    assert per_level <= 2 * (1 << tree.bits)


@pytest.mark.parametrize("off", [0, 1, 63, 64, 65, 128, 150])
def test_counting_in_planes(spark, off):
    rnd = random.Random(off)
    digits = [rnd.randrange(8) for _ in range(150)]
    df = spark.createDataFrame([(digits,)], "digits array<bigint>").select(bit_sql.packed("digits", 3).alias("planes")).crossJoin(spark.range(8).toDF("d")).withColumn("off", F.lit(off).cast("long"))
    got = {r.d: (r.n, r.third) for r in df.select("d", F.expr(bit_sql.rank("planes", 3, "d", "off")).alias("n"), F.expr(bit_sql.select("planes", 3, "d", "3", "150")).alias("third")).collect()}
    where = lambda d: [i for i, x in enumerate(digits) if x == d]
    assert got == {d: (digits[:off].count(d), where(d)[2] if len(where(d)) > 2 else None) for d in range(8)}


def test_changes_against_a_rebuilt_grid(spark):
    rnd = random.Random(4)
    state = {k: (rnd.randrange(20), rnd.randrange(20), rnd.randrange(9)) for k in range(200)}
    base = spark.createDataFrame([(k, *v) for k, v in state.items()], "pid long, x long, y long, w long")
    log = []
    for seq in range(150):
        op, pid = rnd.choice(["insert", "delete", "set"]), rnd.randrange(260)
        if op == "insert" or (op == "set" and pid not in state):
            state[pid] = (rnd.randrange(20), rnd.randrange(20), rnd.randrange(9))
            log.append((seq, "insert", pid, *state[pid]))
        elif op == "delete":
            state.pop(pid, None)
            log.append((seq, op, pid, None, None, None))
        else:
            state[pid] = (*state[pid][:2], rnd.randrange(9))
            log.append((seq, op, pid, *state[pid]))
    changes = spark.createDataFrame(log + log[20:60], "seq long, op string, pid long, x long, y long, w long")
    assert rows(dynamic.alive(base, changes)) == sorted(((k, *v) for k, v in state.items()), key=repr)
    assert rows(dynamic.alive(base, dynamic.compacted(changes))) == rows(dynamic.alive(base, changes))
    rects = rect_table(spark, [(1, 3, 11, 2, 15), (2, 0, 20, 0, 20), (3, 30, 40, 0, 1)])
    before = scan.moments_in(points_in(base, rects), rects).select("qid", "cnt", "s")
    got = dynamic.corrected_sums(before, points_in(dynamic.signed(base, changes), rects))
    want = scan.moments_in(points_in(dynamic.alive(base, changes).drop("pid"), rects), rects).select("qid", "cnt", "s")
    assert rows(got) == rows(want)
    assert rows(dynamic.alive(base, changes, -1)) == rows(base)


def test_compaction_tiers():
    assert dynamic.tiers([1000, 10, 10, 10]) == [[1000], [10, 10, 10]] and dynamic.tiers([4, 4, 4]) == [[4, 4, 4]] and dynamic.tiers([]) == []


def test_grids_refuse_what_has_no_place(spark):
    df = spark.createDataFrame([(1.0, -0.0), (float("nan"), 1.0), (None, 2.0)], "a double, b double")
    got = grids.normalised(df, F.col("a"), F.col("b"), F.lit(1)).collect()
    assert [(r.x, str(r.y)) for r in got] == [(1.0, "0.0")]
    assert rect_source.spread(spark, 30, (0, 1000), (0, 1000)).where("x0 > x1 or y0 > y1").count() == 0


def test_costs(spark):
    p = cost.Size(n=1 << 20, kinds=1 << 10, top=1 << 10, universe=1 << 30)
    found = {(m, k): (steps, bits) for m, k, steps, bits in cost.bounds(p)}
    assert found["count", "static"] == (20.0, 20.0 * (1 << 20))
    more = {(m, k): bits for m, k, _, bits in cost.bounds(cost.Size(1 << 20, 1 << 10, 1 << 10, 1 << 30, t=4))}
    assert more["moments", "static"] < found["moments", "static"][1]
    assert cost.least_bits(1, 4) == pytest.approx(4.0) and cost.choose(None, 10) == "scan"
    points, _ = random_grid(3, 600, 50, 5)
    tree = ytree.build(cut(rank_space(table(spark, points))), 2, 64, extrema=False)
    assert cost.choose(tree, 1, "index") == "index" and cost.choose(tree, 10**6) == "scan"
    for r in cost.space_report(tree).where("component = 'planes'").collect():
        assert r.bound <= r.bits <= r.bound * 1.5 + 64 * 40


def test_plan_broadcasts_the_rectangles_and_pushes_their_box(spark, capsys):
    """Of grid L at a size where points would not fit a broadcast by themselves."""
    rects = rect_source.rects(spark, "L").where("qid in (1, 6)")
    found = scan.count_in(grids.hits(spark, "/root/testdata/sf0.1", "L", rects), rects)
    found.collect()
    found.explain("formatted")
    text = capsys.readouterr().out
    assert "NestedLoop" not in text and "CartesianProduct" not in text and "SortMergeJoin" not in text.split("== Initial Plan ==")[0]
    pushed = next(x for x in text.split("PushedFilters: ")[1:] if "l_extendedprice" in x).split("\n")[0]
    assert "GreaterThanOrEqual(l_extendedprice" in pushed and "LessThanOrEqual(l_quantity" in pushed
    assert "l_partkey" not in text
    build = next(x for x in text.split("BroadcastExchange")[1:] if "_cell" in x)
    assert "l_quantity" not in build.split("BroadcastHashJoin")[0].split("\n")[1]


def test_large_batches_are_not_broadcast(spark, monkeypatch):
    monkeypatch.setattr("planegrid.operators.rangejoin.MOST_BROADCAST", 10)
    points, wanted = random_grid(5, 200, 9, 5)
    df, rects = table(spark, points), rect_table(spark, wanted)
    assert rows(scan.count_in(points_in(df, rects), rects)) == sorted(((r[0], len(inside(points, r))) for r in wanted), key=repr)


def test_blocks_in_several_chunks(spark, monkeypatch):
    """Chunks that no question asks for aren't read, and larger batches than are held on the driver go through files."""
    monkeypatch.setattr("planegrid.operators.blocks.SPAN", 2)
    monkeypatch.setattr("planegrid.plans.storage.MOST_HELD", 5)
    points, wanted = random_grid(7, 900, 200, 5)
    index = point_index.build(table(spark, points), 2, 64)
    rects = rect_table(spark, wanted)
    assert max(x.chunks for x in index.tree.levels) > 3
    assert rows(ytree.count_in(index.tree, index.bounds(rects))) == sorted(((r[0], len(inside(points, r))) for r in wanted), key=repr)
    asked = index.bounds(rects.where("qid = 52"))
    plan = index.tree.levels[0].meet(asked.withColumn("_at", F.lit(3).cast("long")), "_at", ["planes"])
    assert plan.count() == 1 and "PartitionFilters: [isnotnull(chunk" in plan._jdf.queryExecution().executedPlan().toString() or "chunk" in plan._jdf.queryExecution().toString()


def test_nodes_too_large_for_one_task(spark, monkeypatch):
    """The build by global order gives the same blocks as the one by node."""
    points, wanted = random_grid(8, 700, 60, 9)
    ranked = cut(rank_space(table(spark, points)))
    order = ["gblk"]
    small = ytree.build(ranked, 2, 64)
    monkeypatch.setattr(ytree, "ALONE", 3)
    large = ytree.build(ranked, 2, 64)
    for a, b in zip(small.levels + small.dyads, large.levels + large.dyads):
        assert rows(a.rows.orderBy(*order)) == rows(b.rows.orderBy(*order))


def test_a_shared_folder_is_needed_on_a_cluster(spark):
    from types import SimpleNamespace

    from planegrid.plans import storage

    there = SimpleNamespace(sparkContext=SimpleNamespace(getCheckpointDir=lambda: None, master="spark://host:7077"), conf=SimpleNamespace(get=lambda *a: None))
    with pytest.raises(RuntimeError, match="spark.checkpoint.dir"):
        storage.folder(there)
