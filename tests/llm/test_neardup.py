import random

import pytest
from pyspark.sql import functions as F

from planegrid.llm import neardup
from planegrid.llm.components import components, of_few
from tests.llm import brute


def got(df, percent):
    return sorted(tuple(r) for r in neardup.near_duplicates(df, percent=percent).select("doc_id", "n_shingles", "component_id", "kept").collect())


@pytest.mark.parametrize("percent", [80, 85])
def test_whole_table(spark, percent):
    df = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    assert got(df, percent) == sorted(brute.near_duplicates([(r.doc_id, r.text) for r in df.collect()], percent))


def test_large_group_of_near_copies(spark):
    """Copies of one text, each with other small edits, in chains and at all distances, among unrelated texts."""
    rnd = random.Random(5)
    base = [f"w{rnd.randrange(10_000)}" for _ in range(400)]
    rows, words = [], base
    for k in range(700):
        words = list(words if k % 7 else base)
        for _ in range(rnd.randrange(6)):
            words[rnd.randrange(len(words))] = f"x{rnd.randrange(10_000)}"
        rows.append((k, " ".join(words)))
    rows += [(1000 + k, " ".join(f"y{rnd.randrange(300)}" for _ in range(rnd.randrange(3, 60)))) for k in range(300)]
    assert got(spark.createDataFrame(rows, "doc_id long, text string"), 85) == sorted(brute.near_duplicates(rows, 85))


def test_hub_in_the_middle_of_its_copies(spark):
    """Copies link to the original only, which stands in the middle of the ids."""
    rnd = random.Random(11)
    base = [f"w{k}" for k in range(400)]
    rows = []
    for k in range(1000):
        words = list(base)
        for at in rnd.sample(range(400), 5) if k != 500 else ():
            words[at] = f"x{k}_{at}"
        rows.append((k, " ".join(words)))
    want = sorted(brute.near_duplicates(rows, 85))
    assert sum(not r[3] for r in want) > 900
    assert got(spark.createDataFrame(rows, "doc_id long, text string"), 85) == want


def test_blocks_of_a_crowded_family(spark, monkeypatch):
    """Regions and families over many blocks, one component much larger than the others."""
    monkeypatch.setattr(neardup, "BLOCK_ROWS", 16)
    rnd = random.Random(12)
    base = [f"w{k}" for k in range(200)]
    rows = []
    for k in range(240):
        words = list(base)
        for at in rnd.sample(range(200), rnd.choice((0, 1, 1, 4, 5, 5, 6))):
            words[at] = f"x{k}_{at}"
        rows.append((k, " ".join(words)))
    assert got(spark.createDataFrame(rows, "doc_id long, text string"), 85) == sorted(brute.near_duplicates(rows, 85))


def test_odd_rows(spark):
    rows = [(1, None), (2, ""), (3, " \n"), (4, "A b c"), (5, "a B\tc"), (6, "a b c d e"), (9, "x" * 100_000), (8, "x" * 100_000)]
    df = spark.createDataFrame(rows, "doc_id long, text string").select("*", F.lit(1).alias("d"), F.lit(2).alias("labels"))
    assert got(df, 80) == sorted(brute.near_duplicates(rows, 80))
    again = spark.createDataFrame([(4, "a b c"), (4, "a b c"), (None, "a b c"), (7, "A B C")], "doc_id long, text string")
    assert sorted(tuple(r)[:4] for r in neardup.near_duplicates(again).collect() if r.doc_id) == [(4, 1, 4, True), (4, 1, 4, True), (7, 1, 4, False)]
    assert [tuple(r)[:4] for r in neardup.near_duplicates(again).collect() if r.doc_id is None] == [(None, 1, None, True)]
    assert neardup.near_duplicates(df.limit(0)).count() == 0


def test_components_of_a_path_and_a_star(spark):
    edges = [(k, k + 1) for k in range(100, 160)] + [(5, k) for k in range(10, 50)] + [(49, 51), (51, 3), (7, 7)]
    found = {r.node: r.component for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert found == {k: 100 for k in range(101, 161)} | {k: 3 for k in (5, *range(10, 50), 51)}


def test_components_of_few_edges(spark):
    edges = [(k, k + 1) for k in range(100, 160)] + [(5, k) for k in range(10, 50)] + [(49, 51), (51, 3), (7, 7)]
    df = spark.createDataFrame(edges, "a long, b long")
    assert sorted(map(tuple, of_few(df).collect())) == sorted(map(tuple, of_few(df, 1).collect())) == sorted(map(tuple, components(df).collect()))


def test_rows_of_one_id_are_judged_by_their_own_texts(spark):
    """A text that nothing repeats stays, also if another row of its id is a copy."""
    t, u, v = " ".join(f"t{k}" for k in range(60)), " ".join(f"u{k}" for k in range(60)), " ".join(f"t{k}" for k in range(59))
    rows = [(1, t, 1), (2, t, 2), (2, u, 3), (3, v, 4), (None, u, 5), (4, None, 6), (4, "", 7)]
    df = spark.createDataFrame(rows, "doc_id long, text string, mark int")
    kept = neardup.without_near_duplicates(df)
    assert kept.columns == df.columns and sorted(r.mark for r in kept.collect()) == [1, 3, 5, 6, 7]


def thue_morse(n):
    return [bin(k).count("1") % 2 for k in range(n)]


def test_sequences_on_which_polynomial_hashes_agree(spark):
    """Neither words nor texts whose symbols follow a Thue-Morse sequence and its complement are taken for copies."""
    one = thue_morse(4096)
    texts = ["".join("ab"[x ^ flip] for x in one) for flip in (0, 1)] + ["".join("ab"[x ^ flip] for x in one) + " c d e f g" for flip in (0, 1)]
    got = neardup.near_duplicates(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()
    assert all(r.kept for r in got)
