import random

import pytest
from pyspark.sql import functions as F

from planegrid.llm import substrings
from tests.conftest import SF
from tests.llm import brute


def spans(flags):
    out = []
    for i, x in enumerate(flags):
        if x and out and out[-1][1] == i:
            out[-1][1] = i + 1
        elif x:
            out.append([i, i + 1])
    return [tuple(x) for x in out]


def want(rows, size):
    return sorted(((k is None, k, len(w), sum(g), spans(g), " ".join(x for x, y in zip(w, g) if not y)) for k, w, g in brute.removed(rows, size)), key=repr)


def got(df, size):
    return sorted(((r.doc_id is None, r.doc_id, r.n_words, r.n_removed, [tuple(x) for x in r.removed], r.kept) for r in substrings.remove_repeats(df, size).collect()), key=repr)


def test_whole_table(spark):
    df = spark.read.parquet(f"{SF}/documents.parquet")
    assert got(df, 50) == want([(r.doc_id, r.text) for r in df.collect()], 50)


@pytest.mark.parametrize("size", [1, 2, 3, 8])
def test_random_texts_with_few_words(spark, size):
    rnd = random.Random(size)
    rows = [(rnd.choice([None, *range(12)]), rnd.choice([" ", "\n", "\t "]).join(rnd.choices("abé😀d", k=rnd.randrange(40)))) for _ in range(40)]
    rows += [(50, None), (51, ""), (52, " \n "), (53, "q " * 3000), (54, "q " * 3000), (54, "a b c d"), (None, "q " * 3000)]
    df = spark.createDataFrame(rows, "doc_id long, text string").select("*", F.lit(1).alias("kept"), F.lit(2).alias("copy"), F.lit(3).alias("spots"))
    assert got(df, size) == want(rows, size)
    back = substrings.without_repeats(df, size)
    assert back.columns == df.columns
    texts = [" ".join(x for x, y in zip(w, g) if not y) if any(g) else t for (k, w, g), (_, t) in zip(brute.removed(rows, size), rows)]
    assert sorted((repr(r.doc_id), repr(r.text), r.kept, r.copy, r.spots) for r in back.collect()) == sorted((repr(k), repr(t), 1, 2, 3) for (k, _), t in zip(rows, texts))


def test_empty_table(spark):
    df = spark.read.parquet(f"{SF}/documents.parquet").limit(0)
    assert substrings.remove_repeats(df).count() == 0 and substrings.without_repeats(df).count() == 0


def test_sequences_on_which_polynomial_hashes_agree(spark):
    """Texts without a common window, though words follow a Thue-Morse sequence and its complement, keep all words."""
    signs = [bin(k).count("1") % 2 for k in range(4096)]
    blocks = ["alpha " * 30 + "beta " * 7, "gamma " * 30 + "delta " * 7]
    rows = [(flip, "".join(blocks[x ^ flip].replace("alpha", "a%d" % (k % 3 * 0)) for k, x in enumerate(signs[:256]))) for flip in (0, 1)]
    rows += [(2 + flip, " ".join("xy"[x ^ flip] + "z" * 3 for x in signs)) for flip in (0, 1)]
    rows += [(4 + flip, " ".join("".join("ab"[x ^ flip] for x in signs) + str(k) for k in range(60))) for flip in (0, 1)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    assert got(df, 50) == want(rows, 50)


def test_windows_longer_than_a_polynomial_is_trusted_for(spark):
    words = [f"w{k}" for k in range(700)]
    rows = [(1, " ".join(words)), (2, "x " + " ".join(words[:500])), (3, " ".join(words[400:]))]
    assert got(spark.createDataFrame(rows, "doc_id long, text string"), 300) == want(rows, 300)
