import importlib
import zlib

import numpy as np
import pytest
from tokenizers import Tokenizer

import corpus_pipeline
from planegrid.llm import packing, quality, runtime
from tests.conftest import SF
from tests.llm import brute
from tests.llm.test_secret_scan import brute as secrets


@pytest.fixture(scope="module")
def stages(spark, tmp_path_factory):
    """The rows before and after each stage."""
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    out = [docs]
    for name, stage in corpus_pipeline.STAGES:
        path = str(tmp_path_factory.mktemp(name))
        stage(spark, docs, SF).write.mode("overwrite").parquet(path)
        docs = spark.read.parquet(path)
        out.append(docs)
    return out


def texts(df):
    return {r.doc_id: r.text for r in df.collect()}


def test_columns_stay(stages):
    assert all(s.columns == stages[0].columns for s in stages[:5])
    assert all(r.n_chars == len(r.text) for s in stages[2:5] for r in s.collect())


def test_quality_keeps_what_the_operator_keeps(stages):
    want = {r.doc_id for r in quality.rate(stages[0]).where("kept").collect()}
    assert set(texts(stages[1])) == want and 0 < len(want) < stages[0].count()


def test_near_duplicates_against_all_pairs(stages):
    kept = {k for k, _, _, keep in brute.near_duplicates(list(texts(stages[1]).items()), 80) if keep}
    assert set(texts(stages[2])) == kept


def test_substrings_against_all_windows(stages):
    before = texts(stages[2])
    want = {k: " ".join(x for x, y in zip(w, g) if not y) if any(g) else before[k] for k, w, g in brute.removed(list(before.items()))}
    assert texts(stages[3]) == want


def test_secrets_against_python(stages):
    for k, text in texts(stages[3]).items():
        out, at = "", 0
        for a, _, b, _ in secrets(text)[1]:
            out += text[at:a] + "[SECRET]" if a >= at else ""
            at = max(at, b)
        assert texts_after(stages)[k] == out + text[at:]


def texts_after(stages, memo={}):
    if id(stages) not in memo:
        memo[id(stages)] = texts(stages[4])
    return memo[id(stages)]


def test_packing_and_run(spark, stages):
    t = Tokenizer.from_file(runtime.public_file("byte_bpe_50k.json"))
    t.encode_special_tokens = True
    want = []
    for k, text in texts(stages[4]).items():
        ids, at = np.array([*t.encode(text, add_special_tokens=False).ids, 1], dtype="<u4"), 0
        for n in packing.piece_lengths(len(ids)):
            want.append((k, at, n, zlib.crc32(ids[at : at + n].tobytes())))
            at += n
    found = lambda df: sorted((r.doc_id, r.start, r.length, r.ids_crc32) for r in df.collect())
    assert found(stages[5]) == sorted(want)
    assert found(corpus_pipeline.run(spark, SF)) == sorted(want)


def test_empty_table(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet").limit(0)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, docs, SF).count() == 0


def test_odd_rows(spark):
    import pyspark.sql.functions as F

    good = spark.read.parquet(f"{SF}/documents.parquet").where("length(text) > 600")
    odd = spark.createDataFrame([(None, None, None, None, None), (-1, "", "en", "x", 0), (-1, "", "en", "x", 0), (-2, "w " * 200_000, None, "x", 1)], good.schema)
    docs = good.union(odd).union(good.limit(3)).withColumn("copy", F.lit(1)).withColumn("first", F.lit("x"))
    for k, (name, stage) in enumerate(corpus_pipeline.STAGES):
        got = stage(spark, docs, SF)
        if k < 4:
            assert got.columns == docs.columns and got.count() <= docs.count()
            assert got.count() == docs.count() or k < 2
        else:
            assert got.count() > 0
    assert importlib.import_module("corpus_pipeline").ORACLE_SQL is None
