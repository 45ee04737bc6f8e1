import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from planegrid.llm import packing, runtime
from planegrid.llm.registry import packed
from tests.conftest import SF


def brute(rows):
    t = Tokenizer.from_file(runtime.public_file("byte_bpe_50k.json"))
    t.encode_special_tokens = True
    out = []
    for doc_id, text in rows:
        ids = np.array([*t.encode(text or "", add_special_tokens=False).ids, 1], dtype="<u4")
        at = 0
        for n in packing.piece_lengths(len(ids)):
            out.append((doc_id, at, n, zlib.crc32(ids[at : at + n].tobytes()), len(ids)))
            at += n
        assert at == len(ids)
    return sorted(out, key=repr)


@pytest.mark.parametrize("total", [1, 2, 3, 2047, 2048, 2049, 10_000])
def test_lengths_are_powers_of_two(total):
    lengths = packing.piece_lengths(total)
    assert sum(lengths) == total and all(n & (n - 1) == 0 and n <= 2048 for n in lengths)


def test_whole_table_against_the_tokenizers_library(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    got = packed(docs).collect()
    assert sorted(((r.doc_id, r.start, r.length, r.ids_crc32, r.doc_tokens) for r in got), key=repr) == brute((r.doc_id, r.text) for r in docs.collect())
    assert len({r.sequence_id for r in got}) == len(got) and {r.offset for r in got} == {0}
    by = sorted(got, key=lambda r: r.sequence_id)
    assert [r.length for r in by] == sorted((r.length for r in got), reverse=True)


def test_odd_rows(spark):
    rows = [(1, None), (2, ""), (2, ""), (None, "a b"), (3, "x" * 200_000), (4, "<|endoftext|> \n\n  é 日本 😀"), (5, " " * 30_000 + "x")]
    df = spark.createDataFrame(rows, "doc_id long, text string").select("*", F.lit(7).alias("start"), F.lit(8).alias("ids"))
    got = packing.pack(packing.pieces(df, runtime.public_file("byte_bpe_50k.json"), runtime.split_pattern(), 1)).collect()
    assert sorted(((r.doc_id, r.start, r.length, r.ids_crc32, r.doc_tokens) for r in got), key=repr) == brute(rows)
    assert all(len(r.ids) == r.length for r in got)
    assert packed(df.limit(0)).count() == 0
