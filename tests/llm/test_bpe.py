import base64
import hashlib
import random

import pytest
import regex
import tiktoken
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from planegrid.llm import bpe, runtime
from planegrid.llm.registry import op1_byte_bpe
from tests.conftest import SF

PATH = runtime.public_file("byte_bpe_multi_50k.tiktoken")
PATTERN = runtime.split_pattern()
RANKS = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(PATH, "rb"))}
KNOWN = tiktoken.Encoding("own", pat_str=PATTERN, mergeable_ranks=RANKS, special_tokens={})
OURS = bpe.ByteVocabulary(RANKS)


def merged(ranks, piece):
    """Repeated lowest-rank merges."""
    parts = [piece[i : i + 1] for i in range(len(piece))]
    while True:
        pairs = [(ranks[a + b], i) for i, (a, b) in enumerate(zip(parts, parts[1:])) if a + b in ranks]
        if not pairs:
            return [ranks[p] for p in parts]
        _, i = min(pairs)
        parts[i : i + 2] = [parts[i] + parts[i + 1]]


@settings(max_examples=300, deadline=None)
@given(st.text(alphabet="aeinorst é", max_size=60))
def test_pieces_like_merges(text):
    assert OURS.encode_piece(text.encode()) == merged(RANKS, text.encode())


@settings(max_examples=200, deadline=None)
@given(st.lists(st.integers(0, 2**32), min_size=3, max_size=12), st.text(alphabet="ab", max_size=30))
def test_small_vocabularies_like_merges(seeds, text):
    """Vocabularies grown by random merges, so that all kinds of overlap occur."""
    ranks = {bytes([i]): i for i in range(256)}
    have = [b"a", b"b"]
    for s in seeds:
        new = have[s % len(have)] + have[s // 7 % len(have)]
        if new not in ranks and merged(ranks, new)[1:] and len(merged(ranks, new)) == 2:
            ranks[new] = len(ranks)
            have.append(new)
    assert bpe.ByteVocabulary(ranks).encode_piece(text.encode()) == (merged(ranks, text.encode()) if text else [])


def test_long_pieces():
    rnd = random.Random(3)
    for text in ("a" * 100_000, "".join(rnd.choices("aeinorst", k=20_000))):
        assert OURS.encode_piece(text.encode()) == KNOWN.encode_ordinary(text)


def test_whole_table_against_the_library(spark):
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    got = op1_byte_bpe(spark, SF).collect()
    assert len(got) == len(texts)
    for r in got:
        ids = KNOWN.encode_ordinary(texts[r.doc_id])
        assert r.n_tokens == len(ids) and r.ids_sha256 == hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest()
        assert r.decoded_sha256 == hashlib.sha256(texts[r.doc_id].encode()).hexdigest()


def test_odd_rows(spark):
    rows = [(1, None), (1, ""), (None, "a b"), (2, " \n\n é 日本 😀"), (2, " \n\n é 日本 😀"), (3, "x " * 100_000)]
    df = spark.createDataFrame(rows, "doc_id long, text string").select("*", F.lit(1).alias("ids"), F.lit(2).alias("decoded"))
    ids = bpe.encode(df, PATH, PATTERN)
    key = lambda r: (r[0] or 0, len(r[1]), r[1])
    assert sorted(((r.doc_id, r.ids) for r in ids.collect()), key=key) == sorted(((k, KNOWN.encode_ordinary(t or "")) for k, t in rows), key=key)
    back = bpe.decode(ids, PATH).collect()
    assert sorted((repr(r.doc_id), bytes(r.decoded)) for r in back) == sorted((repr(k), (t or "").encode()) for k, t in rows)
    assert bpe.decode(bpe.encode(df.limit(0), PATH, PATTERN), PATH).count() == 0
    with pytest.raises(Exception, match="not in the vocabulary"):
        bpe.decode(spark.createDataFrame([(1, [10**6])], "doc_id long, ids array<int>"), PATH).collect()
    assert regex.findall(PATTERN, "a b") == ["a", " b"]
