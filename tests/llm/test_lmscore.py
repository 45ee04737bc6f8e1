import math
import re
import zlib
from collections import Counter

import pytest
import sentencepiece
from pyspark.sql import functions as F

from planegrid.llm import lmscore, runtime
from planegrid.llm.registry import op3_lm_score
from tests.conftest import SF

PATH = runtime.public_file("piece_bpe_32k.model")
MODEL = sentencepiece.SentencePieceProcessor(model_file=PATH)


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text or "")


def words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", lower(text))


def brute(rows):
    """The definition, word by word, with probabilities rather than logarithms for the segmentations."""
    train = [words(t) for k, t in rows if zlib.crc32(("" if k is None else str(k)).encode()) % 5 != 1]
    count = Counter(w for ws in train for w in ws)
    total, kinds = sum(count.values()) + len(train), len(count) + bool(train)
    pieces = Counter()
    for w, c in count.items():
        for i in MODEL.encode(w):
            pieces[i] += c
    size = MODEL.get_piece_size()
    mass = sum(pieces.values()) + 0.5 * size + len(train) + 0.5
    p = {i: (pieces[i] + 0.5) / mass for i in range(size)}
    plain = {MODEL.id_to_piece(i): p[i] for i in range(size) if not (MODEL.is_control(i) or MODEL.is_unknown(i) or MODEL.is_byte(i))}
    byte = {int(MODEL.id_to_piece(i)[3:5], 16): p[i] for i in range(size) if MODEL.is_byte(i)}
    longest = max(map(len, plain))
    base = lambda c: math.log10((c + 0.5) / (total + 0.5 * (kinds + 1)))
    memo = {}

    def marginal(w):
        if w not in memo:
            text = "▁" + w
            to = [1.0] + [0.0] * len(text)
            for k in range(len(text)):
                for n in range(1, min(longest, len(text) - k) + 1):
                    to[k + n] += to[k] * plain.get(text[k : k + n], 0.0)
                if text[k] not in plain:
                    to[k + 1] += to[k] * math.prod(byte[b] for b in text[k].encode())
            memo[w] = math.log10(to[-1])
        return memo[w]

    for k, t in rows:
        ws = words(t)
        held = zlib.crc32(("" if k is None else str(k)).encode()) % 5 == 1
        yield k, held, len(ws) + 1, sum(w in count for w in ws) + bool(train), total, sum(base(count[w]) for w in ws) + base(len(train)), sum(map(marginal, ws)) + math.log10((len(train) + 0.5) / mass)


def same(got, want):
    key = lambda r: tuple((x is not None, x) for x in r[:3]) + (r[6],)
    got, want = sorted(map(tuple, got), key=key), sorted(want, key=key)
    assert len(got) == len(want)
    for a, b in zip(got, want):
        assert a[:5] == b[:5] and a[5] == pytest.approx(b[5], abs=1e-5) and a[6] == pytest.approx(b[6], abs=1e-5)


def test_whole_table_against_the_definition(spark):
    rows = [tuple(r) for r in spark.read.parquet(f"{SF}/documents.parquet").select("doc_id", "text").collect()]
    same(op3_lm_score(spark, SF).collect(), brute(rows))


@pytest.mark.parametrize("head", [0, 3])
def test_odd_rows(spark, monkeypatch, head):
    monkeypatch.setattr(lmscore, "HEAD", head)
    rows = [(1, "The the THE cat"), (1, "The the THE cat"), (1, "other"), (None, "é 日本😀 cat"), (2, None), (3, ""), (4, "ab" * 50), (7, "cat \t\n dog")]
    df = spark.createDataFrame(rows, "doc_id long, text string").select("*", F.lit(1).alias("c"), F.lit(2).alias("word"), F.lit(3).alias("train"))
    same(lmscore.score(df, PATH).collect(), brute(rows))


def test_empty_and_no_training_rows(spark):
    df = spark.createDataFrame([(3, "a b")], "doc_id long, text string")
    assert lmscore.score(df.limit(0), PATH).count() == 0
    held = next(k for k in range(100) if zlib.crc32(str(k).encode()) % 5 == 1)
    rows = [(held, "a b")]
    same(lmscore.score(spark.createDataFrame(rows, "doc_id long, text string"), PATH).collect(), brute(rows))


def test_very_long_word_stays_finite():
    import numpy as np

    lattice = lmscore.Lattice(MODEL, np.log(np.full(MODEL.get_piece_size(), 1 / 32_000)))
    assert -1e6 < lattice.log_marginal("ab" * 50_000) < -1e4
