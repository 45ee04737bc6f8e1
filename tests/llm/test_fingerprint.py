import hashlib
import math
import struct
from collections import Counter

import pytest
import xxhash
from pyspark.sql import functions as F

from planegrid.llm import fingerprint
from planegrid.llm.registry import op2_fingerprint
from tests.conftest import SF


def signed(h):
    return h - (1 << 64) if h >> 63 else h


def of_long(value, seed):
    return xxhash.xxh64_intdigest(struct.pack("<q", value), seed)


def brute(text, n_lanes=fingerprint.LANES):
    """The samples by their definition."""
    weights = Counter(w for w in __import__("re").findall(r"[^\x20\x09-\x0D]+", text or ""))
    out = []
    terms = {signed(xxhash.xxh64_intdigest(w.encode(), 42)) & -2: n for w, n in weights.items()}
    for lane in range(n_lanes):
        best = None
        for term, n in terms.items():
            one, two = (of_long(term ^ fingerprint._MARKS[2 * lane + k], 42) for k in range(2))
            u = [((h >> 21 * k & (1 << 21) - 1) + 0.5) / (1 << 21) for h, k in ((one, 0), (one, 1), (one, 2), (two, 0), (two, 1))]
            r, c, b = -math.log(u[0] * u[1]), -math.log(u[3] * u[4]), u[2]
            t = math.floor(math.log(n) / r + b)
            a = math.floor((math.log(c) - r * (t - b) - r + fingerprint.OFFSET) * fingerprint.SCALE)
            value = (a, (term ^ t << 9) & 0xFFFFFFFF)
            best = value if best is None or value < best else best
        out.append(f"{(best[1] if best else (1 << 31) - 1) ^ 1 << 31:08x}")
    return "".join(out)


@pytest.fixture(scope="module")
def rows(spark):
    return {r.doc_id: r for r in op2_fingerprint(spark, SF).collect()}


@pytest.fixture(scope="module")
def texts(spark):
    return {r.doc_id: r.text for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}


def test_samples_against_their_definition(rows, texts):
    differ = 0
    for doc_id in texts:
        want, got = brute(texts[doc_id]), rows[doc_id].fingerprint
        differ += sum(want[k : k + 8] != got[k : k + 8] for k in range(0, len(want), 8))
    assert differ <= len(texts) * fingerprint.LANES / 1000  # a rounded logarithm may differ


def test_edited_texts_and_likeness(rows, texts):
    def jaccard(a, b):
        a, b = Counter(a.split()), Counter(b.split())
        return sum((a & b).values()) / max(1, sum((a | b).values()))

    ids = sorted(texts)
    off = []
    for k, doc_id in enumerate(ids):
        text, after, r = texts[doc_id], texts[ids[(k + 1) % len(ids)]], rows[doc_id]
        half = len(text) // 2
        edited = text[: len(text) - half] + after[:half]
        assert r.n_chars == len(text) and r.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        off += [r.near_edited - jaccard(text, edited), r.near_next - jaccard(text, after)]
    assert abs(sum(off) / len(off)) < 0.03 and max(map(abs, off)) < 5 * 0.5 / math.sqrt(fingerprint.LANES)


def test_odd_rows(spark):
    long = " ".join(f"w{k % 5000}" for k in range(60_000))
    data = [(1, "a b"), (1, "a b"), (1, "c"), (None, "x y"), (None, "x y"), (2, None), (3, ""), (4, long), (5, "é😀")]
    df = spark.createDataFrame(data, "doc_id long, text string").select("*", F.lit(1).alias("k"), F.lit(2).alias("lanes"))
    got = fingerprint.compare_edited(df).collect()
    assert sorted((r.doc_id or 0, r.n_chars) for r in got) == sorted((k or 0, len(t or "")) for k, t in data)
    by = {(r.doc_id, r.n_chars): r for r in got}
    assert by[2, 0].near_next == 1.0 and by[2, 0].fingerprint == by[3, 0].fingerprint and by[1, 3].near_next == by[1, 1].near_next == 0.0
    assert by[None, 3].near_next is None and by[None, 3].edited_sha256 == hashlib.sha256(b"x ").hexdigest()
    assert by[3, 0].near_edited == 1.0 and by[5, 2].edited_sha256 in [hashlib.sha256(x.encode()).hexdigest() for x in ("éa", "éc")]
    same = fingerprint.fingerprints(df).collect()
    assert len(same) == len(data) and len({r.fingerprint for r in same}) == 6
    assert fingerprint.compare_edited(df.limit(0)).count() == 0 and fingerprint.fingerprints(df.limit(0)).count() == 0
