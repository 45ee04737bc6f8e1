import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from planegrid.llm import lmscore, runtime, token_count
from planegrid.llm.registry import op8_token_count
from tests.conftest import SF
from tests.llm import brute

PATH = runtime.public_file("piece_bpe_32k.model")


def alone(counter, word):
    """One pre-token's count, nothing shared."""
    text = "▁" + word
    best = [(0.0, 0)] + [None] * len(text)
    for end in range(1, len(text) + 1):
        options = [(best[s][0] + counter.scores[text[s:end]], best[s][1] - 1) for s in range(end) if text[s:end] in counter.scores]
        if text[end - 1] not in counter.scores:
            spelled = text[end - 1].encode()
            options.append((best[end - 1][0] + sum(counter.byte_scores[b] for b in spelled), best[end - 1][1] - len(spelled)))
        best[end] = max(options)
    return -best[-1][1]


@settings(max_examples=200, deadline=None)
@given(st.dictionaries(st.text("ab▁", min_size=1, max_size=4), st.floats(-9, -0.1)), st.sets(st.text("abc", max_size=9)))
def test_shared_prefixes_change_nothing(scores, words):
    trie = token_count.PrefixTrie(scores, [-5.0] * 256)
    assert {w: trie.count("▁" + w) for w in words} == {w: alone(trie, w) for w in words}
    assert trie.nodes == 1 + len({("▁" + w)[: k + 1] for w in words for k in range(len(w) + 1)})


def test_whole_table(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    counter = token_count.PrefixTrie.from_model(open(PATH, "rb").read(), lmscore.learned_scores(docs, PATH))
    texts = {r.doc_id: brute.words(r.text) for r in docs.collect()}
    known = {w: alone(counter, w) for ws in texts.values() for w in ws}
    got = op8_token_count(spark, SF).collect()
    assert {r.doc_id: (r.n_pretokens, r.n_tokens) for r in got} == {k: (len(ws), sum(known[w] for w in ws)) for k, ws in texts.items()}


def test_odd_rows(spark, monkeypatch):
    rows = [(1, None), (1, ""), (None, "a  b\n"), (2, "日本😀 the"), (2, "日本😀 the"), (3, "ab" * 5_000)]
    df = spark.createDataFrame(rows, "doc_id long, text string").select("*", F.lit(1).alias("n_tokens"))
    log_p = -np.log(np.arange(32_000) + 2.0)
    counter = token_count.PrefixTrie.from_model(open(PATH, "rb").read(), log_p)
    want = sorted((repr(k), len(brute.words(t)), sum(alone(counter, w) for w in brute.words(t))) for k, t in rows)
    assert sorted((repr(r.doc_id), r.n_pretokens, r.n_tokens) for r in token_count.count(df, PATH, log_p).collect()) == want
    assert token_count.count(df.limit(0), PATH, log_p).count() == 0
    monkeypatch.setattr(token_count, "MOST_NODES", 2)
    monkeypatch.setattr(counter.terminals, "most", 300)
    assert counter.counts([[b"a", b"b"], [b"c", b"the"], []]) == [alone(counter, "a") + alone(counter, "b"), alone(counter, "c") + alone(counter, "the"), 0]
