import math
import re
from collections import Counter

import numpy as np
from pyspark.sql import functions as F

from planegrid.llm import quality
from planegrid.llm.registry import op4_quality_rules

WORD = re.compile(r"[^\x20\x09-\x0D]+")
FLOOR = np.array(list(quality.FEATURES.values()), dtype=float)


def counts(text):
    text = text or ""
    words = WORD.findall(text)
    lines = [x for x in text.split("\n") if WORD.search(x)]
    grams = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
    found = Counter(grams)
    covered = {i + k for i, g in enumerate(grams) if found[g] > 1 for k in range(3)}
    return words, len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", text)), len(lines) - len(set(lines)), len(covered), len(lines), len(re.findall("[A-Z]", text))


def rounded(x):
    return math.floor(x * 1000 + 0.5)


def features(text):
    _, n, chars, symbols, dup, repeat, lines, capitals = counts(text)
    root = lambda a, b: rounded(math.sqrt(a / max(b, 1)))
    return [rounded(math.log(max(chars, 1) / max(n, 1))), root(symbols, n), root(capitals, chars), root(dup, lines), root(repeat, n)]


def fit(x, inflate):
    c = x.mean(axis=0)
    return c, ((x[:, :, None] * x[:, None, :]).mean(axis=0) - np.outer(c, c)) * inflate + np.diag(FLOOR**2)


def far(x, estimate):
    y = x - estimate[0]
    return np.sqrt((y * np.linalg.solve(estimate[1], y.T).T).sum(axis=1))


def mcd(x):
    """Of three starts, each improved until its determinant stops falling, the one that ends at the least."""
    c = np.median(x, axis=0)
    dev = np.sqrt((1.4826 * np.median(abs(x - c), axis=0)) ** 2 + FLOOR**2)
    ends = []
    for now in ((c, np.diag(dev**2)), fit(x, 1.0), fit(np.floor(np.clip(x, c - 2 * dev, c + 2 * dev) + 0.5), 1.0)):
        least = math.inf
        while True:
            d = np.floor(np.minimum(far(x, now), 200) * 100 + 1e-9)
            new = fit(x[d <= np.quantile(d, quality.SHARE)], quality.SHARE / quality._chi2_below(quality.chi2_point(quality.SHARE, 5), 7))
            det = np.linalg.slogdet(new[1])[1]
            if det >= least - quality.SETTLED:
                break
            least, now = det, new
        ends.append((least, now))
    now = min(ends, key=lambda e: e[0])[1]
    near = far(x, now) ** 2 <= quality.chi2_point(0.975, 5)
    return fit(x[near], 0.975 / quality._chi2_below(quality.chi2_point(0.975, 5), 7))


def test_chi_square_points():
    for share, df, known in ((0.95, 1, 3.841459), (0.975, 5, 12.832502), (0.99, 10, 23.209251)):
        assert abs(quality.chi2_point(share, df) - known) < 1e-5


def test_whole_table_against_numpy(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").collect()
    got = {r.doc_id: r for r in op4_quality_rules(spark, "/root/testdata/sf0.01").collect()}
    assert len(got) == len(docs)
    x, passed = {}, []
    for r in docs:
        _, n, chars, symbols, dup, repeat, _, _ = counts(r.text)
        g = got[r.doc_id]
        assert (g.n_words, g.word_chars, g.n_symbols, g.n_dup_lines, g.n_repeat_words) == (n, chars, symbols, dup, repeat)
        assert g.base_failed == (n < 50 or 100 * repeat > 50 * n)
        x[r.doc_id] = features(r.text)
        if not g.base_failed:
            passed.append(r)
    estimate = {}
    for key in {(r.lang, r.source) for r in passed} | {(r.lang,) for r in passed} | {()}:
        group = np.array([x[r.doc_id] for r in passed if (r.lang, r.source)[: len(key)] == key], dtype=float)
        if len(group) >= quality.ENOUGH or not key:
            estimate[key] = mcd(group)
    cut, off = math.sqrt(quality.chi2_point(1 - quality.TAIL, 5)), 0
    for r in passed:
        use = next(estimate[k] for k in ((r.lang, r.source), (r.lang,), ()) if k in estimate)
        d = float(far(np.array([x[r.doc_id]], dtype=float), use)[0])
        assert abs(d - got[r.doc_id].distance) < 0.02 * (1 + d)
        off += got[r.doc_id].kept != (d <= cut)
    assert off <= 1


def test_labels(spark):
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    rows = op4_quality_rules(spark, "/root/testdata/sf0.01").join(labels, "doc_id").where("not base_failed").collect()
    good, bad = [r for r in rows if r.quality], [r for r in rows if not r.quality]
    assert all(r.kept for r in good) and sum(r.kept for r in bad) <= 0.1 * len(bad)


def test_odd_rows(spark):
    rows = [(1, None, None, None), (2, "", "en", None), (None, "a b " * 100, None, "x"), (3, "x" * 300_000, "en", "x"), (4, "w1 w2 w3\n" * 30, "en", "x")]
    rows += [(5, " ".join(f"w{k}" for k in range(20_000)), "en", "x")] * 2
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string").select("*", F.lit("z").alias("n_words"), F.lit(1).alias("kept"))
    got = quality.rate(df).collect()
    assert sorted((r.doc_id or 0, r.n_words, r.n_dup_lines, r.n_repeat_words, r.base_failed) for r in got) == sorted((r[0] or 0, counts(r[1])[1], counts(r[1])[4], counts(r[1])[5], r[0] != 5) for r in rows)
    assert all(r.kept for r in got if r.doc_id == 5)
    kept = quality.keep_good(df)
    assert kept.columns == df.columns and [r.doc_id for r in kept.collect()] == [5, 5]
    assert quality.rate(df.limit(0)).count() == 0 and quality.keep_good(df.limit(0)).count() == 0


def test_groups_with_nulls_have_estimates_of_their_own(spark):
    """Rows without a source, or without language and source, neither join nor count again in the wider groups."""
    rows = []
    for k, (lang, source) in enumerate((("en", None), ("en", "x"), (None, None), (None, "x"))):
        rows += [(1000 * k + j, " ".join(f"{'abcdefghij'[: 2 + 2 * k]}{j * m % 997}" for m in range(80 + j)), lang, source) for j in range(1, 110)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")
    stats = quality.statistics(df).cache()
    keys = {(r.lang, r.source): (r._group, r._wide) for r in stats.select("lang", "source", "_group", "_wide").distinct().collect()}
    assert len({g for g, _ in keys.values()}) == 4 and len({w for _, w in keys.values()}) == 2 and not {g for g, _ in keys.values()} & {w for _, w in keys.values()}
    use = {r._group: r for r in quality.estimates(stats).collect()}
    for (lang, source), (group, _) in keys.items():
        x = np.array([features(t) for _, t, a, b in rows if (a, b) == (lang, source) and 2 * counts(t)[5] <= counts(t)[1]], dtype=float)
        assert len(x) >= quality.ENOUGH
        assert np.allclose([use[group][c] for c in quality._CENTER], mcd(x)[0], atol=1e-6)


def test_symbols_reject_alone():
    """35 symbols in 100 words are too many if clean texts have none and no scatter."""
    assert math.sqrt(quality.chi2_point(1 - quality.TAIL, 5)) * quality.FEATURES["symbols"] < 1000 * math.sqrt(0.35)
