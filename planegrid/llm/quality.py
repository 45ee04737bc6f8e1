"""Quality rules: plain text statistics, and robust multivariate outliers within each language and source.

Every text gets counts (words, symbols, repeated lines, words in repeated three-word windows) and a vector of
five transformed shares. For each language and source a minimum-covariance-determinant estimate gives a centre
and a scatter that junk does not move: of a fixed share of the rows, those whose scatter has the least determinant.
Three deterministic starts (medians and median deviations; means and scatter of all rows; the same of rows cut off
at two deviations) are each improved by concentration steps, which take the rows nearest by Mahalanobis distance
and fit again, until the determinant stops falling; the start that ends at the least one counts, and a last step
reweights. Every scatter is regularised by a fixed diagonal (as in minimum regularised covariance determinants),
because features that hardly vary would make it singular. A text goes if a base rule fails or its squared distance
is beyond a chi-square cutoff. Groups with too few rows use their language's estimate, then that of all rows. Only
DataFrame expressions are used.

The shares are rounded to thousandths, so sums are exact integers and quantiles come from counts of a bounded
number of values: results do not depend on the order of rows, and hot groups are pre-aggregated.

Rows: null and empty texts have no words and fail the base rules. Null languages or sources form groups of
their own. Repeated rows each count. Columns of the input stay; those with the names of the result are replaced.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import runtime

#: Features, in the order of the vector, each with the least standard deviation that it is given (in thousandths):
#: a feature that is nearly constant in clean texts must not turn small differences into outliers.
FEATURES = {"word_length": 80, "symbols": 95, "capitals": 110, "repeated_lines": 180, "repeated_words": 130}
P = len(FEATURES)
Q = [f"_q{k}" for k in range(P)]
#: Share of rows that a concentration step keeps, rows that a group needs for an estimate of its own.
SHARE, ENOUGH = 0.7, 60
#: A determinant has stopped falling if its logarithm falls by less.
SETTLED = 1e-6
#: Tail probability of the cutoff.
TAIL = 1e-5
#: Groups up to this many are broadcast (about 250 bytes each); more are joined by key.
MOST_BROADCAST = 50_000
COUNTS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")


def _chi2_below(x: float, df: int) -> float:
    """Probability that a chi-square variable is at most x, by the series of the incomplete gamma function."""
    a, h = df / 2, x / 2
    term = total = 1 / a
    for k in range(1, 2000):
        term *= h / (a + k)
        total += term
        if term < total * 1e-16:
            break
    return total * math.exp(-h + a * math.log(h) - math.lgamma(a)) if h > 0 else 0.0


def chi2_point(share: float, df: int) -> float:
    low, high = 0.0, 400.0
    for _ in range(200):
        mid = (low + high) / 2
        low, high = (mid, high) if _chi2_below(mid, df) < share else (low, mid)
    return high


def _let(value: Column, use) -> Column:
    return F.transform(F.array(value), use)[0]


def _repeat_words(words: Column, n: Column) -> Column:
    """Words that lie in a three-word window found twice or more."""
    hashes = F.transform(F.sequence(F.lit(0), n - 3), lambda i: F.xxhash64(words[i], words[i + 1], words[i + 2]))

    def covered(s: Column) -> Column:
        """s: windows as (h, i), sorted; those with an equal neighbour, by place, cover three words each."""
        last = F.size(s) - 1
        twice = F.filter(s, lambda x, k: (x["h"] == s[F.greatest(k - 1, F.lit(0))]["h"]) & (k > 0) | (x["h"] == s[F.least(k + 1, last)]["h"]) & (k < last))
        places = F.sort_array(F.transform(twice, lambda x: x["i"]))
        start = F.struct(F.lit(-3).alias("at"), F.lit(0).alias("n"))
        return F.aggregate(places, start, lambda a, i: F.struct(i.alias("at"), (a["n"] + F.least(F.lit(3), i - a["at"])).alias("n")), lambda a: a["n"])

    def counted(h: Column) -> Column:
        ordered = F.sort_array(F.transform(h, lambda x, i: F.struct(x.alias("h"), i.alias("i"))))
        return F.when(F.size(F.array_distinct(h)) < F.size(h), _let(ordered, covered)).otherwise(F.lit(0))

    return F.when(n >= 3, _let(hashes, counted)).otherwise(F.lit(0))


def statistics(df: DataFrame, text_col: str = "text", lang_col: str = "lang", source_col: str = "source") -> DataFrame:
    """df with COUNTS, base_failed, the rounded features and the group's key."""
    df = df.withColumn("_t", F.coalesce(F.col(text_col).cast("string"), F.lit("")))
    df = df.withColumns({"_w": F.array_remove(F.split("_t", r"[\x20\x09-\x0D]+", -1), ""), "_lines": F.filter(F.split("_t", "\n", -1), lambda x: x.rlike(r"[^\x20\x09-\x0D]"))})
    n = F.size("_w")
    without = lambda pattern: F.char_length("_t") - F.char_length(F.regexp_replace("_t", pattern, ""))
    df = df.withColumns(
        {
            "n_words": n.cast("long"),
            "word_chars": F.char_length(F.array_join("_w", "")).cast("long"),
            "n_symbols": without(r"[#*$%&|<>]").cast("long"),
            "n_dup_lines": (F.size("_lines") - F.size(F.array_distinct("_lines"))).cast("long"),
            "n_repeat_words": _repeat_words(F.col("_w"), n).cast("long"),
            "_capitals": without("[A-Z]"),
            "_n_lines": F.size("_lines"),
        }
    )
    share = lambda a, b: F.round(F.sqrt(F.col(a) / F.greatest(F.col(b), F.lit(1))) * 1000).cast("int")
    features = [
        F.round(F.log(F.greatest(F.col("word_chars"), F.lit(1)) / F.greatest(F.col("n_words"), F.lit(1))) * 1000).cast("int"),
        share("n_symbols", "n_words"),
        share("_capitals", "word_chars"),
        share("n_dup_lines", "_n_lines"),
        share("n_repeat_words", "n_words"),
    ]
    failed = (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))
    # nulls are written out, so that a group with one is not mistaken for a wider group
    key = lambda **columns: F.to_json(F.struct(*(F.col(c).cast("string").alias(name) for name, c in columns.items())), {"ignoreNullFields": "false"})
    group, wide = key(lang=lang_col, source=source_col), key(lang=lang_col)
    return df.withColumns(dict(zip(Q, features)) | {"base_failed": failed, "_group": group, "_wide": wide}).drop("_t", "_w", "_lines", "_capitals", "_n_lines")


_CENTER = [f"_c{i}" for i in range(P)]
#: Lower triangles: of the Cholesky factor of a scatter, and of the scatter's inverse.
_FACTOR = {(i, k): f"_l{i}{k}" for i in range(P) for k in range(i + 1)}
_INVERSE = {(i, k): f"_p{i}{k}" for i, k in _FACTOR}


#: The squared Mahalanobis distance, as one flat sum, so that pushing a filter down doesn't unfold it.
_FAR = " + ".join(f"({Q[i]} - {_CENTER[i]}) * ({Q[k]} - {_CENTER[k]}) * {name} * {1 if i == k else 2}" for (i, k), name in _INVERSE.items())


def _inverted(found: DataFrame) -> DataFrame:
    """found: _CENTER, _FACTOR and other columns. Adds _INVERSE and _det, the logarithm of the determinant; _FACTOR goes."""
    m = {(i, k): f"_m{i}{k}" for i, k in _FACTOR}  # of the factor's inverse, by diagonals
    for gap in range(P):
        each = []
        for i in range(gap, P):
            k = i - gap
            before = " + ".join(f"{_FACTOR[i, j]} * {m[j, k]}" for j in range(k, i))
            each.append(f"{f'-({before})' if before else '1'} / {_FACTOR[i, i]} as {m[i, k]}")
        found = found.selectExpr("*", *each)
    det = " + ".join(f"2 * ln({_FACTOR[i, i]})" for i in range(P))
    inverse = [f"{' + '.join(f'{m[j, i]} * {m[j, k]}' for j in range(i, P))} as {name}" for (i, k), name in _INVERSE.items()]
    return found.selectExpr("*", f"{det} as _det", *inverse).drop(*_FACTOR.values(), *m.values())


def _fitted(sums: DataFrame, inflate: float, groups: int) -> DataFrame:
    """sums: the keys, _n, _rows, _s{i}, _s{i}_{k}; groups: its rows at most. Centre, inverse and determinant of the inflated scatter with its floor."""
    sums = runtime.narrow(sums, groups)  # one row for each group and start
    sums = sums.selectExpr("*", *(f"_s{i} / _n as {_CENTER[i]}" for i in range(P)))
    floors = [x * x for x in FEATURES.values()]

    def rest(i: int, k: int) -> str:
        value = f"(_s{i}_{k} / _n - {_CENTER[i]} * {_CENTER[k]}) * {inflate!r}D"
        value = f"greatest({value}, 0D) + {floors[i]}" if i == k else value
        return value + "".join(f" - {_FACTOR[i, j]} * {_FACTOR[k, j]}" for j in range(k))

    for k in range(P):
        sums = sums.selectExpr("*", f"sqrt(greatest({rest(k, k)}, 1D)) as {_FACTOR[k, k]}")
        if k < P - 1:
            sums = sums.selectExpr("*", *(f"({rest(i, k)}) / {_FACTOR[k, k]} as {_FACTOR[i, k]}" for i in range(k + 1, P)))
    return _inverted(sums.select("_key", "_start", "_rows", *_CENTER, *_FACTOR.values()))


def _sums(rows: DataFrame, q: list[str] = Q) -> DataFrame:
    """Exact: features are integers below 2**15 in size. q: the columns that stand for the features."""
    cross = [f"sum(cast({q[i]} as bigint) * {q[k]}) as _s{i}_{k}" for i in range(P) for k in range(i + 1)]
    each = ["count(*) as _n", "first(_rows) as _rows", *(f"sum({q[i]}) as _s{i}" for i in range(P)), *cross]
    return rows.groupBy("_key", "_start").agg(*map(F.expr, each))


def _starts(rows: DataFrame) -> DataFrame:
    """Centres and scatters (_key, _start, ...) to start from, by medians, by all rows, and by rows cut off at two deviations."""
    middle = runtime.narrow(rows.groupBy("_key").agg(F.expr("count(*) as _rows"), *(F.expr(f"percentile({q}, 0.5D) as {c}") for q, c in zip(Q, _CENTER))))
    groups = middle.count()
    wide = rows.join(_small(middle), "_key").groupBy("_key").agg(*(F.expr(f"percentile(abs({q} - {c}), 0.5D) as _d{i}") for i, (q, c) in enumerate(zip(Q, _CENTER))))
    root = [f"sqrt(pow(1.4826D * _d{i}, 2) + {x * x}) as _r{i}" for i, x in enumerate(FEATURES.values())]
    middle = runtime.narrow(middle.join(wide, "_key").selectExpr("_key", "_rows", *_CENTER, *root), groups)
    first = _inverted(middle.selectExpr("_key", "0 as _start", "_rows", *_CENTER, *(f"{f'_r{i}' if i == k else '0D'} as {name}" for (i, k), name in _FACTOR.items())))
    near = rows.join(_small(middle), "_key")
    every = _fitted(_sums(near.selectExpr("*", "1 as _start")), 1.0, groups)
    cut_off = [f"cast(round(greatest(least({q}, {c} + 2 * _r{i}), {c} - 2 * _r{i})) as int) as _u{i}" for i, (q, c) in enumerate(zip(Q, _CENTER))]
    inner = _fitted(_sums(near.selectExpr("*", "2 as _start", *cut_off), [f"_u{i}" for i in range(P)]), 1.0, groups)
    return first.unionByName(every).unionByName(inner)


def estimates(stats: DataFrame) -> DataFrame:
    """Rows (_group, centre, inverse): the estimate that each group uses, from rows of statistics()."""
    rows = stats.where("not base_failed").selectExpr("explode(array(_group, _wide, '{}')) as _key", *Q)
    own = [*_CENTER, *_INVERSE.values()]
    state = runtime.narrow(_starts(rows).selectExpr("_key", "_start", "_rows", *own, "double('inf') as _det", "false as _done"))
    inflate = SHARE / _chi2_below(chi2_point(SHARE, P), P + 2)
    starts = state.count()
    small = F.broadcast if starts <= MOST_BROADCAST else lambda groups: groups
    while not (going := state.where("not _done")).isEmpty():
        # distances count in hundredths up to 200, so a quantile is of a bounded number of values
        far = rows.join(small(going.drop("_det", "_done")), "_key").selectExpr("_key", "_start", "_rows", f"cast(floor(least(sqrt({_FAR}), 200D) * 100) as int) as _at", *Q)
        limit = runtime.narrow(far.groupBy("_key", "_start").agg(F.expr(f"percentile(_at, {SHARE!r}D) as _limit")), starts)
        fresh = _fitted(_sums(far.join(small(limit), ["_key", "_start"]).where("_at <= _limit")), inflate, starts)
        fresh = fresh.select("_key", "_start", F.struct(*own, "_det").alias("_new"))
        # a step that doesn't lower the determinant is not taken, and ends the start's steps
        falls = f"coalesce(_new._det < _det - {SETTLED!r}D, false)"
        state = runtime.narrow(state.join(small(fresh), ["_key", "_start"], "left").selectExpr("_key", "_start", "_rows", *(f"if({falls}, _new.{c}, {c}) as {c}" for c in (*own, "_det")), f"not {falls} as _done"), starts)
    best = state.groupBy("_key").agg(F.expr("min_by(struct(*), struct(_det, _start)) as best")).select("best.*").drop("_det", "_done")
    weight = 0.975 / _chi2_below(chi2_point(0.975, P), P + 2)
    near = rows.join(small(best), "_key").where(f"{_FAR} <= {chi2_point(0.975, P)!r}D")
    final = runtime.narrow(_fitted(_sums(near), weight, starts).drop("_start", "_det"), starts)
    groups = stats.select("_group", "_wide").distinct()
    every = final.where("_key = '{}'").selectExpr(f"struct(_rows, {', '.join(own)}) as every")  # one row at most
    found, lang = (final.selectExpr(f"_key as {key}", f"struct(_rows, {', '.join(own)}) as {name}") for key, name in (("_group", "found"), ("_wide", "lang")))
    use = groups.join(found, "_group", "left").join(lang, "_wide", "left").join(F.broadcast(every), F.lit(True), "left")
    return runtime.narrow(use.selectExpr("_group", f"case when found._rows >= {ENOUGH} then found when lang._rows >= {ENOUGH} then lang else every end as use").select("_group", "use.*").drop("_rows"))


def _small(groups: DataFrame) -> DataFrame:
    return F.broadcast(groups) if groups.count() <= MOST_BROADCAST else groups


def judged(stats: DataFrame, use: DataFrame) -> DataFrame:
    """stats with distance (null without an estimate) and kept."""
    # a filter on the distance must stay above it: pushed down to the texts, it would work their features out some thirty
    # times for each; an expression that isn't deterministic keeps it there
    rows = stats.join(_small(use), "_group", "left").withColumn("distance", F.expr(f"sqrt({_FAR} + 0 * monotonically_increasing_id())"))
    near = F.coalesce(F.col("distance") <= math.sqrt(chi2_point(1 - TAIL, P)), F.lit(True))
    return rows.withColumn("kept", ~F.col("base_failed") & near).drop(*Q, "_group", "_wide", *_CENTER, *_INVERSE.values())


def rate(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", lang_col: str = "lang", source_col: str = "source") -> DataFrame:
    """One row for each row of df: doc_id, COUNTS, base_failed, kept, distance."""
    named = df.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"), F.col(lang_col).alias("lang"), F.col(source_col).alias("source"))
    stats = runtime.stored(statistics(named).drop("text", "lang", "source"))
    return judged(stats, estimates(stats)).select("doc_id", *COUNTS, "base_failed", "kept", "distance")


def keep_good(df: DataFrame, text_col: str = "text", lang_col: str = "lang", source_col: str = "source") -> DataFrame:
    """The rows of df that are kept, with df's columns. Texts are looked at twice, which takes no disk, rather than written."""
    named = df.select(F.col(text_col).alias("text"), F.col(lang_col).alias("lang"), F.col(source_col).alias("source"))
    use = estimates(runtime.stored(statistics(named).select("_group", "_wide", "base_failed", *Q)))
    inside = df.select(F.struct(*(F.col(f"`{c}`") for c in df.columns)).alias("_row"), F.col(text_col).alias("text"), F.col(lang_col).alias("lang"), F.col(source_col).alias("source"))
    return judged(statistics(inside), use).where("kept").select("_row.*")
