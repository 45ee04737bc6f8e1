"""Document fingerprints by consistent weighted sampling, in DataFrame expressions only.

A document is its words weighted by how often they occur. For every term and lane, hashes give two
gamma(2, 1) variables r and c and a uniform b; with weight w, t = floor(ln(w) / r + b) and
ln(a) = ln(c) - r * (t - b) - r. The lane keeps the term with the smallest a, together with t. Two documents
agree in a lane with a probability equal to their generalised Jaccard similarity, the sum of smaller weights over
the sum of larger ones.

A lane's value packs ln(a) into the upper half of a long and 32 bits of (term, t) into the lower, so that a plain
minimum, which Spark combines early and without objects, is the sample.

Rows: a null or empty text has no terms; its lanes all hold -1 and agree with those of other empty texts. Equal
texts have equal fingerprints. Every row gets a fingerprint, also where ids or whole rows repeat or the id is
null; other columns are not carried along, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from . import runtime

LANES = 32
#: ln(a) is stored as (ln(a) + OFFSET) * SCALE; beyond its bounds the order is lost, which takes weights over e**400.
OFFSET, SCALE = 512.0, float(1 << 20)
_MASK = (1 << 32) - 1
_UNIT = 2.0**-21
#: What tells lanes apart: multiples of a fixed odd number, as signed longs.
_MARKS = [((k + 1) * 0x9E3779B97F4A7C15 + (1 << 63)) % (1 << 64) - (1 << 63) for k in range(2 * 256)]


def _uniforms(term: str, lane: int) -> list[Column]:
    """Five numbers in (0, 1): three from one hash with 21 bits each, two from another."""
    one, two = (F.xxhash64(F.col(term).bitwiseXOR(F.lit(x))) for x in _MARKS[2 * lane : 2 * lane + 2])
    bits = lambda h, k: (F.shiftrightunsigned(h, 21 * k).bitwiseAND(F.lit((1 << 21) - 1)) + 0.5) * _UNIT
    return [bits(one, 0), bits(one, 1), bits(one, 2), bits(two, 0), bits(two, 1)]


def _samples(term: str, log_weights: list[str], lane: int) -> list[Column]:
    """The lane's value of a term for each weight; null where the weight is. What hangs on the term alone is shared."""
    u = _uniforms(term, lane)
    r, c, b = -F.log(u[0] * u[1]), F.log(-F.log(u[3] * u[4])), u[2]
    out = []
    for log_weight in log_weights:
        t = F.floor(F.col(log_weight) / r + b)
        place = F.floor((c - r * (t - b + 1) + OFFSET) * SCALE)
        out.append(F.shiftleft(place, 32).bitwiseOR(F.col(term).bitwiseXOR(F.shiftleft(t, 9)).bitwiseAND(F.lit(_MASK))))
    return out


def _terms(text_cols: list[str]) -> Column:
    """(term, n0[, n1]) of all distinct words of one or two texts, with their numbers in each.

    A term is a hash with its lowest bit cleared; that bit tells the texts apart while all are sorted together.
    """
    hashes = lambda k, c: F.transform(F.array_remove(F.split(F.coalesce(F.col(c), F.lit("")), r"[\x20\x09-\x0D]+", -1), ""), lambda w: F.xxhash64(w).bitwiseAND(F.lit(-2)).bitwiseOR(F.lit(k).cast("long")))
    let = lambda value, use: F.transform(F.array(value), use)[0]
    every = F.sort_array(F.concat(*(hashes(k, c) for k, c in enumerate(text_cols))))

    def runs(x: Column) -> Column:
        """Distinct values of a sorted array, with their numbers."""
        begin = F.filter(F.sequence(F.lit(0), F.size(x) - 1), lambda i: (i == 0) | (x[i] != x[F.greatest(i - 1, F.lit(0))]))
        return let(begin, lambda at: F.transform(at, lambda i, j: F.struct(x[i].alias("v"), (F.when(j + 1 < F.size(at), at[F.least(j + 1, F.size(at) - 1)]).otherwise(F.size(x)) - i).alias("n"))))

    def merged(r: Column) -> Column:
        if len(text_cols) == 1:
            return F.transform(r, lambda y: F.struct(y["v"].alias("term"), y["n"].alias("n0")))
        last = F.size(r) - 1

        def one(y: Column, j: Column) -> Column:
            after, before = r[F.least(j + 1, last)], r[F.greatest(j - 1, F.lit(0))]
            own = y["v"].bitwiseAND(F.lit(1).cast("long")) == 0
            both = F.when((j < last) & (after["v"] == y["v"] + 1), after["n"])
            alone = F.when((j == 0) | (before["v"] != y["v"] - 1), F.struct((y["v"] - 1).alias("term"), F.lit(None).cast("int").alias("n0"), y["n"].alias("n1")))
            return F.when(own, F.struct(y["v"].alias("term"), y["n"].alias("n0"), both.alias("n1"))).otherwise(alone)

        return F.filter(F.transform(r, one), lambda y: y.isNotNull())

    return let(every, lambda x: F.when(F.size(x) > 0, let(runs(x), merged)))


def lanes(texts: DataFrame, keys: list[str], text_cols: list[str], n_lanes: int = LANES) -> DataFrame:
    """Rows (keys, {text}_lanes array<int> for each text column): the samples of rows with any word.

    Rows that agree in keys must agree in their texts. Terms are counted within their row, and a term that two
    columns share is hashed once; what is shuffled is a row of minima for each row of texts.
    """
    weights = [f"_log{k}" for k in range(len(text_cols))]
    rows = texts.select(*keys, F.explode(_terms(text_cols)).alias("_x")).select(*keys, F.col("_x.term").alias("_term"), *(F.log(f"_x.n{k}").alias(w) for k, w in enumerate(weights)))
    sampled = [F.min(x).alias(f"_s{lane}_{k}") for lane in range(n_lanes) for k, x in enumerate(_samples("_term", weights, lane))]
    least = rows.groupBy(*keys).agg(*sampled)
    low = lambda lane, k: F.coalesce(F.col(f"_s{lane}_{k}").bitwiseAND(F.lit(_MASK)) - F.lit(1 << 31), F.lit(-1)).cast("int")
    return least.select(*keys, *(F.array(*(low(lane, k) for lane in range(n_lanes))).alias(f"{c}_lanes") for k, c in enumerate(text_cols)))


def _full(found: str, n_lanes: int) -> Column:
    """Lanes, those of an empty text where there are none."""
    return F.coalesce(F.col(found), F.array_repeat(F.lit(-1), n_lanes))


def likeness(left: Column, right: Column) -> Column:
    """Share of equal lanes."""
    same = F.filter(F.zip_with(left, right, lambda x, y: x == y), lambda x: x)
    return F.size(same) / F.size(left).cast("double")


def written(found: Column) -> Column:
    """Lanes as eight hex digits each."""
    return F.array_join(F.transform(found, lambda x: F.lower(F.lpad(F.hex(x.cast("long").bitwiseAND(F.lit(_MASK))), 8, "0"))), "")


#: What tells rows apart: the id (for rows without one, free, a hash of the text, so that these spread too), and 128 bits of the text.
KEYS = ["k", "free", "m0", "m1"]


def _keyed(df: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(KEYS, text)."""
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    one, two = F.xxhash64(text), F.xxhash64(F.lit(1), text, F.char_length(text))
    return df.select(F.coalesce(F.col(id_col).cast("long"), one).alias("k"), F.col(id_col).isNull().alias("free"), one.alias("m0"), two.alias("m1"), text.alias("text"))


def fingerprints(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", n_lanes: int = LANES) -> DataFrame:
    """Rows (doc_id, lanes, fingerprint), one for each row of df. Rows that agree are sampled together."""
    rows = _keyed(df, id_col, text_col)
    each = rows.select(*KEYS).join(lanes(rows, KEYS, ["text"], n_lanes), KEYS, "left").withColumn("lanes", _full("text_lanes", n_lanes))
    return each.select(F.when(~F.col("free"), F.col("k")).alias("doc_id"), "lanes", written(F.col("lanes")).alias("fingerprint"))


def successors(rows: DataFrame) -> DataFrame:
    """rows: (doc_id, ...), distinct ids. Adds next_id, the id after it; the first comes after the last.

    Ids are range-partitioned; within a partition the next row is the next id, and a partition's last id meets the
    first of the next one through a table with one row for each partition.
    """
    placed = runtime.cut(rows.repartitionByRange("doc_id").withColumn("_part", F.spark_partition_id()))
    heads = placed.groupBy("_part").agg(F.min("doc_id").alias("_head"))
    every = Window.orderBy("_part")
    heads = heads.select("_part", F.coalesce(F.lead("_head").over(every), F.min("_head").over(every)).alias("_after"))
    next_id = F.lead("doc_id").over(Window.partitionBy("_part").orderBy("doc_id"))
    return placed.withColumn("next_id", next_id).join(F.broadcast(heads), "_part").withColumn("next_id", F.coalesce("next_id", "_after")).drop("_part", "_after")


def compare_edited(df: DataFrame, id_col: str = "doc_id", text_col: str = "text", n_lanes: int = LANES) -> DataFrame:
    """Fingerprints of every text and of an edited copy, whose last half is the start of the next document.

    Rows (doc_id, n_chars, edited_sha256, fingerprint, edited_fingerprint, near_edited, near_next), one for each row
    of df. Of floor(n_chars / 2) code points at the end, as many of the next document's first ones take the place,
    or all if it has fewer. Next is the next larger id, and of its rows the one with the least hash if ids repeat;
    without an id there is no next document, nothing takes the place, and near_next is null.
    """
    rows = _keyed(df, id_col, text_col)
    half = (F.char_length("text") / 2).cast("int")
    ids = rows.where("not free").groupBy(F.col("k").alias("doc_id")).agg(F.max(half).alias("half"))
    after = runtime.cut(successors(ids))
    # rows enter both joins as they are, so their texts are shuffled once
    begin = F.when(~F.col("free"), F.struct("m0", "m1", F.substring(F.col("text"), F.lit(1), F.col("half")).alias("begin")))
    begins = rows.join(after, F.col("k") == F.col("next_id")).select("doc_id", begin.alias("row"))
    begins = begins.groupBy(F.col("doc_id").alias("k")).agg(F.min("row")["begin"].alias("begin"))
    both = rows.join(begins, "k", "left")
    n = F.char_length("text")
    begin = F.when(F.col("free"), F.lit("")).otherwise(F.coalesce(F.substring(F.col("begin"), F.lit(1), half), F.lit("")))
    both = both.select(*KEYS, n.cast("long").alias("n_chars"), "text", F.concat(F.substring(F.col("text"), F.lit(1), n - half), begin).alias("edited"))
    found = both.select(*KEYS, "n_chars", F.sha2("edited", 256).alias("edited_sha256")).join(lanes(both, KEYS, ["text", "edited"], n_lanes), KEYS, "left")
    found = runtime.cut(found.select(*KEYS, "n_chars", "edited_sha256", _full("text_lanes", n_lanes).alias("own"), _full("edited_lanes", n_lanes).alias("edited")))
    # each document's lanes go to the one before it
    nexts = found.where("not free").groupBy("k").agg(F.min(F.struct("m0", "m1", "own"))["own"].alias("next")).join(after, F.col("k") == F.col("next_id"))
    nexts = nexts.select(F.col("doc_id").alias("k"), F.lit(False).alias("free"), "next")
    return found.join(nexts, ["k", "free"], "left").select(
        F.when(~F.col("free"), F.col("k")).alias("doc_id"),
        "n_chars",
        "edited_sha256",
        written(F.col("own")).alias("fingerprint"),
        written(F.col("edited")).alias("edited_fingerprint"),
        likeness(F.col("own"), F.col("edited")).alias("near_edited"),
        likeness(F.col("own"), F.col("next")).alias("near_next"),
    )
