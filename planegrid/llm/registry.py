"""The queries that apply the operators to the given tables, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, fingerprint, license_scan, lmscore, neardup, packing, quality, runtime, secret_scan, substrings, token_count

Query = Callable[[SparkSession, str], DataFrame]


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = runtime.public_file("byte_bpe_multi_50k.tiktoken")
    ids = bpe.encode(documents(spark, sf_dir), path, runtime.split_pattern())
    return bpe.decode(ids, path).select(
        "doc_id",
        F.size("ids").cast("long").alias("n_tokens"),
        F.sha2(F.array_join("ids", ","), 256).alias("ids_sha256"),
        F.sha2("decoded", 256).alias("decoded_sha256"),
    )


def op2_fingerprint(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint.compare_edited(documents(spark, sf_dir))


def op3_lm_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lmscore.score(documents(spark, sf_dir), runtime.public_file("piece_bpe_32k.model"))


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.rate(documents(spark, sf_dir))


def op5_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    matches = F.col("matches")
    written = F.transform(matches, lambda m: F.concat_ws(":", m["license"], m["first_word"].cast("string"), m["stop_word"].cast("string")))
    return license_scan.scan(documents(spark, sf_dir)).select(
        "doc_id", F.size(matches).cast("long").alias("n_matches"), F.array_join(F.sort_array(F.array_distinct(matches["license"])), ",").alias("licenses"), F.array_join(written, ",").alias("matches")
    )


def op6_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(documents(spark, sf_dir), percent=85).drop("mark")


def op7_binary_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packed(documents(spark, sf_dir))


def packed(docs: DataFrame) -> DataFrame:
    found = packing.pieces(docs, runtime.public_file("byte_bpe_50k.json"), runtime.split_pattern(), end_id=1, with_ids=False)
    return packing.pack(found)


def op8_token_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, path = documents(spark, sf_dir), runtime.public_file("piece_bpe_32k.model")
    return token_count.count(docs, path, lmscore.learned_scores(docs, path))


def op9_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    spans = F.col("secret_spans")
    count = lambda kind: F.size(F.filter(spans, lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")
    base = F.filter(spans, lambda s: s["kind"] != "entropy")
    return secret_scan.scan(documents(spark, sf_dir).select("doc_id", "text")).select(
        "doc_id", *map(count, ("assign", "access", "hex")), F.sha2(secret_scan.spans_text(base), 256).alias("base_sha256"), secret_scan.spans_text(spans).alias("spans")
    )


def op10_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substrings.remove_repeats(documents(spark, sf_dir)).select("doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    import corpus_pipeline

    return corpus_pipeline.run(spark, sf_dir)


def text_edited(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What op2_fingerprint says of texts that SQL can say too."""
    return op2_fingerprint(spark, sf_dir).select("doc_id", "n_chars", "edited_sha256")


def text_quality_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The counts and base rules of op4_quality_rules."""
    return op4_quality_rules(spark, sf_dir).select("doc_id", *quality.COUNTS, "base_failed")


def text_secrets_base(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The pattern counts of op9_secret_scan."""
    return op9_secret_scan(spark, sf_dir).select("doc_id", "n_assign", "n_access", "n_hex")


QUERIES: dict[str, Query] = {
    "pipeline": pipeline,
    "op1_byte_bpe": op1_byte_bpe,
    "op2_fingerprint": op2_fingerprint,
    "op3_lm_score": op3_lm_score,
    "op4_quality_rules": op4_quality_rules,
    "op5_license_scan": op5_license_scan,
    "op6_near_duplicates": op6_near_duplicates,
    "op7_binary_packing": op7_binary_packing,
    "op8_token_count": op8_token_count,
    "op9_secret_scan": op9_secret_scan,
    "op10_substring_dedup": op10_substring_dedup,
    "text_edited": text_edited,
    "text_quality_base": text_quality_base,
    "text_secrets_base": text_secrets_base,
}

#: Words of a text, as every operator here takes them; a null or empty text has none.
SQL_WORDS = "regexp_extract_all(coalesce(text, ''), '[^ \\x09-\\x0D]+')"

ORACLES: dict[str, str] = {
    "text_edited": """
        with d as (select doc_id, coalesce(text, '') as t, lead(coalesce(text, '')) over o as a, first_value(coalesce(text, '')) over o as b from documents window o as (order by doc_id))
        select doc_id, length(t)::bigint as n_chars, sha256(substr(t, 1, length(t) - length(t) // 2) || substr(coalesce(a, b), 1, length(t) // 2)) as edited_sha256 from d
    """,
    "text_quality_base": f"""
        with d as (select doc_id, coalesce(text, '') as t, {SQL_WORDS} as w, list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^ \\x09-\\x0D]')) as l from documents),
        win as (select doc_id, s, array_to_string(w[s:s+2], ' ') as g from (select doc_id, w, unnest(range(1, len(w) - 1)) as s from d where len(w) >= 3)),
        twice as (select doc_id, s from win qualify count(*) over (partition by doc_id, g) > 1),
        lain as (select doc_id, count(distinct s + k) as n from twice, range(3) r(k) group by doc_id)
        select doc_id, len(w)::bigint as n_words, length(array_to_string(w, ''))::bigint as word_chars, (length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')))::bigint as n_symbols,
            (len(l) - len(list_distinct(l)))::bigint as n_dup_lines, coalesce(n, 0)::bigint as n_repeat_words, len(w) < 50 or 100 * coalesce(n, 0) > 50 * len(w) as base_failed
        from d left join lain using (doc_id)
    """,
    "text_secrets_base": """
        with d as (select doc_id, coalesce(text, '') as t from documents)
        select doc_id, len(list_filter(regexp_extract_all(t, '(?i:(password|passwd|secret|token|api_?key)["'']?\\x20*[:=]\\x20*["'']?([A-Za-z0-9+/_.=-]+))', 2), lambda x: length(x) >= 6))::bigint as n_assign,
            len(list_filter(regexp_extract_all(t, 'AKIA[A-Z0-9]+'), lambda x: length(x) >= 20))::bigint as n_access, len(list_filter(regexp_extract_all(t, '[0-9a-f]+'), lambda x: length(x) >= 24))::bigint as n_hex from d
    """,
    "op6_near_duplicates": f"""
        with recursive d as (select doc_id, {SQL_WORDS.replace("coalesce(text, '')", "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')")} as w from documents),
        sh as (select distinct doc_id, array_to_string(w[s:s+4], ' ') as t from (select doc_id, w, unnest(range(1, greatest(len(w) - 4, 1) + 1)) as s from d where len(w) > 0)),
        n as (select doc_id, count(*) as n from sh group by doc_id),
        pair as (select x.doc_id as a, y.doc_id as b, count(*) as c from sh x join sh y on x.t = y.t and x.doc_id <> y.doc_id group by 1, 2),
        link as materialized (select a, b from pair join n x on a = x.doc_id join n y on b = y.doc_id where 100 * pair.c >= 85 * (x.n + y.n - pair.c)),
        reach as (select doc_id as a, doc_id as b from d union select reach.a, link.b from reach join link on reach.b = link.a)
        select doc_id, coalesce(n, 0)::bigint as n_shingles, c as component_id, c = doc_id as kept
        from d left join n using (doc_id) join (select a as doc_id, min(b) as c from reach group by a) using (doc_id)
    """,
    "op10_substring_dedup": f"""
        with d as (select doc_id, {SQL_WORDS} as w from documents),
        win as (select doc_id, s, array_to_string(w[s:s+49], ' ') as t from (select doc_id, w, unnest(range(1, len(w) - 48)) as s from d where len(w) >= 50)),
        least as (select t, min(doc_id) as m from win group by t),
        hit as (select distinct doc_id, s + k as p from win join least using (t), range(50) r(k) where m < doc_id),
        gone as (select doc_id, list(p) as g, count(*) as n from hit group by doc_id),
        word as (select doc_id, unnest(w) as x, unnest(range(1, len(w) + 1)) as p from d),
        kept as (select doc_id, string_agg(x, ' ' order by p) as t from word anti join hit using (doc_id, p) group by doc_id)
        select d.doc_id, len(w)::bigint as n_words, coalesce(gone.n, 0)::bigint as n_removed, sha256(coalesce(t, '')) as kept_sha256
        from d left join gone using (doc_id) left join kept using (doc_id)
    """,
}
