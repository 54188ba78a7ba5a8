"""One query for each operator of this subpackage, with the SQL that checks it where SQL can."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from arealex.llm import extraction, fingerprints, language, linededup, mixing, neardup, packing, quality, secrets, toxicity
from arealex.llm.common import table


def _remainder(n: int):
    return F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(n))


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality.measure(table(spark, sf_dir, "documents")).drop("failed_rules")


def op2_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(table(spark, sf_dir, "documents"))


def op3_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = language.train(docs.where((_remainder(4) != 2) & F.col("lang").isNotNull()))
    found = language.identify(docs.select("doc_id", "text"), model)
    return found.select("doc_id", (_remainder(4) == 2).alias("held_out"), "lang_pred", "score", "cosine", "rejected")


def op4_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extraction.extract_pages(table(spark, sf_dir, "pages"))


def op5_minhash_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return neardup.near_duplicates(table(spark, sf_dir, "documents"), percent=85)


def op6_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken", "copies", "rate")


def op7_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.scan(table(spark, sf_dir, "documents"))


def op8_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return linededup.classes(table(spark, sf_dir, "documents"), shorter=True)


def op9_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.compare_neighbours(table(spark, sf_dir, "documents"))


def op10_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    model = toxicity.train(docs, labels.where(_remainder(3) != 1))
    found = toxicity.score(docs.select("doc_id", "text"), model)
    return found.select("doc_id", (_remainder(3) == 1).alias("held_out"), "score", "predicted")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    "op1_quality_rules": op1_quality_rules,
    "op2_packing": op2_packing,
    "op3_language_id": op3_language_id,
    "op4_html_extraction": op4_html_extraction,
    "op5_minhash_neardup": op5_minhash_neardup,
    "op6_mixing": op6_mixing,
    "op7_secret_scan": op7_secret_scan,
    "op8_line_dedup": op8_line_dedup,
    "op9_fingerprints": op9_fingerprints,
    "op10_toxicity": op10_toxicity,
}

_STOPS = ", ".join(f"'{x}'" for x in quality.STOP_WORDS)

ORACLE_SQL: dict[str, str] = {
    "op1_quality_rules": rf"""
WITH raw AS (SELECT doc_id, coalesce(text, '') AS t, row_number() OVER () AS r FROM documents),
cut AS (SELECT doc_id, r, t, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS w,
               list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS l FROM raw),
win AS (SELECT r, i, w[i] || chr(32) || w[i + 1] || chr(32) || w[i + 2] AS g FROM (SELECT r, w, unnest(range(1, len(w) - 1)) AS i FROM cut)),
twice AS (SELECT r, i FROM (SELECT r, i, count(*) OVER (PARTITION BY r, g) AS n FROM win) WHERE n > 1),
marked AS (SELECT r, count(DISTINCT i + k) AS n FROM twice, (SELECT unnest([0, 1, 2]) AS k) GROUP BY r),
m AS (SELECT doc_id, len(w)::BIGINT AS n_words, length(regexp_replace(t, '[\x20\x09-\x0D]+', '', 'g'))::BIGINT AS word_chars,
             length(regexp_replace(t, '[^#*$%&|<>]+', '', 'g'))::BIGINT AS n_symbols, (len(l) - len(list_distinct(l)))::BIGINT AS n_dup_lines,
             coalesce(marked.n, 0)::BIGINT AS n_repeat_words, len(l)::BIGINT AS n_lines,
             len(list_filter(l, lambda x: regexp_matches(ltrim(x, ' '), '^[-*•]')))::BIGINT AS n_bullets,
             len(list_filter(l, lambda x: rtrim(x, ' ') LIKE '%...' OR rtrim(x, ' ') LIKE '%…'))::BIGINT AS n_ellipses,
             len(list_filter(w, lambda x: lower(x) IN ({_STOPS})))::BIGINT AS n_stop_words,
             length(regexp_replace(t, '\P{{L}}+', '', 'g'))::BIGINT AS n_letters
      FROM cut LEFT JOIN marked USING (r)),
f AS (SELECT *, (n_words < 50 OR 100 * n_repeat_words > 50 * n_words) AS base_failed,
             CASE WHEN n_words = 0 THEN 0.0 ELSE word_chars::DOUBLE / n_words END AS mean_chars,
             CASE WHEN n_words = 0 THEN 0.0 ELSE n_symbols::DOUBLE / n_words END AS symbols,
             CASE WHEN n_lines = 0 THEN 0.0 ELSE n_dup_lines::DOUBLE / n_lines END AS dups,
             CASE WHEN n_words = 0 THEN 0.0 ELSE n_stop_words::DOUBLE / n_words END AS stops,
             CASE WHEN word_chars = 0 THEN 0.0 ELSE n_letters::DOUBLE / word_chars END AS letters,
             CASE WHEN n_lines = 0 THEN 0.0 ELSE n_bullets::DOUBLE / n_lines END AS bullets,
             CASE WHEN n_lines = 0 THEN 0.0 ELSE n_ellipses::DOUBLE / n_lines END AS ellipses FROM m)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, n_lines, n_bullets, n_ellipses, n_stop_words, n_letters, base_failed,
       (NOT base_failed AND mean_chars BETWEEN 2.0 AND 15.0 AND symbols <= 0.25 AND dups <= 0.5 AND stops >= 0.02 AND letters >= 0.5 AND bullets <= 0.9 AND ellipses <= 0.5) AS kept
FROM f""",
    "op5_minhash_neardup": r"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
sh AS (SELECT DISTINCT doc_id, array_to_string(w[i:i + 4], ' ') AS s FROM (SELECT doc_id, w, unnest(range(1, greatest(1, len(w) - 4) + 1)) AS i FROM w WHERE len(w) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM sh GROUP BY doc_id),
pairs AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM sh a JOIN sh b USING (s) WHERE a.doc_id < b.doc_id GROUP BY ALL),
links AS (SELECT a, b FROM pairs JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 85 * (x.n + y.n - c)),
both_ AS (SELECT a, b FROM links UNION ALL SELECT b, a FROM links),
reach(doc_id, r) AS (SELECT doc_id, doc_id FROM w UNION SELECT both_.b, r FROM reach JOIN both_ ON reach.doc_id = both_.a)
SELECT doc_id, coalesce(n.n, 0) AS n_shingles, component_id, doc_id = component_id AS kept FROM (SELECT doc_id, min(r) AS component_id FROM reach GROUP BY doc_id) LEFT JOIN n USING (doc_id)""",
}
