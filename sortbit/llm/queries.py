"""The queries opN_<name>: each operator with its production parameters over its whole table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontaminate, language_id, license_scan, line_dedup, near_dedup, packing, pii, quality_rules, token_output, toxicity
from .base import fold_is_held_out, read

#: A text is taken as toxic from this score on.
TOXIC_FROM = 0.3
#: The key of the surrogates in the query; a real run gives its own secret.
PII_KEY = "surrogates-1"


def op5_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    found = language_id.detect(docs, language_id.fit(docs))
    return found.select("doc_id", fold_is_held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")


def op6_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    return pii.pseudonymise(docs, PII_KEY, count_as="n_entities")


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    scored = toxicity.score(docs, toxicity.fit(docs, read(spark, sf_dir, "labels")))
    return scored.select("doc_id", fold_is_held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= TOXIC_FROM).cast("int").alias("predicted"))


def op1_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.contaminated(read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark"))


def op2_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan(read(spark, sf_dir, "documents"), license_scan.known_texts(spark))


def op3_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_output.pack_tokens(read(spark, sf_dir, "documents"))


def op4_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents").select("doc_id", "text")
    done = line_dedup.deduplicate_lines(docs, count_as="deleted_lines")
    return done.select("doc_id", "deleted_lines", F.md5("text").alias("text_md5"))


def op8_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read(spark, sf_dir, "documents")
    rules = quality_rules.fit(docs, read(spark, sf_dir, "labels"))
    found = quality_rules.apply_rules(quality_rules.statistics(docs), rules)
    return found.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op9_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_duplicates(read(spark, sf_dir, "documents"))


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(read(spark, sf_dir, "documents"))


def license_sql() -> str:
    """The scan with the same fixed values, in DuckDB's words."""
    quoted = lambda x: "'" + x.replace("'", "''") + "'"
    x = "lower(text)"
    x = f"regexp_replace({x}, {quoted(license_scan.COPYRIGHT_LINE)}, '\\1', 'g')"
    x = f"' ' || trim(regexp_replace({x}, {quoted(license_scan.PLAIN_GAP)}, ' ', 'g')) || ' '"
    for old, new in 2 * license_scan.SPELLINGS:
        x = f"replace({x}, ' {old} ', ' {new} ')"
    form = f"trim({x})"
    known = ", ".join(f"({quoted(a)}, {quoted(b)})" for a, b in license_scan.KNOWN)
    return f"""
        WITH known AS (
            SELECT sha256(form) AS digest, string_agg(DISTINCT license, ',' ORDER BY license) AS license
            FROM (SELECT license, {form} AS form FROM (VALUES {known}) v(license, text)) GROUP BY ALL),
        whole AS (SELECT doc_id, sha256({form}) AS digest FROM documents),
        line AS (SELECT doc_id, sha256({form}) AS digest FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS text FROM documents)),
        notice AS (SELECT doc_id, string_agg(DISTINCT k.license, ',' ORDER BY k.license) AS notices FROM line JOIN known k USING (digest) GROUP BY doc_id)
        SELECT w.doc_id, w.digest, k.license, n.notices FROM whole w LEFT JOIN known k USING (digest) LEFT JOIN notice n ON n.doc_id = w.doc_id
    """


#: Up to a table `stripped` (doc_id, text, flags): documents without later copies of repeated line runs.
LINE_DEDUP_SQL = r"""
        WITH line AS (
            SELECT doc_id, unnest(string_split(text, chr(10))) AS s, generate_subscripts(string_split(text, chr(10)), 1) AS i
            FROM {docs} WHERE text IS NOT NULL),
        long AS (SELECT doc_id, i, s, sum(length(s) + 1) OVER (PARTITION BY doc_id ORDER BY i) AS upto, length(s) + 1 AS n FROM line),
        block AS (
            SELECT a.doc_id, a.i AS first_line, min(b.i) AS last_line FROM long a JOIN long b ON b.doc_id = a.doc_id AND b.i BETWEEN a.i AND a.i + {most} - 1
            WHERE b.upto - a.upto + a.n >= {most} GROUP BY ALL
            UNION
            SELECT b.doc_id, max(a.i), b.i FROM long a JOIN long b ON b.doc_id = a.doc_id AND a.i BETWEEN b.i - {most} + 1 AND b.i
            WHERE b.upto - a.upto + a.n >= {most} GROUP BY b.doc_id, b.i),
        content AS (
            SELECT k.doc_id, first_line, last_line, list_slice(string_split(d.text, chr(10)), first_line, last_line) AS body
            FROM block k JOIN {docs} d ON d.doc_id = k.doc_id),
        later AS (
            SELECT doc_id, first_line, last_line FROM content
            QUALIFY row_number() OVER (PARTITION BY body ORDER BY doc_id, first_line) > 1),
        gone AS (SELECT DISTINCT doc_id, unnest(range(first_line, last_line + 1)) AS i FROM later),
        stripped AS (
            SELECT l.doc_id, coalesce(string_agg(l.s, chr(10) ORDER BY l.i) FILTER (WHERE g.i IS NULL), '') AS text, list(g.i IS NOT NULL) AS flags
            FROM line l LEFT JOIN gone g ON g.doc_id = l.doc_id AND g.i = l.i GROUP BY l.doc_id)
"""

QUERIES = {
    "op1_decontaminate": op1_decontaminate,
    "op2_license_scan": op2_license_scan,
    "op3_token_output": op3_token_output,
    "op5_language_id": op5_language_id,
    "op6_pii": op6_pii,
    "op7_toxicity": op7_toxicity,
    "op4_line_dedup": op4_line_dedup,
    "op8_quality_rules": op8_quality_rules,
    "op9_near_dedup": op9_near_dedup,
    "op10_packing": op10_packing,
}

#: DuckDB SQL for the queries that SQL can express.
ORACLES: dict[str, str] = {
    "op2_license_scan": license_sql(),
    "op4_line_dedup": LINE_DEDUP_SQL.format(docs="documents", most=line_dedup.MIN_CHARS)
    + """
        SELECT d.doc_id, coalesce(list_sum(flags::BIGINT[]), 0)::BIGINT AS deleted_lines, md5(s.text) AS text_md5
        FROM documents d LEFT JOIN stripped s ON s.doc_id = d.doc_id
    """,
    "op9_near_dedup": r"""
        WITH RECURSIVE worded AS (
            SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w
            FROM documents),
        shingle AS (
            SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) >= 5 THEN [array_to_string(w[i:i + 4], ' ') FOR i IN range(1, len(w) - 3)]
                                               WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END) AS s
            FROM worded),
        counted AS (SELECT doc_id, count(*) AS n FROM shingle GROUP BY doc_id),
        pair AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS both_n FROM shingle a JOIN shingle b USING (s) WHERE a.doc_id < b.doc_id GROUP BY ALL),
        link AS (
            SELECT x, y FROM pair JOIN counted p ON p.doc_id = x JOIN counted q ON q.doc_id = y
            WHERE 100 * both_n >= 75 * (p.n + q.n - both_n)),
        edge AS (SELECT x, y FROM link UNION ALL SELECT y, x FROM link),
        reach AS (SELECT x AS doc_id, x AS other FROM edge UNION SELECT r.doc_id, e.y FROM reach r JOIN edge e ON e.x = r.other),
        least AS (SELECT doc_id, min(other) AS component FROM reach GROUP BY doc_id)
        SELECT d.doc_id, coalesce(c.n, 0)::BIGINT AS n_shingles, coalesce(l.component, d.doc_id) AS component_id, coalesce(l.component, d.doc_id) = d.doc_id AS kept
        FROM documents d LEFT JOIN counted c ON c.doc_id = d.doc_id LEFT JOIN least l ON l.doc_id = d.doc_id
    """,
}
