"""The queries of this subpackage, opN_<name>, and their SQL for DuckDB."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathsieve.llm import decontamination, fingerprints, html_text, huffman, language, language_model, licenses, near_dedup, packing, suffix_dedup
from pathsieve.llm.shared import fresh_path, table


def op1_simhash_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprints.edited_fingerprints(table(spark, sf_dir, "documents"))


def op2_kernel_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = language.predict(docs, language.fit(docs))
    return found.select("doc_id", language.held_out(F.col("doc_id")).alias("held_out"), "lang_pred", "score")


def op3_page_differencing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_text.extract(table(spark, sf_dir, "pages"))


def op4_positional_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontamination.contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op5_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(packing.pieces(table(spark, sf_dir, "documents")))


def op6_huffman_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = fresh_path(spark, "tokens")
    huffman.write_tokens(table(spark, sf_dir, "documents"), path)
    return huffman.read_tokens(spark, path)


def op7_simhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_dedup.near_duplicates(table(spark, sf_dir, "documents"))


def op8_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix_dedup.remove_repeats(table(spark, sf_dir, "documents")).drop("kept_text")


def op9_trie_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    held_out = language_model.held_out(F.col("doc_id"))
    found = language_model.score(table(spark, sf_dir, "documents"), ~held_out)
    return found.select("doc_id", (~F.col("learnt")).alias("held_out"), "n_tokens", "n_known", "train_tokens", "base_score", "score")


def op10_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {k: f for k, f in globals().items() if k.startswith("op") and k[2].isdigit()}


#: Words of a text; the pattern is that of the contract.
_WORDS = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

OP4_SQL = rf"""
WITH d AS (SELECT row_number() OVER () AS k, doc_id, {_WORDS} AS w FROM documents),
b AS (SELECT coalesce(item_id::VARCHAR, '') AS item, {_WORDS} AS w FROM benchmark),
win AS (SELECT DISTINCT item, list_slice(w, p, p + 9) AS ws FROM (SELECT item, w, unnest(range(1, greatest(len(w) - 9, 1) + 1)) AS p FROM b WHERE len(w) > 0)),
sizes AS (SELECT DISTINCT len(ws) AS n FROM win),
places AS (SELECT k, p, n, list_slice(w, p, p + n - 1) AS ws FROM (SELECT k, w, n, unnest(range(1, len(w) - n + 2)) AS p FROM d, sizes WHERE len(w) >= n)),
hits AS (SELECT k, p, n, item FROM places JOIN win USING (ws)),
cover AS (SELECT k, count(DISTINCT q) AS n_hit FROM (SELECT k, unnest(range(p, p + n)) AS q FROM hits) GROUP BY k),
items AS (SELECT k, count(DISTINCT item) AS n_items, array_to_string(list_sort(list(DISTINCT item)), ',') AS joined FROM hits GROUP BY k)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items, sha256(coalesce(joined, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM d LEFT JOIN cover USING (k) LEFT JOIN items USING (k)
"""


def _op10_sql() -> str:
    values = lambda d: ", ".join(f"('{k}', '{v}')" for k, v in d.items())
    return rf"""
WITH d AS (SELECT row_number() OVER () AS k, doc_id, text, {_WORDS} AS w FROM documents),
phrases(phrase, label) AS (VALUES {values(licenses.PHRASES)}),
base AS (SELECT k, label, unnest(list_filter(range(0, len(w)), lambda i: list_slice(w, i + 1, i + len(string_split(phrase, ' '))) = string_split(phrase, ' '))) AS place FROM d, phrases WHERE list_has_all(w, string_split(phrase, ' '))),
b AS (SELECT k, count(*) AS n_base, min(place) AS first_word, max(place) AS last_word, list(DISTINCT label) AS labels FROM base GROUP BY k),
split AS (SELECT k, nth, line, length(line) <= {licenses.WRAP} AND trim(line, ' ') <> '' AS fits FROM (SELECT k, unnest(string_split(coalesce(text, ''), chr(10))) AS line, unnest(range(len(string_split(coalesce(text, ''), chr(10))))) AS nth FROM d)),
rows_of AS (SELECT k, list(line) OVER w AS run_lines, list(fits) OVER w AS fit FROM split WINDOW w AS (PARTITION BY k ORDER BY nth ROWS BETWEEN CURRENT ROW AND {licenses.WRAPPED - 1} FOLLOWING)),
blocks AS (SELECT k, line AS text FROM split UNION ALL SELECT k, array_to_string(list_slice(run_lines, 1, coalesce(nullif(list_position(fit, false), 0) - 1, len(fit))), chr(10)) AS text FROM rows_of WHERE fit[1]),
lines AS (SELECT k, list_distinct(text_words) AS lw FROM (SELECT k, {_WORDS} AS text_words FROM blocks)),
templates AS (SELECT label, list_distinct({_WORDS}) AS tw FROM (VALUES {values(licenses.TEMPLATES)}) AS t(label, text)),
s AS (SELECT k, list(DISTINCT label) AS labels, max(c) AS score FROM (SELECT k, label, len(list_intersect(lw, tw)) / len(tw) AS c FROM lines, templates WHERE list_has_any(lw, tw) AND len(list_intersect(lw, tw)) >= {licenses.THRESHOLD} * len(tw) - 1e-9) GROUP BY k)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_base, 0)::BIGINT AS n_base, first_word::BIGINT AS first_word, last_word::BIGINT AS last_word,
array_to_string(list_sort(coalesce(b.labels, [])), ',') AS base_labels, array_to_string(list_sort(list_distinct(list_concat(coalesce(b.labels, []), coalesce(s.labels, [])))), ',') AS labels,
CASE WHEN n_base > 0 THEN 1.0::DOUBLE ELSE coalesce(score, 0)::DOUBLE END AS score
FROM d LEFT JOIN b USING (k) LEFT JOIN s USING (k)
"""


def oracle_sql() -> dict[str, str]:
    return {"op4_positional_decontamination": OP4_SQL, "op10_license_scan": _op10_sql()}
