"""The registered queries of this subpackage, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from . import chat_format, decontamination, html_extraction, huffman_ids, near_duplicates, packing, pii, quality_classifier, quality_rules, repeated_bytes
from .common import table

BYTE_BPE = public_tokenizers.path("byte_bpe_50k.json")
WORD_BPE = public_tokenizers.path("word_bpe_49k.json")


def op1_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html_extraction.extract_pages(table(spark, sf_dir, "pages"))


def op2_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = decontamination.decontaminate(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", "n_items", "items_sha256", "contaminated")


def op3_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.quality_rules(table(spark, sf_dir, "documents"))


def op4_packing(spark: SparkSession, sf_dir: str, path: str = BYTE_BPE) -> DataFrame:
    return packing.pack_documents(table(spark, sf_dir, "documents"), path, keep_ids=False)


def op5_repeated_bytes(spark: SparkSession, sf_dir: str) -> DataFrame:
    return repeated_bytes.remove_repeats(table(spark, sf_dir, "documents"), passage_words=50)


def op6_huffman_ids(spark: SparkSession, sf_dir: str, path: str = WORD_BPE) -> DataFrame:
    folder = huffman_ids.write_ids(table(spark, sf_dir, "documents"), path)
    return huffman_ids.read_ids(spark, folder, keep_ids=False)


def op7_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.find_pii(table(spark, sf_dir, "documents"))


def op8_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    turns = table(spark, sf_dir, "conversations")
    kinds = ", ".join(f"{c} {turns.schema[c].dataType.simpleString()}" for c in ("conv_id", "turn", "role", "text"))
    said = "</s>[INST] ok [/INST]"
    more = spark.createDataFrame([(-1, 0, "user", said), (-1, 1, "assistant", said)], kinds)
    return chat_format.format_and_read_back(turns.select("conv_id", "turn", "role", "text").unionByName(more))


def op9_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_classifier.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op10_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates.near_duplicates(table(spark, sf_dir, "documents")).select("doc_id", "class_id", "is_first")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_html_extraction, op2_decontamination, op3_quality_rules, op4_packing, op5_repeated_bytes,
        op6_huffman_ids, op7_pii, op8_chat_format, op9_quality_classifier, op10_near_duplicates,
    )
}

_OP2_SQL = r"""
WITH pattern AS (SELECT '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+' AS p),
doc AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), p) AS w
  FROM documents, pattern),
item AS (
  SELECT CAST(item_id AS VARCHAR) AS item_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), p) AS w
  FROM benchmark, pattern),
win AS (
  SELECT item_id, least(10, len(w)) AS k, unnest(list_transform(range(1, greatest(2, CAST(len(w) AS BIGINT) - 8)), lambda i: array_to_string(w[i : i + least(10, len(w)) - 1], ' '))) AS x
  FROM item WHERE len(w) > 0),
sizes AS (SELECT DISTINCT k FROM win),
place AS (
  SELECT doc_id, k, unnest(range(1, greatest(1, CAST(len(w) AS BIGINT) - k + 2))) AS i,
    unnest(list_transform(range(1, greatest(1, CAST(len(w) AS BIGINT) - k + 2)), lambda i: array_to_string(w[i : i + k - 1], ' '))) AS x
  FROM doc, sizes),
hit AS (SELECT place.doc_id, place.i, place.k, win.item_id FROM place JOIN (SELECT DISTINCT * FROM win) win ON place.k = win.k AND place.x = win.x),
covered AS (SELECT doc_id, count(DISTINCT j) AS n FROM (SELECT doc_id, unnest(range(i, i + k)) AS j FROM hit) GROUP BY doc_id),
met AS (SELECT doc_id, count(DISTINCT item_id) AS n, string_agg(DISTINCT item_id, ',' ORDER BY item_id) AS ids FROM hit GROUP BY doc_id)
SELECT doc.doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(coalesce(covered.n, 0) AS BIGINT) AS n_hit,
  CAST(coalesce(met.n, 0) AS BIGINT) AS n_items, sha256(coalesce(met.ids, '')) AS items_sha256, coalesce(covered.n, 0) > 0 AS contaminated
FROM doc LEFT JOIN covered USING (doc_id) LEFT JOIN met USING (doc_id)
"""

_OP3_SQL = r"""
WITH doc AS (
  SELECT doc_id, coalesce(source, '') AS host, coalesce(text, '') AS t,
    regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w
  FROM documents),
win AS (
  SELECT doc_id, unnest(range(1, greatest(1, CAST(len(w) AS BIGINT) - 1))) AS i,
    unnest(list_transform(range(1, greatest(1, CAST(len(w) AS BIGINT) - 1)), lambda i: array_to_string(w[i : i + 2], ' '))) AS x
  FROM doc),
twice AS (SELECT doc_id, x FROM win GROUP BY ALL HAVING count(*) > 1),
repeated AS (
  SELECT doc_id, count(DISTINCT j) AS n
  FROM (SELECT doc_id, unnest(range(i, i + 3)) AS j FROM win JOIN twice USING (doc_id, x)) GROUP BY doc_id),
own_lines AS (SELECT doc_id, unnest(string_split(t, chr(10))) AS line FROM doc),
dup AS (
  SELECT doc_id, count(*) - count(DISTINCT line) AS n FROM own_lines WHERE regexp_matches(line, '[^\x20\x09-\x0D]') GROUP BY doc_id),
plain AS (
  SELECT doc_id, host, i, regexp_extract_all(x, '[^\x20\x09-\x0D]+') AS w
  FROM (SELECT doc_id, host, unnest(l) AS x, unnest(range(1, len(l) + 1)) AS i FROM (
    SELECT doc_id, host, string_split(regexp_replace(translate(t, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[0-9]', '0', 'g'), chr(10)) AS l FROM doc))),
lines AS (
  SELECT doc_id, host, i, array_to_string(w, ' ') AS h, len(w) AS n FROM plain WHERE len(w) >= 1),
frequent AS (
  SELECT host, h FROM (SELECT DISTINCT lines.host, h, t FROM lines JOIN doc USING (doc_id))
    JOIN (SELECT host, count(*) AS size FROM doc GROUP BY host) USING (host)
  GROUP BY host, h, size HAVING count(*) > 20 AND count(*) > 0.002 * size),
removed AS (SELECT doc_id, sum(n) AS n FROM lines JOIN frequent USING (host, h) GROUP BY doc_id),
counted AS (
  SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, CAST(length(array_to_string(w, '')) AS BIGINT) AS word_chars,
    CAST(len(regexp_extract_all(t, '[#*$%&|<>]')) AS BIGINT) AS n_symbols, CAST(coalesce(dup.n, 0) AS BIGINT) AS n_dup_lines,
    CAST(coalesce(repeated.n, 0) AS BIGINT) AS n_repeat_words, CAST(coalesce(removed.n, 0) AS BIGINT) AS n_removed_words
  FROM doc LEFT JOIN dup USING (doc_id) LEFT JOIN repeated USING (doc_id) LEFT JOIN removed USING (doc_id))
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, failed AS base_failed,
  NOT failed AND n_words - n_removed_words >= 0.3 * n_words AS kept, n_removed_words
FROM (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS failed FROM counted)
"""

#: Op 3's windows and lines are compared as strings here and by hashes in the operator.
ORACLES: dict[str, str] = {"op2_decontamination": _OP2_SQL, "op3_quality_rules": _OP3_SQL}
