"""The queries of this subpackage, each over whole tables, and the DuckDB SQL that some of them equal."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from unionlake.llm import covering, decontaminate, fingerprint, langid, license_scan, packing, ppm, token_store, toxicity, warc
from unionlake.llm.common import table


def op1_fingerprints(spark: SparkSession, sf_dir: str) -> DataFrame:
    return fingerprint.edited_report(spark, table(spark, sf_dir, "documents"))


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.classify(spark, table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op3_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return langid.identify(spark, table(spark, sf_dir, "documents"))


def op4_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan.scan(spark, table(spark, sf_dir, "documents"))


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.scan(spark, table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op6_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack(spark, table(spark, sf_dir, "documents"))


def op7_token_store(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_store.round_trip(spark, table(spark, sf_dir, "documents"))


def op8_ppm(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ppm.score(spark, table(spark, sf_dir, "documents"))


def op9_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return covering.link_components(spark, table(spark, sf_dir, "documents"))


def op10_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(spark, table(spark, sf_dir, "pages"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_fingerprints": op1_fingerprints,
        "op2_toxicity": op2_toxicity,
        "op3_language": op3_language,
        "op4_license_scan": op4_license_scan,
        "op5_decontaminate": op5_decontaminate,
        "op6_packing": op6_packing,
        "op7_token_store": op7_token_store,
        "op8_ppm": op8_ppm,
        "op9_simhash": op9_simhash,
        "op10_warc": op10_warc,
    }


#: Words as the contracts of this subpackage take them, in DuckDB.
WORDS = r"regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x00-\x2F\x3A-\x60\x7B-\x7F]+')"

DECONTAMINATE = f"""WITH dw AS (SELECT doc_id, {WORDS} AS w FROM documents), bw AS (SELECT item_id, {WORDS} AS w FROM benchmark),
 bl AS (SELECT item_id, w, least(10, len(w)) AS n FROM bw WHERE len(w) > 0),
 bi AS (SELECT DISTINCT item_id, n, array_to_string(w[i:i + n - 1], ' ') AS win FROM (SELECT *, unnest(range(1, len(w) - n + 2)) AS i FROM bl)),
 di AS (SELECT doc_id, n, i, array_to_string(w[i:i + n - 1], ' ') AS win FROM (SELECT doc_id, w, n, unnest(range(1, len(w) - n + 2)) AS i FROM dw, (SELECT DISTINCT n FROM bi) WHERE len(w) >= n)),
 hit AS (SELECT doc_id, i, n, item_id FROM di JOIN bi USING (n, win)),
 wo AS (SELECT doc_id, count(DISTINCT p) AS n_hit FROM (SELECT doc_id, unnest(range(i, i + n)) AS p FROM hit) GROUP BY 1),
 it AS (SELECT doc_id, count(*) AS n_items, string_agg(x, ',' ORDER BY x) AS items FROM (SELECT DISTINCT doc_id, CAST(item_id AS VARCHAR) AS x FROM hit) GROUP BY 1)
SELECT doc_id, CAST(len(w) AS BIGINT) AS n_words, coalesce(n_hit, 0) AS n_hit, coalesce(n_items, 0) AS n_items, sha256(coalesce(items, '')) AS items_sha256, n_hit IS NOT NULL AS contaminated
FROM dw LEFT JOIN wo USING (doc_id) LEFT JOIN it USING (doc_id)"""

WARC = """WITH p AS (SELECT page_id, coalesce(html, '') AS h FROM pages),
 g AS (SELECT h, max(page_id) AS origin FROM p WHERE strlen(h) >= 1000 GROUP BY 1)
SELECT page_id, CAST(strlen(p.h) AS BIGINT) AS payload_bytes, sha1(p.h) AS payload_digest, CASE WHEN page_id < origin THEN 'revisit' ELSE 'response' END AS record_type, CASE WHEN page_id < origin THEN origin END AS refers_to
FROM p LEFT JOIN g USING (h)"""


def oracle_sql() -> dict[str, str]:
    """Of the others, SQL has no Unicode composition, tokenizer, xxhash or learned model; tests hold them against brute force."""
    return {"op5_decontaminate": DECONTAMINATE, "op10_warc": WARC}
