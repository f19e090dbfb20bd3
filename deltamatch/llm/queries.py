"""The registered query of each operator, over whole tables, and SQL where SQL can express it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ann, bpe, licenses, mixing, quality_knn, quality_rules, secrets, simhash, toxicity, warc
from .common import table


def op1_simhash_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_duplicates(table(spark, sf_dir, "documents"))


def op2_warc_archives(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(spark, table(spark, sf_dir, "pages"))


def op3_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return licenses.scan(table(spark, sf_dir, "documents"))


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op5_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.scan(table(spark, sf_dir, "documents"), bpe.public_codec())


def op6_adaptive_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.quality_verdicts(table(spark, sf_dir, "documents"))


def op7_quality_neighbours(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_knn.classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op8_temperature_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mix_report(table(spark, sf_dir, "documents"))


def op9_cross_polytope(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.search(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 100 == 0)


def op10_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_digests(table(spark, sf_dir, "documents"), bpe.public_codec())


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {f.__name__: f for f in (op1_simhash_groups, op2_warc_archives, op3_license_scan, op4_toxicity, op5_secret_scan, op6_adaptive_quality, op7_quality_neighbours, op8_temperature_mix, op9_cross_polytope, op10_byte_bpe)}


def _quality_sql(reach: float = 6.0) -> str:
    """Twin of op6: exact quartiles, which the sketches hold as long as a group has fewer than half as many documents as their accuracy."""
    measures = {"symbol_ratio": "n_symbols / n", "word_length": "word_chars / n", "dup_line_share": "n_dup_lines / lines", "repeat_share": "n_repeat_words / n"}
    quartile = lambda k, p: f"list_sort(list({k}))[CAST(ceil({p} * count(*)) AS BIGINT)]"
    limits, fine = [], []
    for k, (below, above) in quality_rules.SLACK.items():
        limits.append(f"{quartile(k, 0.25)} AS a_{k}, {quartile(k, 0.75)} AS b_{k}")
        fine += [f"coalesce({k} >= a_{k} - {reach} * (b_{k} - a_{k}) - {below}, true)"] if below is not None else []
        fine += [f"coalesce({k} <= b_{k} + {reach} * (b_{k} - a_{k}) + {above}, true)"] if above is not None else []
    return f"""
        WITH d AS (SELECT row_number() OVER () AS rid, doc_id, lang, source, coalesce(text, '') AS t FROM documents),
        w AS (SELECT *, regexp_extract_all(t, '[^\\x20\\x09-\\x0D]+') AS ws FROM d),
        g AS (SELECT rid, i, ws[i] || ' ' || ws[i + 1] || ' ' || ws[i + 2] AS three FROM (SELECT rid, ws, unnest(range(1, len(ws) - 1)) AS i FROM w)),
        r AS (SELECT rid, i FROM g QUALIFY count(*) OVER (PARTITION BY rid, three) > 1),
        rw AS (SELECT rid, count(DISTINCT j) AS n_repeat_words FROM (SELECT rid, unnest([i, i + 1, i + 2]) AS j FROM r) GROUP BY rid),
        l AS (SELECT rid, count(*) AS n_lines, count(*) - count(DISTINCT line) AS n_dup_lines FROM (SELECT rid, unnest(string_split(t, chr(10))) AS line FROM d) WHERE regexp_matches(line, '[^\\x20\\x09-\\x0D]') GROUP BY rid),
        c AS (SELECT doc_id, lang, source, CAST(len(ws) AS BIGINT) AS n_words, CAST(length(array_to_string(ws, '')) AS BIGINT) AS word_chars,
                     CAST(length(t) - length(regexp_replace(t, '[#*$%&|<>]', '', 'g')) AS BIGINT) AS n_symbols, coalesce(n_dup_lines, 0) AS n_dup_lines, coalesce(n_repeat_words, 0) AS n_repeat_words,
                     CAST(greatest(len(ws), 1) AS DOUBLE) AS n, CAST(greatest(coalesce(n_lines, 0), 1) AS DOUBLE) AS lines FROM w LEFT JOIN rw USING (rid) LEFT JOIN l USING (rid)),
        m AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed, {', '.join(f'{v} AS {k}' for k, v in measures.items())} FROM c),
        q AS (SELECT lang AS ql, source AS qs, {', '.join(limits)} FROM m WHERE NOT base_failed GROUP BY lang, source)
        SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND {' AND '.join(fine)} AS kept
        FROM m LEFT JOIN q ON lang IS NOT DISTINCT FROM ql AND source IS NOT DISTINCT FROM qs"""


#: DuckDB twins.
ORACLES: dict[str, str] = {
    "op2_warc_archives": """
        WITH p AS (SELECT page_id, coalesce(html, '') AS body FROM pages),
        d AS (SELECT page_id, CAST(strlen(body) AS BIGINT) AS payload_bytes, sha256(body) AS payload_digest FROM p),
        f AS (SELECT payload_digest AS dg, min(page_id) AS first_id FROM d WHERE payload_bytes >= 100 GROUP BY payload_digest)
        SELECT page_id, payload_bytes, payload_digest,
               CASE WHEN payload_bytes >= 100 AND page_id <> first_id THEN 'revisit' ELSE 'response' END AS record_type,
               CASE WHEN payload_bytes >= 100 AND page_id <> first_id THEN first_id END AS refers_to
        FROM d LEFT JOIN f ON payload_digest = dg""",
    "op6_adaptive_quality": _quality_sql(),
}
