"""The operators as queries over whole tables."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from gridmul.llm import op1_mixing, op2_neardup, op10_lines, op3_media, op4_urls, op5_quality, op6_pii, op7_pieces, op8_html, op9_licences
from gridmul.llm.common import table


def op1_source_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = op1_mixing.mix(table(spark, sf_dir, "documents"), op1_mixing.label_domains(table(spark, sf_dir, "labels")))
    return mixed.select("doc_id", "n_tokens", *[F.col("p")[i].alias(f"p_{n}") for i, n in enumerate(op1_mixing.TARGETS)], "rate", "share_error")


def op2_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op2_neardup.near_duplicates(table(spark, sf_dir, "documents"))


def op3_media_columns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op3_media.digest_texts(table(spark, sf_dir, "documents"))


def op4_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op4_urls.filter_urls(table(spark, sf_dir, "pages")).select("page_id", "host", "path", "rule", "verdict")


def op5_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op5_quality.quality(table(spark, sf_dir, "documents"))


def op6_personal_data(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = op6_pii.personal_data(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_email", "n_ip", "n_card", "n_phone", "n_context", F.sha2(op6_pii.span_text(F.col("base")), 256).alias("base_sha256"), op6_pii.span_text(F.concat("base", "context")).alias("spans"))


def op7_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op7_pieces.encode(table(spark, sf_dir, "documents"))


def op8_html_extraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    return op8_html.main_texts(table(spark, sf_dir, "pages"))


def op9_licence_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = op9_licences.scan_licences(table(spark, sf_dir, "documents"))
    spans = F.array_join(F.transform("spans", lambda s: F.concat_ws(":", s["licence"], s["start"].cast("string"), s["end"].cast("string"))), ",")
    return found.select("doc_id", "n_spans", "licence", "score", spans.alias("spans"))


def op10_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = op10_lines.dedup_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.select("doc_id", F.col("_gm_lines").alias("n_lines"), F.col("_gm_removed").alias("n_removed"), "text")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = (op1_source_mixing, op2_ngram_jaccard_join, op3_media_columns, op4_url_filters, op5_quality_rules, op6_personal_data, op7_sentencepiece, op8_html_extraction, op9_licence_scans, op10_line_dedup)
    return {f.__name__: f for f in own}


def _line_sql() -> str:
    """Line dedup by least windows: a run of so many words is covered by the shortest such windows from each of its lines on and
    up to each of its lines; a window is gone where the same lines, in order, stand earlier."""
    least = op10_lines.MIN_WORDS
    return f"""WITH l AS (SELECT doc_id, string_split(text, chr(10)) AS ls FROM documents), p AS (SELECT doc_id, ls, unnest(range(len(ls))) AS pos FROM l),
        w AS (SELECT doc_id, pos, len(regexp_extract_all(ls[pos + 1], '\\S+')) AS n FROM p), c AS (SELECT doc_id, pos, n, sum(n) OVER (PARTITION BY doc_id ORDER BY pos) AS upto FROM w),
        least AS (SELECT a.doc_id, a.pos AS lo, min(b.pos) + 1 AS hi FROM c a JOIN c b ON a.doc_id = b.doc_id AND b.pos >= a.pos AND b.upto - a.upto + a.n >= {least} GROUP BY 1, 2
            UNION SELECT b.doc_id, max(a.pos) AS lo, b.pos + 1 AS hi FROM c a JOIN c b ON a.doc_id = b.doc_id AND b.pos >= a.pos AND b.upto - a.upto + a.n >= {least} GROUP BY 1, b.pos),
        later AS (SELECT doc_id, lo, hi, row_number() OVER (PARTITION BY md5(array_to_string(ls[lo + 1:hi], chr(10))) ORDER BY doc_id, lo) AS place FROM least JOIN l USING (doc_id)),
        gone AS (SELECT DISTINCT doc_id, unnest(range(lo, hi)) AS pos FROM later WHERE place > 1),
        kept AS (SELECT p.doc_id, count(*) AS n_lines, count(g.pos) AS n_removed, coalesce(string_agg(ls[p.pos + 1], chr(10) ORDER BY p.pos) FILTER (WHERE g.pos IS NULL), '') AS text
            FROM p LEFT JOIN gone g ON g.doc_id = p.doc_id AND g.pos = p.pos GROUP BY p.doc_id)
        SELECT doc_id, n_lines, n_removed, text FROM kept"""


def _url_sql(steps: int = 100) -> str:
    """Rules, then the walks of trust and distrust, a common table expression a step; so many steps change a score by 1e-7 of all mass."""
    lower = "translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
    case = {"rule": "", "verdict": ""}
    for what, h, path in sorted(op4_urls.RULES, key=lambda r: -len(r[1] + r[2])):
        fits = f"(host = '{h}' OR suffix(host, '.{h}')) AND prefix(path, '{path}')"
        case["rule"] += f" WHEN {fits} THEN '{h}{path}'"
        case["verdict"] += f" WHEN {fits} THEN '{what}'"
    link = op4_urls.LINK.replace("'", "''")
    walks = ""
    for kind, src, dst in (("good", "src", "dst"), ("bad", "dst", "src")):
        walks += f", seed_{kind} AS MATERIALIZED (SELECT host, {kind} / (SELECT sum({kind}) FROM hosts)::DOUBLE AS x FROM hosts WHERE {kind} > 0), share_{kind} AS MATERIALIZED (SELECT {src} AS s, {dst} AS d, n / sum(n) OVER (PARTITION BY {src})::DOUBLE AS w FROM edges), {kind}_0 AS MATERIALIZED (SELECT * FROM seed_{kind})"
        for k in range(steps):
            walks += f", {kind}_{k + 1} AS MATERIALIZED (SELECT host, sum(x) AS x FROM (SELECT d AS host, w * x * {op4_urls.DAMPING} AS x FROM share_{kind} JOIN {kind}_{k} ON s = host UNION ALL SELECT host, x * (1 - {op4_urls.DAMPING}) FROM seed_{kind}) GROUP BY 1)"
        walks += f", {kind} AS (SELECT host, x / sum(x) OVER () AS x FROM {kind}_{steps})"
    return f"""WITH u AS (SELECT page_id, html, {lower.format("regexp_extract(coalesce(url, ''), '(?s)^.*?://([^/?#]*)', 1)")} AS host, regexp_extract(coalesce(url, ''), '(?s)^.*?://[^/?#]*([^?#]*)', 1) AS path FROM pages),
        j AS (SELECT *, CASE{case["rule"]} END AS rule, CASE{case["verdict"]} END AS ruled FROM u),
        hosts AS (SELECT host, count(*) FILTER (WHERE ruled = 'allow') AS good, count(*) FILTER (WHERE ruled = 'block') AS bad FROM j GROUP BY 1),
        edges AS (SELECT src, dst, count(*) AS n FROM (SELECT DISTINCT page_id, host AS src, {lower.format(f"unnest(regexp_extract_all(coalesce(html, ''), '{link}', 1))")} AS dst FROM j) WHERE src <> '' AND src <> dst GROUP BY 1, 2){walks}
        SELECT page_id, j.host, path, rule, coalesce(ruled, CASE WHEN coalesce(b.x, 0) > coalesce(g.x, 0) THEN 'block' ELSE 'allow' END) AS verdict
        FROM j LEFT JOIN good g ON g.host = j.host LEFT JOIN bad b ON b.host = j.host"""


def oracle_sql() -> dict[str, str]:
    """SQL for the operators that it can express; the others are tested against brute force, round trips or held-out labels."""
    return {"op4_url_filters": _url_sql(), "op10_line_dedup": _line_sql()}
