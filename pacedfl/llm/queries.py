"""One query per operator of this subpackage, with production parameters on its whole table, and SQL for
those that SQL can express."""

from __future__ import annotations

import os

from pyspark.sql import DataFrame, SparkSession

from pacedfl.llm import url_filter
from pacedfl.llm.byte_bpe import bpe_documents
from pacedfl.llm.common import table
from pacedfl.llm.decontaminate import find_leaks
from pacedfl.llm.iso_media import text_media
from pacedfl.llm.language_id import identify_documents
from pacedfl.llm.quality import fit_quality_model, grade_documents, graded_labels
from pacedfl.llm.secret_scan import scan_secrets
from pacedfl.llm.simhash_dedup import near_duplicate_components
from pacedfl.llm.substring_dedup import WINDOW, remove_repeats
from pacedfl.llm.url_filter import judge_urls
from pacedfl.llm.web_archive import MIN_REVISIT, archive_pages

VOCABULARY = "byte_bpe_50k.tiktoken"


def vocabulary() -> tuple[str, str]:
    """Path of the rank file and the pattern that splits texts; the path can be set by PACEDFL_VOCABULARY."""
    import public_tokenizers

    return os.environ.get("PACEDFL_VOCABULARY") or public_tokenizers.path(VOCABULARY), public_tokenizers.PATTERN


def op1_media(spark: SparkSession, sf_dir: str) -> DataFrame:
    return text_media(table(spark, sf_dir, "documents"))


def op2_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    return archive_pages(table(spark, sf_dir, "pages")).select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op3_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op4_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicate_components(table(spark, sf_dir, "documents"))


def op5_urls(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_urls(table(spark, sf_dir, "pages")).select("page_id", "host", "path", "rule", "verdict")


def op6_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe_documents(table(spark, sf_dir, "documents"), *vocabulary())


def op7_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    return identify_documents(table(spark, sf_dir, "documents"))


def op8_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_secrets(table(spark, sf_dir, "documents"), *vocabulary()).drop("n_random")


def op9_substring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents"))


def op10_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return grade_documents(docs, fit_quality_model(docs, graded_labels(table(spark, sf_dir, "labels"))))


QUERIES = {f.__name__: f for f in (op1_media, op2_warc, op3_decontaminate, op4_simhash, op5_urls, op6_bpe, op7_language, op8_secrets, op9_substring, op10_quality)}


def _rules_sql() -> tuple[str, str]:
    """CASE expressions for rule and verdict."""
    cases = []
    for verdict, rule in sorted(url_filter.RULES, key=lambda x: (-len(x[1]), x[1])):
        host, path = url_filter.split_rule(rule)
        cases.append((f"(host = '{host}' OR ends_with(host, '.{host}')) AND starts_with(path, '{path}')", rule, verdict))
    return tuple("CASE " + " ".join(f"WHEN {c[0]} THEN '{c[k]}'" for c in cases) + " END" for k in (1, 2))  # type: ignore[return-value]


def _host_sql(url: str) -> str:
    return f"translate(regexp_extract(coalesce({url}, ''), '://([^/?#]*)', 1), '{url_filter.UPPER}', '{url_filter.LOWER}')"


def _op5_sql() -> str:
    rule, verdict = _rules_sql()
    link = url_filter.LINK.replace("'", "''")
    d = url_filter.DAMPING
    rounds = url_filter.most_rounds()
    spread = "".join(
        f""", r{t + 1} AS MATERIALIZED (
  SELECT n.kind, n.host, n.ends, CASE WHEN m.moved <= {url_filter.SETTLED!r}::DOUBLE THEN r.rank ELSE {1 - d!r} * n.seed + {d!r} * (coalesce(g.got, 0) + b.back * n.seed) END AS rank, r.rank AS old
  FROM nodes n JOIN r{t} r ON r.kind = n.kind AND r.host = n.host
  LEFT JOIN (SELECT s.kind, s.target AS host, sum(r.rank * s.share) AS got FROM shares s JOIN r{t} r ON r.kind = s.kind AND r.host = s.source GROUP BY 1, 2) g
    ON g.kind = n.kind AND g.host = n.host
  JOIN (SELECT kind, sum(CASE WHEN ends THEN rank ELSE 0 END) AS back FROM r{t} GROUP BY 1) b ON b.kind = n.kind
  CROSS JOIN (SELECT max(moved) AS moved FROM (SELECT sum(abs(rank - old)) AS moved FROM r{t} GROUP BY kind)) m)"""
        for t in range(rounds)
    )
    return f"""
WITH parts AS (SELECT page_id, url, html, {_host_sql("url")} AS host, regexp_extract(coalesce(url, ''), '://[^/?#]*([^?#]*)', 1) AS path FROM pages)
, ruled AS (SELECT page_id, host, path, {rule} AS rule, {verdict} AS ruled FROM parts)
, hosts AS (SELECT host, count(*) AS pages, count(*) FILTER (WHERE ruled = 'allow') AS trust, count(*) FILTER (WHERE ruled = 'block') AS distrust FROM ruled WHERE host <> '' GROUP BY 1)
, total AS (SELECT coalesce(sum(trust), 0)::DOUBLE AS trust, coalesce(sum(distrust), 0)::DOUBLE AS distrust FROM hosts)
, linked AS (SELECT host AS source, unnest(regexp_extract_all(html, '{link}', 1)) AS link FROM parts)
, links AS (SELECT source, target, count(*) AS n FROM (SELECT source, {_host_sql("CASE WHEN starts_with(link, '//') THEN 'http:' || link ELSE link END")} AS target FROM linked)
  WHERE source <> '' AND target <> '' AND source <> target GROUP BY 1, 2)
, edges AS (SELECT 'trust' AS kind, source, target, n FROM links UNION ALL SELECT 'distrust', target, source, n FROM links)
, seeds AS (SELECT kind, host, seed FROM (SELECT 'trust' AS kind, host, h.trust / greatest(t.trust, 1) AS seed FROM hosts h, total t UNION ALL SELECT 'distrust', host, h.distrust / greatest(t.distrust, 1) FROM hosts h, total t) WHERE seed > 0)
, outs AS (SELECT kind, source, sum(n) AS n FROM edges GROUP BY 1, 2)
, shares AS (SELECT e.kind, e.source, e.target, e.n / o.n AS share FROM edges e JOIN outs o ON o.kind = e.kind AND o.source = e.source)
, nodes AS (SELECT a.kind, a.host, coalesce(s.seed, 0) AS seed, o.source IS NULL AS ends
  FROM (SELECT kind, host FROM seeds UNION SELECT kind, source FROM edges UNION SELECT kind, target FROM edges) a
  LEFT JOIN seeds s ON s.kind = a.kind AND s.host = a.host LEFT JOIN outs o ON o.kind = a.kind AND o.source = a.host)
, r0 AS (SELECT kind, host, ends, seed AS rank, NULL::DOUBLE AS old FROM nodes){spread}
, scores AS (SELECT h.host, round(sum(CASE WHEN r.kind = 'trust' THEN -t.trust ELSE t.distrust END * r.rank) / any_value(h.pages), 9) AS score
  FROM r{rounds} r JOIN hosts h ON h.host = r.host, total t GROUP BY 1)
SELECT p.page_id, p.host, p.path, p.rule, coalesce(p.ruled, CASE WHEN coalesce(s.score, 0) > {url_filter.THRESHOLD} THEN 'block' ELSE 'allow' END) AS verdict
FROM ruled p LEFT JOIN scores s ON s.host = p.host
"""


ORACLE = {
    "op2_warc": f"""
WITH p AS (SELECT page_id, coalesce(html, '') AS body, sha256(coalesce(html, '')) AS digest FROM pages)
, f AS (SELECT digest, min(page_id) AS first FROM p WHERE strlen(body) >= {MIN_REVISIT} GROUP BY 1)
SELECT p.page_id, strlen(p.body)::BIGINT AS payload_bytes, p.digest AS payload_digest,
  CASE WHEN p.page_id <> f.first THEN 'revisit' ELSE 'response' END AS record_type,
  CASE WHEN p.page_id <> f.first THEN f.first END AS refers_to
FROM p LEFT JOIN f ON f.digest = p.digest
""",
    "op5_urls": _op5_sql(),
    "op9_substring": rf"""
WITH d AS (SELECT doc_id, list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS words FROM documents)
, w AS (SELECT doc_id, i, array_to_string(words[i:i + {WINDOW - 1}], ' ') AS s FROM (SELECT doc_id, words, unnest(range(1, len(words) - {WINDOW - 2})) AS i FROM d))
, f AS (SELECT s, min(doc_id) AS first FROM w GROUP BY 1)
, gone AS (SELECT DISTINCT w.doc_id, w.i + k AS i FROM w JOIN f ON f.s = w.s, range({WINDOW}) t(k) WHERE f.first < w.doc_id)
, each AS (SELECT doc_id, unnest(words) AS word, unnest(range(1, len(words) + 1)) AS i FROM d)
, kept AS (SELECT e.doc_id, string_agg(e.word, ' ' ORDER BY e.i) AS t, count(*) AS n FROM each e LEFT JOIN gone g ON g.doc_id = e.doc_id AND g.i = e.i WHERE g.i IS NULL GROUP BY 1)
SELECT d.doc_id, len(d.words)::BIGINT AS n_words, (len(d.words) - coalesce(k.n, 0))::BIGINT AS n_removed, sha256(coalesce(k.t, '')) AS kept_sha256
FROM d LEFT JOIN kept k ON k.doc_id = d.doc_id
""",
}
