"""The queries of the operators, their SQL, and nothing else."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from blockmf.llm.common import table
from blockmf.llm.decontaminate import contamination
from blockmf.llm.exact_dedup import exact_groups
from blockmf.llm.html_text import extract_pages
from blockmf.llm.near_dedup import near_classes
from blockmf.llm.packing import pack
from blockmf.llm.quality import held_out, scored, train
from blockmf.llm.secrets import find_secrets
from blockmf.llm.suffix_dedup import repeated_bytes
from blockmf.llm.token_files import encode_to_files
from blockmf.llm.tokenize import vocabulary
from blockmf.llm.url_filter import RULES, judge


def op1_exact_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact_groups(table(spark, sf_dir, "documents").select("doc_id", "text"), stays="max")


def op2_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contamination(table(spark, sf_dir, "documents").select("doc_id", "text"), table(spark, sf_dir, "benchmark"))


def op3_secrets(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_secrets(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op4_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    model = train(docs, table(spark, sf_dir, "labels"), cut=0.7)
    found = scored(docs, model).select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score")
    return found.withColumn("predicted", (F.col("score") >= 0.7).cast("int"))


def op5_html_text(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_pages(table(spark, sf_dir, "pages").select("page_id", "html"))


def op6_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "pages").select("page_id", "url", "html"))


def op7_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = repeated_bytes(table(spark, sf_dir, "documents").select("doc_id", "text"))
    return found.drop("removed")


def op8_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_classes(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op9_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_to_files(table(spark, sf_dir, "documents").select("doc_id", "text"), vocabulary("byte_bpe_50k.json"))


def op10_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents").select("doc_id", "text"), vocabulary("word_bpe_49k.json"))


QUERIES = {f.__name__: f for f in (op1_exact_dedup, op2_decontaminate, op3_secrets, op4_quality, op5_html_text, op6_url_filter, op7_suffix_dedup, op8_near_dedup, op9_token_files, op10_packing)}

_NORM = "translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"


def _host_sql(rest: str) -> str:
    return f"coalesce(translate(regexp_extract({rest}, '^([^/?#]*)', 1), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '')"


def _path_sql(rest: str) -> str:
    return f"coalesce(regexp_extract({rest}, '^[^/?#]*([^?#]*)', 1), '')"


def _rule_sql(host: str, path: str, what: int) -> str:
    """CASE over the rules, longest first; what: 0 action, 1 rule text."""
    whens = "".join(f" WHEN ({host} = '{h}' OR {host} LIKE '%.{h}') AND starts_with({path}, '{p}') THEN '{(a, h + p)[what]}'" for a, h, p in sorted(RULES, key=lambda r: -len(r[1] + r[2])))
    return f"CASE{whens} END"


_LINK_SQL = r"""regexp_extract(html, '<link\b[^>]*\brel\s*=\s*["'']?canonical\b[^>]*>', 0, 'is')"""
_META_SQL = r"""regexp_extract(html, '<meta\b[^>]*\bhttp-equiv\s*=\s*["'']?refresh\b[^>]*>', 0, 'is')"""
_HREF_SQL = ", ".join(f"nullif(regexp_extract({_LINK_SQL}, '{p}', 1, 'is'), '')" for p in (r'\bhref\s*=\s*"([^"]*)"', r"\bhref\s*=\s*''([^'']*)''", r'\bhref\s*=\s*([^\s"' r"''>]+)"))
_REST_SQL = "substr(to_url, strpos(to_url, '://') + 3)"
_URL_SQL = rf"""
WITH RECURSIVE p AS (SELECT page_id, url, html, CASE WHEN strpos(url, '://') > 0 THEN substr(url, strpos(url, '://') + 3) END AS rest FROM pages),
h AS (SELECT *, {_host_sql('rest')} AS host, {_path_sql('rest')} AS path FROM p),
n AS (SELECT *, {_rule_sql('host', 'path', 0)} AS own, {_rule_sql('host', 'path', 1)} AS rule, nullif(host || path, '') AS node FROM h),
l AS (SELECT node, url, host, path, trim(coalesce({_HREF_SQL})) AS target FROM n WHERE rest IS NOT NULL
      UNION ALL SELECT node, url, host, path, trim(nullif(regexp_extract({_META_SQL}, '\burl\s*=\s*["'']?([^"''>\s]+)', 1, 'is'), '')) FROM n WHERE rest IS NOT NULL),
f AS (SELECT node, CASE WHEN regexp_matches(target, '^https?://', 'i') THEN target WHEN starts_with(target, '//') THEN split_part(url, '://', 1) || ':' || target
      WHEN starts_with(target, '/') THEN split_part(url, '://', 1) || '://' || host || target WHEN regexp_matches(target, '^[A-Za-z][A-Za-z0-9+.-]*:') THEN NULL
      WHEN regexp_matches(target, '^[?#]') THEN split_part(url, '://', 1) || '://' || host || path
      ELSE split_part(url, '://', 1) || '://' || host || CASE WHEN regexp_extract(path, '^(.*/)', 1) = '' THEN '/' ELSE regexp_extract(path, '^(.*/)', 1) END || target END AS to_url FROM l WHERE target IS NOT NULL),
e AS (SELECT DISTINCT node AS a, {_host_sql(_REST_SQL)} || {_path_sql(_REST_SQL)} AS b FROM f WHERE to_url IS NOT NULL),
pairs AS (SELECT a, b FROM e WHERE a != b AND b != '' UNION SELECT b, a FROM e WHERE a != b AND b != ''),
reach(node, other) AS (SELECT a, a FROM pairs UNION SELECT r.node, k.b FROM reach r JOIN pairs k ON k.a = r.other),
c AS (SELECT node, min(other) AS component FROM reach GROUP BY node),
s AS (SELECT component, CASE WHEN bool_or(act = 'allow') THEN 'allow' WHEN bool_or(act = 'block') THEN 'block' END AS spread
      FROM (SELECT component, {_rule_sql("regexp_extract(node, '^([^/?#]*)', 1)", "regexp_extract(node, '^[^/?#]*([^?#]*)', 1)", 0)} AS act FROM c) x GROUP BY component)
SELECT page_id, host, path, rule, coalesce(own, spread, 'allow') AS verdict, coalesce(c.component, n.node) AS component
FROM n LEFT JOIN c ON c.node = n.node LEFT JOIN s ON s.component = c.component"""
ORACLE_SQL = {
    "op1_exact_dedup": f"""
        SELECT doc_id, max(doc_id) OVER w AS keep_id, count(*) OVER w AS group_size,
               doc_id = max(doc_id) OVER w AS kept, sha256(norm) AS text_sha256
        FROM (SELECT doc_id, {_NORM} AS norm FROM documents) WINDOW w AS (PARTITION BY norm)""",
    "op6_url_filter": _URL_SQL,
}
