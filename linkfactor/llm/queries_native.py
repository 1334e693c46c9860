"""Queries of the operators that run in DataFrame functions alone, with their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import mixing, urls
from .cluster import table


def op5_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Equal weights for all sources, as many rows as documents has on average."""
    return mixing.mix_sources(table(spark, sf_dir, "documents"))


OP5_SQL = f"""
WITH n AS (SELECT source, count(*) AS n_rows FROM documents GROUP BY source),
t AS (SELECT sum(n_rows)::double AS goal, count(*)::double AS weights FROM n),
r AS (SELECT source, goal * 1.0::double / weights / n_rows AS rate FROM n, t),
k AS (SELECT source, rate, unnest(range(0, (ceil(rate + 10 * sqrt(rate)) + 21)::bigint)) AS k FROM r),
p AS (SELECT source, k, exp(-rate + k * ln(rate) - coalesce((SELECT sum(ln(j)) FROM range(1, k + 1) g(j)), 0)) AS p FROM k),
c AS (SELECT source, k, sum(p) OVER (PARTITION BY source ORDER BY k) AS cdf FROM p),
d AS (SELECT d.*, ('0x' || substr(md5('{mixing.SEED}|' || coalesce(doc_id::varchar, 'null')), 1, 13))::bigint / 4503599627370496.0::double AS u FROM documents d),
m AS (SELECT d.doc_id, d.text, d.lang, d.source, d.n_chars, (SELECT count(*) FROM c WHERE c.source IS NOT DISTINCT FROM d.source AND c.cdf <= d.u) AS copies FROM d),
e AS (SELECT doc_id, text, lang, source, n_chars, unnest(range(1, copies + 1))::integer AS copy FROM m)
SELECT *, ('0x' || substr(md5('{mixing.SEED}|place|' || coalesce(doc_id::varchar, 'null') || '|' || copy), 1, 13))::bigint AS shuffle_key FROM e
"""


def block_list(pages: DataFrame) -> DataFrame:
    """Stand-in for a delivered block list: the page keys (host and path) whose md5 begins with 0, one in sixteen."""
    keys = pages.select(F.concat(urls.url_host(F.col("url")), urls.url_path(F.col("url"))).alias("key"))
    return keys.where(F.md5("key").startswith("0"))


def op7_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages")
    return urls.judge_urls(pages, block_list(pages))


_FITS = " ".join(f"WHEN (host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}') THEN {{}}" for h, p, _ in sorted(urls.RULES, key=lambda r: -len(r[0] + r[1])))
_ORDER = sorted(urls.RULES, key=lambda r: -len(r[0] + r[1]))
OP7_SQL = f"""
WITH a AS (SELECT page_id, CASE WHEN contains(url, '://') THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
b AS (SELECT page_id, regexp_extract(rest, '^([^/?#]*)', 1) AS raw, rest FROM a),
c AS (SELECT page_id, translate(raw, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(substr(rest, length(raw) + 1), '^(/[^?#]*)', 1) AS path FROM b)
SELECT page_id, host, path, CASE {_FITS.format(*[f"'{h}{p}'" for h, p, _ in _ORDER])} END AS rule,
  CASE {_FITS.format(*[f"'{v}'" for *_, v in _ORDER])} WHEN starts_with(md5(host || path), '0') THEN 'block' ELSE 'allow' END AS verdict,
  starts_with(md5(host || path), '0') AS on_list
FROM c
"""

QUERIES = {"op5_mixing": op5_mixing, "op7_url_filter": op7_url_filter}
SQL = {"op5_mixing": OP5_SQL, "op7_url_filter": OP7_SQL}
