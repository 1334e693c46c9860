"""Link graphs: extraction, resolution, filters, variants."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import sources
from ..operators import graph
from . import twins as S


def links(s, d) -> DataFrame:
    return graph.extract_links(sources.read_table(s, d, "pages"))


def links_resolve(s, d):
    return graph.resolve_links(links(s, d)).select("page_id", F.col("target").alias("absolute_url"))


def links_tld(s, d):
    x = links(s, d).withColumn("tld", graph.tld_of(F.col("url")))
    return x.groupBy("tld").agg(F.count(F.lit(1)).alias("edges"), F.countDistinct("page_id").alias("sources"), F.countDistinct("href").alias("targets"))


def links_min_degree(s, d):
    pages = graph.min_degree(links(s, d), "page_id", "href", 5).agg(F.count(F.lit(1)).alias("edges")).select(F.lit("links").alias("graph"), "edges")
    words = sources.word_observations(s, d, 5).agg(F.count(F.lit(1)).alias("edges")).select(F.lit("words").alias("graph"), "edges")
    return pages.unionByName(words)


def links_kcore(s, d):
    """pass and edges left, for 3 links, to the fixed point (the last pass changes nothing)."""
    out = None
    for n, edges in enumerate(graph.core(links(s, d).select("page_id", "href"), "page_id", "href", 3), 1):
        one = edges.agg(F.count(F.lit(1)).alias("edges")).select(F.lit(n).alias("pass"), "edges")
        out = one if out is None else out.unionByName(one)
    return out


def min_degree_nodes(s, d):
    """The one-node-set reading, on nations linked by who sells to whom."""
    o = sources.read_table(s, d, "orders").select("o_orderkey", "o_custkey")
    x = sources.read_table(s, d, "lineitem").select("l_orderkey", "l_suppkey").join(o, F.col("l_orderkey") == F.col("o_orderkey"))
    x = x.join(sources.read_table(s, d, "supplier").select("s_suppkey", F.col("s_nationkey").alias("src")), F.col("l_suppkey") == F.col("s_suppkey"))
    x = x.join(sources.read_table(s, d, "customer").select("c_custkey", F.col("c_nationkey").alias("dst")), F.col("o_custkey") == F.col("c_custkey"))
    edges = x.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("n")).where("n >= 40").select("src", "dst")
    return graph.min_degree_of_nodes(edges, "src", "dst", 8)


def graph_variants(s, d):
    return graph.all_stats(links(s, d))


def wl_graph_stats(s, d):
    """Statistics of the documents' word graph at three least counts."""
    t, out = sources.tokens(s, d), None
    for k in (2, 5, 10):
        one = graph.graph_stats(graph.min_degree(t, "doc_id", "word", k), "doc_id", "word", "documents", k)
        out = one if out is None else out.unionByName(one)
    return out


def links_dangling(s, d):
    pages = sources.read_table(s, d, "pages")
    return graph.dangling(graph.resolve_links(graph.extract_links(pages)), pages).agg(F.count(F.lit(1)).alias("n"))


def host_graph(s, d):
    return graph.host_graph(links(s, d))


def page_locales(s, d):
    x = sources.read_table(s, d, "pages").select(graph.tld_of(F.col("url")).alias("tld"), graph.page_language(F.col("html")).alias("lang"))
    return x.groupBy("tld", "lang").agg(F.count(F.lit(1)).alias("n"))


def build_graph_stats(s, d):
    """least, nodes and edges of absolute links after one pass with 1 link (which keeps all) and with 2."""
    out = None
    for least in (1, 2):
        edges, nodes = graph.build_graph(sources.read_table(s, d, "pages"), None, least)
        sums = [F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("out_links", "in_links")]
        one = edges.agg(F.count(F.lit(1)).alias("edges")).crossJoin(nodes.agg(F.count(F.lit(1)).alias("nodes"), *sums)).withColumn("least", F.lit(least))
        out = one if out is None else out.unionByName(one)
    return out


def wl_split(s, d):
    from .serving import split_strong

    return split_strong(s, d).groupBy("role").agg(F.count(F.lit(1)).alias("links"), F.countDistinct("page_id").alias("sources"))


_LU = f"WITH {S.L}, lu AS (SELECT l.page_id, path, url, regexp_extract(url, '^[a-z]+://([^/?#]*)', 1) AS host FROM l JOIN pages ON l.page_id = pages.page_id), lt AS (SELECT *, list_extract(string_split(host, '.'), -1) AS tld FROM lu)"
_ABS = f"{_LU}, ab AS (SELECT DISTINCT page_id, url, regexp_extract(url, '^([a-z]+://[^/?#]*)', 1) || path AS target FROM lu)"


def _kept(name: str, obs: str, src: str, dst: str, k: int) -> str:
    return f"{name} AS (SELECT * FROM {obs} WHERE {src} IN (SELECT {src} FROM {obs} GROUP BY 1 HAVING count(*) >= {k}) AND {dst} IN (SELECT {dst} FROM {obs} GROUP BY 1 HAVING count(*) >= {k}))"


def _stats(cte: str, cases: list[tuple[str, int, str]], src: str, dst: str) -> str:
    one = "SELECT '{v}' AS variant, {k} AS k, count(DISTINCT {s}) AS sources, count(DISTINCT {t}) AS targets, count(DISTINCT {s}) + count(DISTINCT {t}) AS nodes, count(*) AS edges, round(CASE WHEN count(*) > 0 THEN count(*)::double / count(DISTINCT {s}) END, 6) AS mean_degree FROM {c}"
    return f"{cte} " + " UNION ALL ".join(one.format(v=v, k=k, s=src, t=dst, c=c) for v, k, c in cases)


def _core_sql(k: int = 3, passes: int = 12) -> str:
    """More passes than the given tables need; those after the first that changes nothing are left out."""
    steps = ", ".join(_kept(f"p{i}", f"p{i - 1}" if i > 1 else "l", "page_id", "path", k) for i in range(1, passes + 1))
    counts = " UNION ALL ".join(f"SELECT {i} AS pass, count(*) AS edges FROM {f'p{i}' if i else 'l'}" for i in range(passes + 1))
    return f"WITH {S.L}, {steps}, n AS ({counts}), c AS (SELECT *, lag(edges, 1) OVER (ORDER BY pass) AS one, lag(edges, 2) OVER (ORDER BY pass) AS two FROM n) SELECT pass, edges FROM c WHERE pass = 1 OR (pass > 1 AND one < two)"


_SIX = [(v, k) for v in ("all", "com", "net") for k in (2, 5)]
SQL = {
    "links_resolve": f"{_ABS} SELECT page_id, target AS absolute_url FROM ab",
    "links_tld": f"{_LU} SELECT tld, count(*) AS edges, count(DISTINCT page_id) AS sources, count(DISTINCT path) AS targets FROM lt GROUP BY tld",
    "links_min_degree": f"WITH {S.L}, {S.T}, {_kept('a', 'l', 'page_id', 'path', 5)}, {_kept('b', 't', 'doc_id', 'word', 5)} SELECT 'links' AS graph, count(*) AS edges FROM a UNION ALL SELECT 'words', count(*) FROM b",
    "links_kcore": _core_sql(),
    "min_degree_nodes": "WITH x AS (SELECT s_nationkey AS src, c_nationkey AS dst, count(*) AS n FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN supplier ON l_suppkey = s_suppkey JOIN customer ON o_custkey = c_custkey GROUP BY 1, 2), e AS (SELECT src, dst FROM x WHERE n >= 40), k AS (SELECT node FROM (SELECT src AS node, 1 AS o, 0 AS i FROM e UNION ALL SELECT dst, 0, 1 FROM e) GROUP BY 1 HAVING sum(o) >= 8 AND sum(i) >= 8) SELECT src, dst FROM e WHERE src IN (SELECT node FROM k) AND dst IN (SELECT node FROM k)",
    "graph_variants": _stats(f"{_LU}, " + ", ".join(f"{v} AS (SELECT page_id, path FROM lt{'' if v == 'all_links' else f' WHERE tld = {chr(39)}{v}{chr(39)}'})" for v in ("all_links", "com", "net")) + ", " + ", ".join(_kept(f"v_{v}_{k}", "all_links" if v == "all" else v, "page_id", "path", k) for v, k in _SIX), [(v, k, f"v_{v}_{k}") for v, k in _SIX], "page_id", "path"),
    "wl_graph_stats": _stats(f"WITH {S.T}, " + ", ".join(_kept(f"v{k}", "t", "doc_id", "word", k) for k in (2, 5, 10)), [("documents", k, f"v{k}") for k in (2, 5, 10)], "doc_id", "word"),
    "links_dangling": f"{_ABS} SELECT count(DISTINCT target) AS n FROM ab WHERE target NOT IN (SELECT url FROM pages)",
    "host_graph": f"{_LU} SELECT host, path, count(*) AS n FROM lu GROUP BY 1, 2",
    "page_locales": "SELECT list_extract(string_split(regexp_extract(url, '^[a-z]+://([^/?#]*)', 1), '.'), -1) AS tld, regexp_extract(html, 'lang=\"([a-z]+)\"', 1) AS lang, count(*) AS n FROM pages GROUP BY 1, 2",
    "build_graph_stats": f"{_ABS}, al AS (SELECT DISTINCT url AS src, target AS dst FROM ab), {_kept('ed', 'al', 'src', 'dst', 2)} "
    + " UNION ALL ".join(f"SELECT {k} AS least, (SELECT count(*) FROM {t}) AS edges, (SELECT count(*) FROM (SELECT src FROM {t} UNION SELECT dst FROM {t})) AS nodes, (SELECT count(*) FROM {t}) AS out_links, (SELECT count(*) FROM {t}) AS in_links" for k, t in ((1, "al"), (2, "ed"))),
}
QUERIES = {k: globals()[k] for k in SQL}


def _split_counts() -> str:
    from .serving import _split_sql

    return f"WITH {S.L}, {_split_sql('l', 'page_id', 'path')} SELECT role, count(*) AS links, count(DISTINCT page_id) AS sources FROM sp GROUP BY role"


SQL["wl_split"] = _split_counts()
QUERIES["wl_split"] = wl_split
