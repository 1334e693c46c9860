"""Link graphs from raw pages: extraction, resolution, filters, variants, statistics."""

from __future__ import annotations

from collections.abc import Iterator
from urllib.parse import urljoin, urlsplit

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..runtime import generation


def host_of(url: Column) -> Column:
    return F.regexp_extract(url, r"^[a-z]+://([^/?#]*)", 1)


def tld_of(url: Column) -> Column:
    return F.element_at(F.split(host_of(url), r"\."), -1)


def page_language(html: Column) -> Column:
    return F.regexp_extract(html, r'lang="([a-z]+)"', 1)


def extract_links(pages: DataFrame) -> DataFrame:
    """page_id, url and each distinct href of a page."""
    hrefs = F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1)))
    return pages.select("page_id", "url", hrefs.alias("href")).where("href != ''").distinct()


@F.pandas_udf(T.StringType())
def join_url(base: pd.Series, href: pd.Series) -> pd.Series:
    """Absolute http(s) URL without a fragment by the standard library, or null."""

    def one(b: str | None, h: str | None) -> str | None:
        try:
            out = urlsplit(urljoin(b, h.strip()))
        except (ValueError, AttributeError, TypeError):
            return None
        return out._replace(fragment="").geturl() if out.scheme in ("http", "https") and out.hostname else None

    return pd.Series([one(b, h) for b, h in zip(base, href, strict=True)], dtype=object)


def resolve_links(links: DataFrame) -> DataFrame:
    """page_id, url, href and target: root-relative links by expressions, all others in Arrow batches; links that aren't valid go."""
    plain = F.col("href").rlike(r"^/[^/.][^#\s]*$") & ~F.col("href").contains("/.") & ~F.col("href").contains("..")
    origin = F.regexp_extract("url", r"^([a-z]+://[^/?#]*)", 1)
    easy = links.where(plain).withColumn("target", F.concat(origin, F.col("href")))
    other = links.where(~plain).withColumn("target", join_url(F.col("url"), F.col("href")))
    return easy.unionByName(other).where("target is not null")


def filter_tld(edges: DataFrame, tld: str | None, url: str = "url") -> DataFrame:
    return edges if tld is None else edges.where(tld_of(F.col(url)) == tld)


def min_degree(edges: DataFrame, src: str, dst: str, k: int) -> DataFrame:
    """One pass: edges whose source has at least k targets and whose target has at least k sources, counted before the pass."""
    out = edges.groupBy(F.col(src).alias("keep_src")).agg(F.count(F.lit(1)).alias("n_out")).where(F.col("n_out") >= k).select("keep_src")
    back = edges.groupBy(F.col(dst).alias("keep_dst")).agg(F.count(F.lit(1)).alias("n_in")).where(F.col("n_in") >= k).select("keep_dst")
    return edges.join(out, F.col(src) == F.col("keep_src"), "left_semi").join(back, F.col(dst) == F.col("keep_dst"), "left_semi")


def min_degree_of_nodes(edges: DataFrame, src: str, dst: str, k: int) -> DataFrame:
    """The reading for one set of nodes: a node needs k links out and k links in, and an edge both its nodes."""
    both = edges.select(F.col(src).alias("node"), F.lit(1).alias("o"), F.lit(0).alias("i")).union(edges.select(F.col(dst), F.lit(0), F.lit(1)))
    keep = both.groupBy("node").agg(F.sum("o").alias("o"), F.sum("i").alias("i")).where((F.col("o") >= k) & (F.col("i") >= k)).select("node")
    return edges.join(keep, F.col(src) == F.col("node"), "left_semi").join(keep, F.col(dst) == F.col("node"), "left_semi")


def core(edges: DataFrame, src: str, dst: str, k: int) -> Iterator[DataFrame]:
    """The edges after each pass, until a pass changes nothing: the last ones are the true core. A pass that changes something takes an edge away, so there is an end."""
    left = edges.count()
    while True:
        edges, before = generation(min_degree(edges, src, dst, k), "core"), left
        left = edges.count()
        yield edges
        if left == before:
            return


def graph_stats(edges: DataFrame, src: str, dst: str, label: str, k: int) -> DataFrame:
    """variant, k, sources, targets, nodes, edges, mean out-degree, least link counts; one row."""
    one = edges.agg(F.countDistinct(src).alias("sources"), F.countDistinct(dst).alias("targets"), F.count(F.lit(1)).alias("edges"))
    return one.select(F.lit(label).alias("variant"), F.lit(k).alias("k"), "sources", "targets", (F.col("sources") + F.col("targets")).alias("nodes"), "edges", F.round(F.try_divide(F.col("edges").cast("double"), F.col("sources")), 6).alias("mean_degree"))


def variants(links: DataFrame, tlds=(None, "com", "net"), ks=(2, 5)) -> dict[tuple[str, int], DataFrame]:
    """Six graphs: {all, two top-level domains} x {sparse, dense}; links need page_id, url, href."""
    return {(t or "all", k): min_degree(filter_tld(links, t), "page_id", "href", k) for t in tlds for k in ks}


def all_stats(links: DataFrame, **which) -> DataFrame:
    out = None
    for (label, k), edges in variants(links, **which).items():
        one = graph_stats(edges, "page_id", "href", label, k)
        out = one if out is None else out.unionByName(one)
    return out


def write_variants(links: DataFrame, path: str, **which) -> None:
    """All variants as one table, partitioned by variant and k."""
    for (label, k), edges in variants(links, **which).items():
        edges.withColumns({"variant": F.lit(label), "k": F.lit(k)}).write.mode("append").partitionBy("variant", "k").parquet(path)


def dangling(resolved: DataFrame, pages: DataFrame) -> DataFrame:
    """Targets that no crawled page has."""
    known = pages.select(F.col("url").alias("known")).distinct()
    return resolved.select("target").distinct().join(known, F.col("target") == F.col("known"), "left_anti")


def host_graph(links: DataFrame) -> DataFrame:
    return links.groupBy(host_of(F.col("url")).alias("host"), F.col("href").alias("path")).agg(F.count(F.lit(1)).alias("n"))


def build_graph(pages: DataFrame, tld: str | None = None, min_links: int = 10, passes: int | None = 1, rule: str = "bipartite") -> tuple[DataFrame, DataFrame]:
    """(edges src, dst; nodes key, host, tld, out_links, in_links) of absolute links."""
    links = resolve_links(extract_links(filter_tld(pages, tld)))
    edges = links.select(F.col("url").alias("src"), F.col("target").alias("dst")).distinct()
    if rule == "node":
        edges = min_degree_of_nodes(edges, "src", "dst", min_links)
    elif passes is None:
        for edges in core(edges, "src", "dst", min_links):
            pass
    else:
        for _ in range(passes):
            edges = min_degree(edges, "src", "dst", min_links)
    ends = edges.select(F.col("src").alias("key"), F.lit(1).alias("o"), F.lit(0).alias("i")).union(edges.select("dst", F.lit(0), F.lit(1)))
    nodes = ends.groupBy("key").agg(F.sum("o").alias("out_links"), F.sum("i").alias("in_links")).withColumns({"host": host_of(F.col("key")), "tld": tld_of(F.col("key"))})
    return edges, nodes
