"""Mixing and URL filters on small tables."""

import math

from pyspark.sql import functions as F

from linkfactor.llm import mixing, urls
from linkfactor.llm.cluster import table
from linkfactor.llm.queries_native import op7_url_filter

SMALL = "/root/testdata/sf0.001"


def test_mixing_counts_follow_poisson(spark):
    docs = spark.range(6000).select(F.col("id").alias("doc_id"), F.when(F.col("id") % 3 == 0, "a").otherwise("b").alias("source"), F.lit(1).alias("copy"))
    out = mixing.mix_sources(docs, {"a": 3, "b": 1}, size=12000)
    got = {r.source: r.n for r in out.groupBy("source").agg(F.count("*").alias("n")).collect()}
    assert abs(got["a"] - 9000) < 5 * math.sqrt(9000) and abs(got["b"] - 3000) < 5 * math.sqrt(3000)
    zero = docs.where("source = 'b'").count() - out.where("source = 'b'").select("doc_id").distinct().count()
    assert abs(zero - 4000 * math.exp(-0.75)) < 5 * math.sqrt(4000 * 0.25)
    assert out.select("doc_id", "copy").distinct().count() == out.count()


def test_mixing_odd_rows(spark):
    docs = spark.createDataFrame([(None, "x", None), (1, None, "a"), (1, None, "a"), (2, "", "b")], "doc_id long, text string, source string")
    assert mixing.mix_sources(docs.limit(0)).count() == 0
    assert set(mixing.mix_sources(docs, {None: 1.0}, size=40).select("source").distinct().collect()) == {(None,)}
    both = mixing.mix_sources(docs, {"a": 1.0}, size=40).groupBy("doc_id", "copy").count().collect()
    assert {r["count"] for r in both} == {2}
    assert mixing.mix_sources(docs, {}).count() == 0


def test_url_parts_and_rules(spark):
    rows = [(1, "http://A.example.ORG/es/x?q=/"), (2, "https://x.com/fr/1#a"), (3, "x.com/fr/"), (4, None), (5, "ftp://com"), (6, "http://example.org/en/12"), (7, "http://notexample.org/es/"), (8, "http://h?x://y/z"), (9, "http://a\nb.net/p\nq")]
    pages = spark.createDataFrame([(*r, "z") for r in rows], "page_id long, url string, host string")
    none = pages.select(F.lit("q").alias("key")).limit(0)
    got = {r.page_id: r for r in urls.judge_urls(pages, none).collect()}
    assert (got[1].host, got[1].path, got[1].rule, got[1].verdict) == ("a.example.org", "/es/x", "example.org/es/", "block")
    assert (got[2].rule, got[2].verdict) == ("com/fr/", "allow")
    assert (got[3].host, got[4].host, got[5].path, got[5].rule) == ("", "", "", None)
    assert got[6].rule == "example.org/en/1" and got[7].rule == "org/" and got[8].host == "h" and got[9].path == "/p\nq"


def test_cascade_is_exact(spark):
    universe = spark.range(5000).select(F.concat(F.lit("k"), F.col("id")).alias("key"))
    listed = universe.where("crc32(key) % 7 = 0")
    for frame in (urls.build_cascade(universe, listed), urls.build_cascade(universe, listed, word_limit=200)):
        wrong = frame.is_listed(universe, F.col("key"), "hit").where("hit != (crc32(key) % 7 = 0)")
        assert wrong.count() == 0
    built = urls.build_cascade(universe, listed, word_limit=200)
    assert len(built.shards) == 3 and all(64 * 200 >= bits for levels in built.shards for _, _, bits in levels)
    assert len(urls.build_cascade(universe, listed).shards[0]) >= 2
    twice = spark.createDataFrame([(None, "http://a.net/k"), (1, "http://a.net/k"), (1, "http://a.net/k"), (2, "http://b.net/")], "page_id long, url string")
    got = sorted((r.page_id or 0, r.verdict) for r in urls.judge_urls(twice, spark.createDataFrame([("a.net/k",), (None,), ("a.net/k",)], "key string")).collect())
    assert got == [(0, "block"), (1, "block"), (1, "block"), (2, "allow")]
    assert urls.build_cascade(universe, listed.limit(0)).is_listed(universe, F.col("key"), "hit").where("hit").count() == 0


def test_op7_covers_all_pages(spark):
    assert op7_url_filter(spark, SMALL).count() == table(spark, SMALL, "pages").count()
