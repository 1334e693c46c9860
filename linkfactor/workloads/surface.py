"""Relational and scalar operators that users of the methods need, each on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .. import sources
from ..functions import bf16, cosine, dot, norm, udx
from ..operators import evaluate, graph, smallrank
from ..runtime import scratch
from . import twins as S
from .graphs import links
from .model import columns_of, embeddings, rounded, rows_of
from .serving import _grid, event_split
from .twins import REG, UNOBSERVED


def table(s, d, name: str) -> DataFrame:
    return sources.read_table(s, d, name)


def op_scan_pruned(s, d):
    """Two columns and a pushed filter."""
    return table(s, d, "lineitem").where((F.col("l_quantity") >= 45) & (F.col("l_returnflag") == "R")).select("l_orderkey", "l_partkey")


def op_semi_keep(s, d):
    busy = table(s, d, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n")).where("n >= 12")
    return table(s, d, "customer").join(busy, F.col("c_custkey") == F.col("o_custkey"), "left_semi").select("c_custkey", "c_name")


def op_anti_exclude(s, d):
    x = event_split(s, d)
    return x.select("row_id", "col_id").join(x.where("role = 'given'").select("row_id", "col_id"), ["row_id", "col_id"], "left_anti")


def op_left_outer(s, d):
    n = table(s, d, "orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))
    return table(s, d, "customer").join(n, F.col("c_custkey") == F.col("o_custkey"), "left").select("c_custkey", F.coalesce("n", F.lit(0)).alias("n_orders"))


def op_full_outer(s, d):
    a = table(s, d, "customer").groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("customers"))
    b = table(s, d, "supplier").groupBy("s_nationkey").agg(F.count(F.lit(1)).alias("suppliers"))
    return a.join(b, F.col("c_nationkey") == F.col("s_nationkey"), "full").select(F.coalesce("c_nationkey", "s_nationkey").alias("nation"), F.coalesce("customers", F.lit(0)).alias("customers"), F.coalesce("suppliers", F.lit(0)).alias("suppliers"))


def op_range_join(s, d):
    """Parts to the price band that holds them; the bands are eight rows."""
    bands = s.createDataFrame([(i, 900.0 + 150 * i, 900.0 + 150 * (i + 1)) for i in range(8)], "band int, low double, high double")
    x = table(s, d, "part").select("p_partkey", "p_retailprice").join(F.broadcast(bands), (F.col("p_retailprice") >= F.col("low")) & (F.col("p_retailprice") < F.col("high")))
    return x.groupBy("band").agg(F.count(F.lit(1)).alias("n"), F.min("p_partkey").alias("first_part"))


def op_asof(s, d):
    """For each purchase the last click of the user at or before it: one pass over the events in order, without a join."""
    e = table(s, d, "events").where("event_type in ('click', 'purchase')").select("event_id", "user_id", "ts", "event_type")
    so_far = Window.partitionBy("user_id").orderBy("ts", F.when(F.col("event_type") == "click", 0).otherwise(1), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    seen = e.withColumn("click_id", F.last(F.when(F.col("event_type") == "click", F.col("event_id")), ignorenulls=True).over(so_far))
    return seen.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "click_id")


def _locales(s, d) -> DataFrame:
    return table(s, d, "pages").select(graph.tld_of(F.col("url")).alias("tld"), graph.page_language(F.col("html")).alias("lang"))


def op_grouping_sets(s, d):
    _locales(s, d).createOrReplaceTempView("page_locales_view")
    return s.sql("SELECT coalesce(tld, 'any') AS tld, coalesce(lang, 'any') AS lang, count(*) AS n FROM page_locales_view GROUP BY GROUPING SETS ((tld), (lang))")


def op_rollup(s, d):
    return _locales(s, d).rollup("tld", "lang").agg(F.count(F.lit(1)).alias("n")).select(F.coalesce("tld", F.lit("any")).alias("tld"), F.coalesce("lang", F.lit("any")).alias("lang"), "n")


def op_cube(s, d):
    return _locales(s, d).cube("tld", "lang").agg(F.count(F.lit(1)).alias("n")).select(F.coalesce("tld", F.lit("any")).alias("tld"), F.coalesce("lang", F.lit("any")).alias("lang"), "n")


def op_pivot_grid(s, d):
    """Losses by regularization and three of the weights."""
    named = rounded(_grid(s, d), but=("reg", "unobserved")).withColumn("w", F.when(F.col("unobserved") == 1e-3, "high").when(F.col("unobserved") == 5e-5, "mid").when(F.col("unobserved") == 1e-6, "low"))
    return named.groupBy("reg").pivot("w", ["high", "mid", "low"]).agg(F.first("loss"))


def op_approx_distinct(s, d):
    return sources.purchases(s, d).agg(F.approx_count_distinct("col_id", 0.02).alias("n"))


def op_percentiles(s, d):
    n = sources.purchases(s, d).groupBy("row_id").agg(F.count(F.lit(1)).alias("n"))
    return rounded(n.agg(*[F.percentile("n", F.lit(q)).alias(f"p{round(100 * q)}") for q in (0.1, 0.5, 0.9)]))


def op_degree_histogram(s, d):
    n = sources.purchases(s, d).groupBy("row_id").agg(F.count(F.lit(1)).alias("n"))
    return n.groupBy(F.floor(F.col("n") / 8).cast("int").alias("bin")).agg(F.count(F.lit(1)).alias("n_rows"))


def _usage(s, d) -> DataFrame:
    return sources.events_as_observations(s, d).groupBy("col_id").agg(F.count(F.lit(1)).alias("uses"))


def op_running_coverage(s, d):
    """Share of all observations that the most used columns cover, cumulatively (columns are few: one window)."""
    up = Window.orderBy(F.desc("uses"), "col_id").rowsBetween(Window.unboundedPreceding, 0)
    return rounded(_usage(s, d).select("col_id", (F.sum("uses").over(up) / F.sum("uses").over(Window.partitionBy())).alias("coverage")))


def op_degree_ntile(s, d):
    x = table(s, d, "supplier").select("s_nationkey", "s_suppkey", "s_acctbal")
    return x.select("s_suppkey", F.ntile(4).over(Window.partitionBy("s_nationkey").orderBy("s_acctbal", "s_suppkey")).alias("quarter"))


def op_rank_dense(s, d):
    x = sources.events_as_observations(s, d)
    w = Window.partitionBy("row_id").orderBy(F.desc("y"))
    return x.select("row_id", "col_id", F.rank().over(w).alias("rank"), F.dense_rank().over(w).alias("dense"))


def op_lag_loss(s, d):
    """Fall of the loss from epoch to epoch."""
    from .model import train_loss_curve

    w = Window.partitionBy(F.lit(1)).orderBy("epoch")
    return rounded(train_loss_curve(s, d).select("epoch", (F.lag("loss").over(w) - F.col("loss")).alias("fall")), 3)


def op_sort_limit(s, d):
    return _usage(s, d).orderBy(F.desc("uses"), "col_id").limit(10)


def op_union_variants(s, d):
    a, b = links(s, d).where(graph.tld_of(F.col("url")) == "com"), links(s, d).where(graph.tld_of(F.col("url")) == "net")
    return a.select("href").union(b.select("href")).distinct()


def op_intersect(s, d):
    a, b = links(s, d).where(graph.tld_of(F.col("url")) == "com"), links(s, d).where(graph.tld_of(F.col("url")) == "net")
    return a.select("href").intersect(b.select("href"))


def op_except(s, d):
    x = event_split(s, d).select("row_id", "col_id", "role")
    return x.where("role != 'train'").select("row_id", "col_id").exceptAll(x.where("role = 'given'").select("row_id", "col_id"))


def op_stratified_sample(s, d):
    """A tenth of each event type by hash."""
    from ..functions import hash_bucket

    e = table(s, d, "events").where(hash_bucket(10, F.lit("st"), F.col("event_type"), F.col("event_id").cast("string")) == 0)
    return e.groupBy("event_type").agg(F.count(F.lit(1)).alias("n"), F.min("event_id").alias("first_id"))


def op_negative_sample(s, d):
    """One hashed unseen column for each user of the nearly full event matrix."""
    from ..functions import hash_unit

    x = sources.events_as_observations(s, d)
    pairs = x.select("row_id").distinct().crossJoin(x.select("col_id").distinct()).join(x.select("row_id", "col_id"), ["row_id", "col_id"], "left_anti")
    return pairs.groupBy("row_id").agg(F.min_by("col_id", F.struct(hash_unit(F.lit("n"), F.col("row_id").cast("string"), F.lit("|"), F.col("col_id").cast("string")), "col_id")).alias("col_id"))


def fn_string(s, d):
    p = table(s, d, "pages")
    return p.select("page_id", F.lower(graph.host_of(F.col("url"))).alias("host"), F.size(F.split("url", "/")).alias("parts"), F.substring(F.md5("url"), 1, 6).alias("mark"), F.levenshtein(F.substring("url", 1, 24), F.lit("https://www.example.com/")).alias("edit"), F.concat_ws("|", F.length("url").cast("string"), graph.tld_of(F.col("url"))).alias("joined"))


def fn_date(s, d):
    o = table(s, d, "orders")
    return o.select("o_orderkey", F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q"), F.datediff(F.lit("2030-01-01").cast("date"), F.col("o_orderdate")).alias("age"), F.date_format(F.date_trunc("month", "o_orderdate"), "yyyy-MM-dd").alias("month"))


def fn_math(s, d):
    p = table(s, d, "part").select("p_partkey", F.col("p_retailprice").alias("x"))
    return rounded(p.select("p_partkey", F.sqrt("x").alias("root"), F.log2("x").alias("bits"), F.pow("x", F.lit(1.5)).alias("power"), F.rint("x").alias("even"), F.pmod(F.col("p_partkey") * 7919, F.lit(101)).alias("hashed"), bf16(F.col("x")).alias("short")), 5)


def fn_array(s, d):
    v = embeddings(s, d)
    unit = F.transform(F.slice("vec", 1, 8), lambda x: x * 2)
    other = F.reverse("vec")
    return rounded(v.select("id", dot("vec", other).alias("mirror"), norm("vec").alias("length"), cosine("vec", other).alias("cos"), F.aggregate(unit, F.lit(0.0), lambda a, x: a + x).alias("head"), F.size(F.filter("vec", lambda x: x > 0)).alias("positive"), F.exists("vec", lambda x: x > 0.3).alias("large")))


def fn_map(s, d):
    """Sparse rows as maps: size, sum over a filtered map, and the sparse dot product of users 0 and 1's neighbours."""
    m = sources.events_as_observations(s, d).groupBy("row_id").agg(F.map_from_entries(F.collect_list(F.struct("col_id", "y"))).alias("cells"))
    first = m.where("row_id = 1").select(F.col("cells").alias("other"))
    x = m.crossJoin(F.broadcast(first))
    both = F.map_zip_with("cells", "other", lambda k, a, b: F.coalesce(a, F.lit(0.0)) * F.coalesce(b, F.lit(0.0)))
    total = lambda arr: F.aggregate(arr, F.lit(0.0), lambda a, v: a + v)
    return x.select("row_id", F.size("cells").alias("n"), total(F.map_values(F.map_filter("cells", lambda k, v: k < 50))).alias("low_sum"), total(F.map_values(both)).alias("dot_with_1"))


def fn_json(s, d):
    e = table(s, d, "events")
    return e.select("event_id", F.from_json("props", "k INT")["k"].alias("k"), F.to_json(F.struct(F.col("event_type").alias("type"))).alias("back"))


def udf_urljoin(s, d):
    x = graph.extract_links(table(s, d, "pages"))
    return x.select("page_id", graph.join_url(F.col("url"), F.col("href")).alias("absolute_url"))


def udaf_gram(s, d):
    """Gram of the first four coordinates by label, from the registered aggregate."""
    udx.register(s)
    table(s, d, "embeddings").select("label", F.slice(F.col("embedding").cast("array<double>"), 1, 4).alias("v")).createOrReplaceTempView("label_vectors_view")
    g = s.sql("SELECT label, gram_of(v) AS g FROM label_vectors_view GROUP BY label")
    return rounded(g.select("label", *[F.get("g", n).alias(f"g{i}{j}") for n, (i, j) in enumerate(S.pairs(4))]), 5)


def udtf_links(s, d):
    udx.register(s)
    table(s, d, "pages").createOrReplaceTempView("pages_udtf_view")
    return s.sql("SELECT page_id, x.link, x.place FROM pages_udtf_view, LATERAL links_of(html) x")


def udtf_segments(s, d):
    udx.register(s)
    lists = sources.events_as_observations(s, d).groupBy("row_id").agg(F.array_sort(F.collect_list("col_id")).alias("ids"))
    lists.createOrReplaceTempView("histories_view")
    return s.sql("SELECT row_id, x.seg_no, x.n_valid, x.col_ids[0] AS first_id FROM histories_view, LATERAL segments_of(ids, 8) x")


def io_roundtrip(s, d):
    """One table through four formats: rows and a checksum of each."""
    base, folder, out = sources.weighted_purchases(s, d), scratch(s, "formats"), None
    for kind in ("parquet", "orc", "json", "csv"):
        base.write.format(kind).save(f"{folder}/{kind}")
        back = s.read.schema(base.schema).format(kind).load(f"{folder}/{kind}")
        one = back.agg(F.count(F.lit(1)).alias("n"), F.sum("row_id").alias("rows_sum"), F.sum("y").alias("y_sum")).select(F.lit(kind).alias("format"), "n", "rows_sum", "y_sum")
        out = one if out is None else out.unionByName(one)
    return out


def io_crawl_source(s, d):
    """Pages' links written as crawl metadata (JSON lines) and read back by the Python data source."""
    from ..sources.crawl import read_crawl

    folder = scratch(s, "crawl")
    links = sources.link_observations(s, d).groupBy(F.col("page_id").cast("string").alias("url")).agg(F.collect_list("path").alias("links"))
    links.write.json(folder)
    return read_crawl(s, folder).select(F.col("url").cast("bigint").alias("page_id"), "href")


def io_bucketed(s, d):
    """Factors as a bucketed, sorted table; a later join on id needs no exchange."""
    name = "linkfactor_bucketed_columns"
    h = columns_of(sources.purchases(s, d))
    s.sql(f"DROP TABLE IF EXISTS {name}")
    h.write.mode("overwrite").bucketBy(4, "id").sortBy("id").option("path", scratch(s, "bucketed")).saveAsTable(name)
    return s.table(name).groupBy((F.col("id") % 10).alias("last")).agg(F.count(F.lit(1)).alias("n"))


def star_revenue_and_score(s, d):
    """Revenue of each brand beside the mean predicted score of its sold cells."""
    p = sources.purchases(s, d)
    scored = smallrank.predict(p.select("row_id", "col_id"), rows_of(p), columns_of(p))
    part = table(s, d, "part").select("p_partkey", "p_brand")
    score = scored.join(part, F.col("col_id") == F.col("p_partkey")).groupBy("p_brand").agg(F.avg("score").alias("mean_score"))
    sold = table(s, d, "lineitem").join(part, F.col("l_partkey") == F.col("p_partkey")).groupBy("p_brand").agg(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))).alias("revenue"))
    both = sold.join(score, "p_brand").select("p_brand", F.round("revenue", 2).alias("revenue"), "mean_score")
    return rounded(both, but=("revenue",))


def star_nation_factors(s, d):
    p = sources.purchases(s, d)
    w = smallrank.refit(p, columns_of(p), REG, UNOBSERVED)
    c = table(s, d, "customer").select("c_custkey", "c_nationkey").join(table(s, d, "nation").select("n_nationkey", "n_name"), F.col("c_nationkey") == F.col("n_nationkey"))
    return rounded(w.join(c, F.col("id") == F.col("c_custkey")).groupBy("n_name").agg(F.avg("f0").alias("m0"), F.avg("f1").alias("m1"), F.count(F.lit(1)).alias("n")))


def most_popular(s, d):
    """The popularity list for three users, given cells left out."""
    x = event_split(s, d)
    ranked = evaluate.popularity_topk(x.where("role = 'train'"), x.where("role = 'given'"), 5, exclude=x.where("role = 'given'"))
    return ranked.select("row_id", "col_id", "rank")


def _sql_split() -> str:
    from .serving import _split_sql

    return f"WITH {S.E}, {_split_sql('e', 'row_id', 'col_id', ', y')}"


def _grid_cte() -> str:
    from .serving import _grid_sql

    return _grid_sql()


_LOC = "x AS (SELECT list_extract(string_split(regexp_extract(url, '^[a-z]+://([^/?#]*)', 1), '.'), -1) AS tld, regexp_extract(html, 'lang=\"([a-z]+)\"', 1) AS lang FROM pages)"
_HREF = f"WITH {S.L}, lt AS (SELECT path AS href, list_extract(string_split(regexp_extract(url, '^[a-z]+://([^/?#]*)', 1), '.'), -1) AS tld FROM l JOIN pages ON l.page_id = pages.page_id)"
_V = "v AS (SELECT vec_id AS id, i, embedding[i + 1]::double AS x, embedding[64 - i]::double AS z FROM embeddings, (SELECT unnest(range(0, 64)) AS i))"
_HP = f"WITH {S.P}, {S.factors('h', 'p', 'col_id')}"

SQL = {
    "op_scan_pruned": "SELECT l_orderkey, l_partkey FROM lineitem WHERE l_quantity >= 45 AND l_returnflag = 'R'",
    "op_semi_keep": "SELECT c_custkey, c_name FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders GROUP BY 1 HAVING count(*) >= 12)",
    "op_anti_exclude": f"{_sql_split()} SELECT row_id, col_id FROM sp WHERE role <> 'given'",
    "op_left_outer": "SELECT c_custkey, count(o_orderkey) AS n_orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY 1",
    "op_full_outer": "SELECT coalesce(a.k, b.k) AS nation, coalesce(a.n, 0) AS customers, coalesce(b.n, 0) AS suppliers FROM (SELECT c_nationkey AS k, count(*) AS n FROM customer GROUP BY 1) a FULL JOIN (SELECT s_nationkey AS k, count(*) AS n FROM supplier GROUP BY 1) b ON a.k = b.k",
    "op_range_join": "SELECT floor((p_retailprice - 900.0::double) / 150.0::double)::integer AS band, count(*) AS n, min(p_partkey) AS first_part FROM part WHERE p_retailprice >= 900 AND p_retailprice < 2100 GROUP BY 1",
    "op_asof": "WITH e AS (SELECT event_id, user_id, ts, event_type FROM events WHERE event_type IN ('click', 'purchase')), x AS (SELECT p.event_id AS purchase_id, c.event_id AS click_id, row_number() OVER (PARTITION BY p.event_id ORDER BY c.ts DESC, c.event_id DESC) AS r FROM e p LEFT JOIN e c ON c.user_id = p.user_id AND c.event_type = 'click' AND c.ts <= p.ts WHERE p.event_type = 'purchase') SELECT purchase_id, click_id FROM x WHERE r = 1",
    "op_grouping_sets": f"WITH {_LOC} SELECT coalesce(tld, 'any') AS tld, coalesce(lang, 'any') AS lang, count(*) AS n FROM x GROUP BY GROUPING SETS ((tld), (lang))",
    "op_rollup": f"WITH {_LOC} SELECT coalesce(tld, 'any') AS tld, coalesce(lang, 'any') AS lang, count(*) AS n FROM x GROUP BY ROLLUP (tld, lang)",
    "op_cube": f"WITH {_LOC} SELECT coalesce(tld, 'any') AS tld, coalesce(lang, 'any') AS lang, count(*) AS n FROM x GROUP BY CUBE (tld, lang)",
    "op_pivot_grid": f"{_grid_cte()} SELECT reg, max(CASE WHEN unobserved = 0.001::double THEN loss END) AS high, max(CASE WHEN unobserved = 5e-05::double THEN loss END) AS mid, max(CASE WHEN unobserved = 1e-06::double THEN loss END) AS low FROM gr GROUP BY reg",
    "op_percentiles": f"WITH {S.P}, n AS (SELECT count(*) AS n FROM p GROUP BY row_id) SELECT round(quantile_cont(n, 0.1), 6) AS p10, round(quantile_cont(n, 0.5), 6) AS p50, round(quantile_cont(n, 0.9), 6) AS p90 FROM n",
    "op_degree_histogram": f"WITH {S.P}, n AS (SELECT count(*) AS n FROM p GROUP BY row_id) SELECT floor(n / 8.0::double)::integer AS bin, count(*) AS n_rows FROM n GROUP BY 1",
    "op_running_coverage": f"WITH {S.E}, u AS (SELECT col_id, count(*) AS uses FROM e GROUP BY 1) SELECT col_id, round(sum(uses) OVER (ORDER BY uses DESC, col_id)::double / (SELECT sum(uses) FROM u)::double, 6) + 0.0 AS coverage FROM u",
    "op_degree_ntile": "SELECT s_suppkey, ntile(4) OVER (PARTITION BY s_nationkey ORDER BY s_acctbal, s_suppkey)::integer AS quarter FROM supplier",
    "op_rank_dense": f"WITH {S.E} SELECT row_id, col_id, rank() OVER (PARTITION BY row_id ORDER BY y DESC)::integer AS rank, dense_rank() OVER (PARTITION BY row_id ORDER BY y DESC)::integer AS dense FROM e",
    "op_lag_loss": "",
    "op_sort_limit": f"WITH {S.E} SELECT col_id, count(*) AS uses FROM e GROUP BY 1 ORDER BY uses DESC, col_id LIMIT 10",
    "op_union_variants": f"{_HREF} SELECT DISTINCT href FROM lt WHERE tld IN ('com', 'net')",
    "op_intersect": f"{_HREF} SELECT href FROM lt WHERE tld = 'com' INTERSECT SELECT href FROM lt WHERE tld = 'net'",
    "op_except": f"{_sql_split()} SELECT row_id, col_id FROM sp WHERE role = 'hidden'",
    "op_stratified_sample": "SELECT event_type, count(*) AS n, min(event_id) AS first_id FROM events WHERE ('0x' || substr(md5('st' || event_type || event_id), 1, 8))::bigint % 10 = 0 GROUP BY 1",
    "op_negative_sample": f"WITH {S.E}, q AS (SELECT r.row_id, c.col_id FROM (SELECT DISTINCT row_id FROM e) r, (SELECT DISTINCT col_id FROM e) c WHERE NOT EXISTS (SELECT 1 FROM e WHERE e.row_id = r.row_id AND e.col_id = c.col_id)), z AS (SELECT *, row_number() OVER (PARTITION BY row_id ORDER BY ('0x' || substr(md5('n' || row_id || '|' || col_id), 1, 8))::bigint, col_id) AS k FROM q) SELECT row_id, col_id FROM z WHERE k = 1",
    "fn_string": "SELECT page_id, lower(regexp_extract(url, '^[a-z]+://([^/?#]*)', 1)) AS host, len(string_split(url, '/'))::integer AS parts, substr(md5(url), 1, 6) AS mark, levenshtein(substr(url, 1, 24), 'https://www.example.com/')::integer AS edit, length(url) || '|' || list_extract(string_split(regexp_extract(url, '^[a-z]+://([^/?#]*)', 1), '.'), -1) AS joined FROM pages",
    "fn_date": "SELECT o_orderkey, year(o_orderdate)::integer AS y, quarter(o_orderdate)::integer AS q, date_diff('day', o_orderdate::date, DATE '2030-01-01')::integer AS age, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month FROM orders",
    "fn_math": f"SELECT p_partkey, round(sqrt(x), 5) + 0.0 AS root, round(log2(x), 5) + 0.0 AS bits, round(pow(x, 1.5::double), 5) + 0.0 AS power, round_even(x::double, 0) + 0.0 AS even, (p_partkey * 7919) % 101 AS hashed, round({S.bf16('x')}, 5) + 0.0 AS short FROM (SELECT p_partkey, p_retailprice AS x FROM part)",
    "fn_array": f"WITH {_V}, a AS (SELECT id, sum(x * z) AS m, sqrt(sum(x * x)) AS n, sum(CASE WHEN i < 8 THEN 2 * x ELSE 0.0::double END) AS hd, sum(CASE WHEN x > 0 THEN 1 ELSE 0 END) AS ps, max(x) AS mx FROM v GROUP BY id) SELECT id, round(m, 6) + 0.0 AS mirror, round(n, 6) + 0.0 AS length, round(m / (n * n), 6) + 0.0 AS cos, round(hd, 6) + 0.0 AS head, ps::integer AS positive, mx > 0.3::double AS large FROM a",
    "fn_map": f"WITH {S.E} SELECT a.row_id, count(*)::integer AS n, sum(CASE WHEN a.col_id < 50 THEN a.y ELSE 0.0::double END) AS low_sum, sum(a.y * coalesce(b.y, 0.0::double)) AS dot_with_1 FROM e a LEFT JOIN e b ON b.row_id = 1 AND a.col_id = b.col_id GROUP BY a.row_id",
    "fn_json": "SELECT event_id, json_extract_string(props, '$.k')::integer AS k, '{\"type\":\"' || event_type || '\"}' AS back FROM events",
    "udf_urljoin": f"WITH {S.L} SELECT l.page_id, regexp_extract(url, '^([a-z]+://[^/?#]*)', 1) || path AS absolute_url FROM l JOIN pages ON l.page_id = pages.page_id",
    "udaf_gram": "WITH v AS (SELECT label, embedding[1]::double AS x0, embedding[2]::double AS x1, embedding[3]::double AS x2, embedding[4]::double AS x3 FROM embeddings) SELECT label, " + ", ".join(f"round(sum(x{i} * x{j}), 5) + 0.0 AS g{i}{j}" for i, j in S.pairs(4)) + " FROM v GROUP BY label",
    "udtf_links": "WITH x AS (SELECT page_id, regexp_extract_all(html, 'href=\"([^\"]*)\"', 1) AS ls FROM pages) SELECT page_id, ls[i + 1] AS link, i::integer AS place FROM (SELECT page_id, ls, unnest(range(0, len(ls))) AS i FROM x)",
    "udtf_segments": f"WITH {S.E}, o AS (SELECT row_id, col_id, row_number() OVER (PARTITION BY row_id ORDER BY col_id) - 1 AS place FROM e) SELECT row_id, floor(place / 8.0::double)::integer AS seg_no, count(*)::integer AS n_valid, min(col_id) AS first_id FROM o GROUP BY 1, 2",
    "io_roundtrip": "WITH w AS (SELECT o_custkey AS row_id, l_partkey AS col_id, sum(l_quantity) AS y FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1, 2), t AS (SELECT count(*) AS n, sum(row_id)::bigint AS rows_sum, sum(y) AS y_sum FROM w) SELECT f AS format, t.* FROM t, (SELECT unnest(['parquet', 'orc', 'json', 'csv']) AS f)",
    "io_crawl_source": f"WITH {S.L} SELECT page_id, path AS href FROM l",
    "io_bucketed": f"{_HP} SELECT id % 10 AS last, count(*) AS n FROM h GROUP BY 1",
    "star_revenue_and_score": f"{_HP}, {S.factors('w', 'p', 'row_id')}, a AS (SELECT p_brand, avg(w.f0 * h.f0 + w.f1 * h.f1) AS mean_score FROM p JOIN w ON row_id = w.id JOIN h ON col_id = h.id JOIN part ON col_id = p_partkey GROUP BY 1), b AS (SELECT p_brand, sum(l_extendedprice * (1 - l_discount)) AS revenue FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY 1) SELECT a.p_brand, round(revenue, 2) AS revenue, round(mean_score, 6) + 0.0 AS mean_score FROM a JOIN b ON a.p_brand = b.p_brand",
    "star_nation_factors": f"{_HP}, {S.refit('w', 'p', 'h')} SELECT n_name, round(avg(f0), 6) + 0.0 AS m0, round(avg(f1), 6) + 0.0 AS m1, count(*) AS n FROM w JOIN customer ON id = c_custkey JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name",
    "most_popular": f"{_sql_split()}, gv AS (SELECT row_id, col_id FROM sp WHERE role = 'given'), us AS (SELECT col_id, count(*) AS uses FROM sp WHERE role = 'train' GROUP BY 1), rk AS (SELECT q.row_id, us.col_id, row_number() OVER (PARTITION BY q.row_id ORDER BY uses DESC, us.col_id) AS rank FROM (SELECT DISTINCT row_id FROM gv) q, us WHERE NOT EXISTS (SELECT 1 FROM gv WHERE gv.row_id = q.row_id AND gv.col_id = us.col_id)) SELECT row_id, col_id, rank::integer AS rank FROM rk WHERE rank <= 5",
}


def _lag_sql() -> str:
    from .model import SQL as model_sql

    return f"SELECT epoch, round(lag(loss) OVER (ORDER BY epoch) - loss, 3) + 0.0 AS fall FROM ({model_sql['train_loss_curve']})"


SQL["op_lag_loss"] = _lag_sql()
QUERIES = {k: globals()[k] for k in [*SQL, "op_approx_distinct"]}
