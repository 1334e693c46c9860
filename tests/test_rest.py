"""Graphs, splits, retrieval, measures, streams, plan shapes and the registry."""

import pytest
from pyspark.sql import functions as F

import __spark_entry__
from linkfactor import sources
from linkfactor.operators import evaluate, graph, topk
from linkfactor.operators.split import strong_split
from linkfactor.streaming import events as st
from linkfactor.workloads import streams
from linkfactor.workloads.model import embeddings

SMALL = "/root/testdata/sf0.001"


def test_links_of_all_kinds(spark):
    page = '<a href="/x">a</a><a href="">e</a><a href="#f">f</a><a href="mailto:a@b">m</a><a href="//h.com/y">s</a><a href="../z">u</a><a href="javascript:1">j</a><a href="/x">again</a><a href="q?a=1#b">q</a><a href="/a/../b">d</a>'
    pages = spark.createDataFrame([(1, "https://site.org/d/e/p", page), (2, None, None), (3, "https://x.de", "none")], "page_id long, url string, html string")
    found = {r.href: r.target for r in graph.resolve_links(graph.extract_links(pages)).collect()}
    assert found == {"/x": "https://site.org/x", "#f": "https://site.org/d/e/p", "//h.com/y": "https://h.com/y", "../z": "https://site.org/d/z", "q?a=1#b": "https://site.org/d/e/q?a=1", "/a/../b": "https://site.org/b"}


def test_min_degree_passes_and_core(spark):
    edges = spark.createDataFrame([(a, b) for a in range(4) for b in range(4) if a != b] + [(9, 0), (9, 8), (7, 8)], "s long, t long")
    once = graph.min_degree(edges, "s", "t", 2)
    assert {(r.s, r.t) for r in once.collect()} == {(a, b) for a in range(4) for b in range(4) if a != b} | {(9, 0), (9, 8)}
    last = list(graph.core(edges, "s", "t", 2))[-1]
    assert last.groupBy("t").count().agg(F.min("count")).first()[0] >= 2
    both = graph.min_degree_of_nodes(edges, "s", "t", 3)
    assert {(r.s, r.t) for r in both.collect()} == {(a, b) for a in range(4) for b in range(4) if a != b}
    assert graph.min_degree(edges.limit(0), "s", "t", 2).count() == 0


def test_split_is_disjoint_and_hides_a_quarter(spark):
    edges = spark.range(400).select((F.col("id") % 40).alias("s"), F.col("id").alias("t"))
    split = strong_split(edges, "s", "t", train=0.8).cache()
    roles = {r.s: set() for r in split.collect()}
    for r in split.collect():
        roles[r.s].add(r.role)
    assert all(x in ({"train"}, {"given", "hidden"}) for x in roles.values()) and split.count() == 400
    assert {r["count"] for r in split.where("role = 'hidden'").groupBy("s").count().collect()} == {2}
    one = strong_split(spark.range(30).select(F.col("id").alias("s"), F.lit(1).alias("t")), "s", "t")
    assert one.where("role = 'hidden'").count() == 0


def test_recall_by_hand(spark):
    hidden = spark.createDataFrame([(1, "a"), (1, "b"), (1, "d")], "row_id long, col_id string")
    ranked = spark.createDataFrame([(1, "a", 1), (1, "c", 2)], "row_id long, col_id string, rank int")
    row = evaluate.recall(ranked, hidden, (2,)).first()
    assert row.recall_truth == pytest.approx(1 / 3) and row.recall_capped == pytest.approx(1 / 2)
    m = evaluate.ranking_measures(ranked, hidden, 2).first()
    assert m.precision == 0.5 and m.mrr == 1.0 and m.ndcg == pytest.approx(1 / (1 + 0.6309297535714575))


def test_topk_ties_blocks_and_exclusion(spark):
    v = spark.createDataFrame([(i, [1.0, float(i % 2)]) for i in range(10)], "id long, vec array<double>")
    for a, b in ((1, 1), (3, 4)):
        got = topk.topk_exact(v, v, 3, 2, row_blocks=a, col_blocks=b).where("row_id = 1").orderBy("rank").collect()
        assert [(r.col_id, r.rank) for r in got] == [(1, 1), (3, 2), (5, 3)]
    gone = spark.createDataFrame([(1, 1), (1, 5)], "row_id long, col_id long")
    left = topk.topk_exact(v, v, 3, 2, exclude=gone).where("row_id = 1").orderBy("rank").collect()
    assert [r.col_id for r in left] == [3, 7, 9]
    assert topk.topk_exact(v.limit(0), v, 3, 2).count() == 0


def test_topk_over_many_blocks_is_exact(spark):
    import numpy as np

    from linkfactor.operators.factors import init_vectors

    v = init_vectors(spark.range(600), 8).cache()
    x = np.stack([r.vec for r in v.orderBy("id").collect()])
    got = {}
    for r in topk.topk_exact(v.where("id < 40"), v, 30, 8, row_blocks=3, col_blocks=5).collect():
        got.setdefault(r.row_id, set()).add(r.col_id)
    assert all(got[i] == set(np.argsort(-(x @ x[i]))[:30].tolist()) for i in range(40))


@pytest.mark.parametrize("how", ["lsh", "ivf"])
def test_approximate_search_finds_most_among_few(spark, how):
    v = embeddings(spark, SMALL).cache()
    n = v.count()
    search, candidates = {"lsh": (topk.topk_lsh, topk.candidates_lsh), "ivf": (topk.topk_ivf, topk.candidates_ivf)}[how]
    for k in (20, 50):
        exact = topk.topk_exact(v, v, k, 64).cache()
        assert evaluate.overlap(search(v, v, k, 64), exact, (k,)).first().recall >= 0.9
        assert candidates(v, v, k, 64).count() < 0.2 * n * n
    gone = exact.where("rank <= 5").select("row_id", "col_id")
    found = search(v, v, 20, 64, exclude=gone)
    assert found.join(gone, ["row_id", "col_id"]).count() == 0
    assert search(v.limit(0), v, 3, 64).count() == 0


def test_crawl_source_reads_odd_lines(spark, tmp_path):
    from linkfactor.sources.crawl import read_crawl

    (tmp_path / "a.json").write_text('{"url": "u", "links": ["/x", "/y"]}\nnot json\n\n[1]\n{"url": null}\n{"url": "v", "links": ["é"]}')
    (tmp_path / "b.txt").write_text('{"url": "w", "links": ["/z"]}')
    (tmp_path / "c.jsonl").write_text("")
    assert sorted((r.url, r.href) for r in read_crawl(spark, str(tmp_path)).collect()) == [("u", "/x"), ("u", "/y"), ("v", "é")]
    (tmp_path / "none").mkdir()
    assert read_crawl(spark, str(tmp_path / "none")).count() == 0


def test_popularity_skips_given(spark):
    used = spark.createDataFrame([(1, "a"), (2, "a"), (3, "b"), (4, "c"), (5, "b"), (6, "a")], "row_id long, col_id string")
    given = spark.createDataFrame([(9, "a")], used.schema)
    got = evaluate.popularity_topk(used, given, 2, exclude=given).orderBy("rank").collect()
    assert [r.col_id for r in got] == ["b", "c"]


def test_streams_equal_their_batches(spark):
    got = {(r.w_start, r.event_type): r.n for r in streams.stream_tumbling(spark, SMALL).collect()}
    twin = st.batch_twin(spark, SMALL).groupBy(F.date_format(F.date_trunc("day", "ts"), "yyyy-MM-dd HH:mm:ss").alias("d"), "event_type").count().collect()
    assert got == {(r.d, r.event_type): r["count"] for r in twin}


def test_late_data_is_dropped(spark):
    kept = {r.w_start for r in streams.stream_late_data(spark, SMALL).collect()}
    assert kept and min(kept) >= "2024-01-16"


def test_plans(spark):
    obs = sources.purchases(spark, SMALL)
    assert "CartesianProduct" not in obs._jdf.queryExecution().toString()
    from linkfactor.workloads.surface import op_scan_pruned

    frame = op_scan_pruned(spark, SMALL)
    plan = spark._jvm.PythonSQLUtils.explainString(frame._jdf.queryExecution(), "formatted")
    assert "GreaterThanOrEqual(l_quantity,45.0), EqualTo(l_returnflag,R)" in plan
    assert "ReadSchema: struct<l_orderkey:bigint,l_partkey:bigint,l_quantity:double,l_returnflag:string>" in plan


def test_registry():
    known, twins = __spark_entry__.queries(), __spark_entry__.oracle_sql()
    assert set(twins) <= set(known) and len(known) > 120


@pytest.mark.parametrize("name", ["refit_rows", "split_strong", "op_asof", "fold_in", "links_resolve", "links_kcore", "build_graph_stats", "same_host_share", "spot_check", "stream_late_data", "wl_batching", "wl_gram", "topk_exclude_given", "io_crawl_source", "refit_broadcast"])
def test_queries_agree_with_sql(spark, name):
    import duckdb

    con = duckdb.connect()
    for t in ("orders", "lineitem", "events", "pages", "customer", "documents", "embeddings"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{SMALL}/{t}.parquet'")
    got = __spark_entry__.queries()[name](spark, SMALL)
    names = sorted(got.columns)
    want = con.sql(f"SELECT {', '.join(names)} FROM ({__spark_entry__.oracle_sql()[name]})").fetchall()
    key = lambda r: tuple((x is None, x) for x in r)
    assert sorted([tuple(r) for r in got.select(*names).collect()], key=key) == sorted(want, key=key)


def test_entry(spark):
    rows = {(r.method, r.k): r.recall_truth for r in __spark_entry__.entry(spark).collect()}
    assert set(rows) == {(m, k) for m in ("factors", "popularity") for k in (20, 50)}


def test_sort_search_never_joins_cells(spark):
    """the baseline went over a cross join of all cells, which were sorted by a window."""
    import duckdb

    con = duckdb.connect()
    con.sql(f"CREATE VIEW embeddings AS SELECT * FROM '{SMALL}/embeddings.parquet'")
    frame = __spark_entry__.queries()["topk_sort"](spark, SMALL)
    assert not any(x in frame._jdf.queryExecution().toString() for x in ("CartesianProduct", "NestedLoop"))
    want = con.sql(f"SELECT vec_id, rank, nbr FROM ({__spark_entry__.oracle_sql()['topk_sort']})").fetchall()
    assert sorted(tuple(r) for r in frame.select("vec_id", "rank", "nbr").collect()) == sorted(want) and len(want) == 250


@pytest.mark.parametrize("levels", [3, 50, 10_000])
def test_best_places_of_many_columns(levels):
    """places are narrowed by tiles; ties and left-out places come out as by a sort."""
    import numpy as np

    rng = np.random.default_rng(levels)
    scores = rng.integers(0, levels, (7, 3000)).astype(float)
    scores[rng.random(scores.shape) < 0.3] = -np.inf
    scores[3, 5:] = -np.inf
    for k in (1, 20):
        row, col = topk.best_places(scores, k)
        want = [np.sort(np.lexsort((np.arange(3000), -s))[: min(k, int(np.isfinite(s).sum()))]) for s in scores]
        assert [col[row == i].tolist() for i in range(7)] == [w.tolist() for w in want]
        row, col = topk.sorted_places(scores, k)
        assert [np.sort(col[row == i]).tolist() for i in range(7)] == [w.tolist() for w in want]


def test_lsh_codes_columns_once(spark):
    """the columns' codes were made anew for each portion of the rows."""
    import numpy as np

    rng = np.random.default_rng(3)
    a, b = rng.standard_normal((5, 8)), rng.standard_normal((70, 8))
    scored = topk.sign_codes(64, 8, 7)(b)
    planes = np.random.default_rng(7).standard_normal((64, 8))
    differ = ((a @ planes.T > 0)[:, None] != (b @ planes.T > 0)[None]).sum(axis=2)
    assert np.allclose(scored(a), np.cos(np.pi * differ / 64) * np.linalg.norm(b, axis=1))
    asked = __spark_entry__.queries()["topk_lsh"](spark, SMALL).select("vec_id").distinct().collect()
    assert sorted(r.vec_id for r in asked) == list(range(0, 500, 20))


@pytest.mark.parametrize("search", [topk.topk_lsh, topk.topk_ivf])
def test_pools_are_scored_where_vectors_are(spark, search):
    """two joins shuffled a vector for each place of each pool."""
    v = embeddings(spark, SMALL)
    found = search(v.where("id % 20 = 0"), v, 5, 64)
    assert "Join" not in found._jdf.queryExecution().toString()
    x = {r.id: r.vec for r in v.collect()}
    assert all(r.score == pytest.approx(sum(p * q for p, q in zip(x[r.row_id], x[r.col_id]))) for r in found.collect())


def test_solver_residuals_reads_the_embeddings(spark):
    """F16: the systems were made up on the driver."""
    frame = __spark_entry__.queries()["solver_residuals"](spark, SMALL)
    assert any("embeddings" in f for f in frame.inputFiles())
    found = {(r.solver, r.dim): r for r in frame.collect()}
    assert set(found) == {(k, n) for k in ("lu", "qr", "cholesky", "cg") for n in (16, 32, 64, 128)}
    assert all(r.max_residual < 1e-8 and r.max_diff < 1e-6 for r in found.values())


def test_precision_bytes_move_each_vector_once(spark, monkeypatch):
    """a vector of 128 numbers was shuffled for each observation, in four modes."""
    from linkfactor.workloads import experiments

    rows, measure = [], experiments.shuffled_bytes
    monkeypatch.setattr(experiments, "shuffled_bytes", lambda frame: rows.append(frame.count()) or measure(frame))
    found = {r.mode: (r.stored_bytes, r.shuffled_bytes) for r in experiments.precision_bytes(spark, SMALL).collect()}
    assert found == {"float64": (1024, 1088), "float32": (512, 552), "mixed": (256, 296), "bf16_all": (256, 296)}
    assert set(rows) == {sources.purchases(spark, SMALL).select("col_id").distinct().count()}


def test_searches_are_measured_by_a_twentieth_of_the_rows(spark, monkeypatch):
    """all rows were searched against all."""
    from linkfactor.workloads import experiments

    asked, search = [], topk.topk_exact
    monkeypatch.setattr(topk, "topk_exact", lambda rows, *a, **b: asked.append(rows.count()) or search(rows, *a, **b))
    found = experiments.search_measures(embeddings(spark, SMALL), 64, "embeddings").collect()
    assert asked == [25, 25] and {(r.method, r.k) for r in found} == {(m, k) for m in ("exact", "lsh", "ivf") for k in (20, 50)}
    assert all(r.recall >= 0.9 and (r.method == "exact" or r.share < 0.2) for r in found)


def test_solver_seconds_need_no_broadcast(spark, monkeypatch):
    """each half-step sent the frozen table through the driver."""
    from linkfactor.operators import halfstep
    from linkfactor.workloads import experiments

    taken, refit = [], halfstep.refit_side
    monkeypatch.setattr(halfstep, "gather", lambda *a, **b: pytest.fail("vectors are gathered by a join"))
    monkeypatch.setattr(halfstep, "refit_side", lambda *a, **b: taken.append(a[4]) or refit(*a, **b))
    found = {(r.solver, r.warm, r.dim): r.n_rows for r in experiments.wl_solvers(spark, SMALL).collect()}
    assert len(found) == 28 and set(taken) == {"held"}
    assert set(found.values()) == {sources.purchases(spark, SMALL).select("row_id").distinct().count()}
