"""Records, lists and held searches, and that results leave no tables behind."""

from pathlib import Path

import numpy as np
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from linkfactor import sources
from linkfactor.config import FactorConfig
from linkfactor.operators import factors, halfstep, topk, train
from linkfactor.runtime import generation_at, shared_folder
from linkfactor.workloads import experiments
from linkfactor.workloads.model import embeddings

SMALL = "/root/testdata/sf0.001"


def test_lists_train_as_cells(spark):
    """Rows with lists, cells in any order and records of columns made from them give the same model, heavy rows and columns included."""
    obs = experiments.matrix(spark, SMALL, "purchases")
    lists = obs.groupBy("row_id").agg(F.collect_list("col_id").alias("col_ids"))
    got = []
    for what, cfg in ((lists, FactorConfig(rank=4, epochs=2)), (lists, FactorConfig(rank=4, epochs=2, heavy_row=20)), (obs, FactorConfig(rank=4, epochs=2, heavy_row=20)), (obs, FactorConfig(rank=4, epochs=2, gather="shuffle"))):
        model = train.fit(what, cfg)
        got.append(({r.id: r.vec for r in model.row_factors.collect()} | {-1 - r.id: r.vec for r in model.col_factors.collect()}, model.history[-1]["total"]))
    for vectors, total in got[:3]:
        assert vectors.keys() == got[3][0].keys() and total == pytest.approx(got[3][1])
        assert max(abs(a - b) for k in vectors for a, b in zip(vectors[k], got[3][0][k], strict=True)) < 1e-8


def test_records_keep_labels_and_wide_ids(spark):
    obs = spark.createDataFrame([(1, 5, 2.0), (1, 1 << 40, 3.0), (1, 5, 1.0), (2, 5, 1.0)], "row_id long, col_id long, y double")
    stored = halfstep.generation_at(halfstep.records(obs), "records")[0]
    whole, pieces, _ = halfstep.turned_records(stored, 100)
    assert pieces is None
    found = {}
    for batch in whole.toArrow().to_batches():
        names, counts, cells, labels = halfstep.cells_of(batch)
        owner = np.repeat(names, counts)
        found |= {(int(a), int(b)): float(y) for a, b, y in zip(owner, cells, np.ones(len(cells)) if labels is None else labels, strict=True)}
    assert found == {(5, 1): 3.0, (1 << 40, 1): 3.0, (5, 2): 1.0}


def test_held_search_is_the_exact_one(spark):
    table = generation_at(embeddings(spark, SMALL), "searched")
    some, exclude = table[0].where("id < 40"), spark.createDataFrame([(0, 0), (1, 3), (39, 7)], "row_id long, col_id long")
    topk.HELD_COLUMNS, before = 100, topk.HELD_COLUMNS
    try:
        got = topk.topk_held(some, table[1], 7, 64, "float64", exclude)
        want = topk.topk_exact(some, table[0], 7, 64, exclude)
        assert {(r.row_id, r.rank): r.col_id for r in got.collect()} == {(r.row_id, r.rank): r.col_id for r in want.collect()}
        assert got.rdd.getNumPartitions() >= 2 * spark.sparkContext.defaultParallelism
        assert "cogroup" not in got._jdf.queryExecution().toString().lower()
    finally:
        topk.HELD_COLUMNS = before


def test_sort_search_asks_for_all_rows(spark):
    """only the rows with ids divisible by 20 were searched, in the query and in its SQL. Held and by blocks the lists are the same."""
    import duckdb

    con = duckdb.connect()
    con.sql(f"CREATE VIEW embeddings AS SELECT * FROM '{SMALL}/embeddings.parquet'")
    frame = __spark_entry__.queries()["topk_sort"](spark, SMALL).select("vec_id", "rank", "nbr")
    got = sorted(tuple(r) for r in frame.collect())
    assert len(got) == 5000 and len({r[0] for r in got}) == 500
    assert got == sorted(con.sql(f"SELECT vec_id, rank, nbr FROM ({__spark_entry__.oracle_sql()['topk_sort']})").fetchall())
    v, exclude = embeddings(spark, SMALL), spark.createDataFrame([(0, 0), (1, 3), (39, 7), (5, 9999)], "row_id long, col_id long")
    before, found = topk.HELD_BYTES, []
    try:
        for topk.HELD_BYTES in (before, 0):
            found.append({(r.row_id, r.rank): r.col_id for r in topk.topk_sort(v, v, 7, exclude, 1).collect()})
    finally:
        topk.HELD_BYTES = before
    assert found[0] == found[1] and len(found[0]) == 3500


@pytest.mark.parametrize("digits", [0, 1, 6, 17])
def test_cells_are_sorted_as_one_number(digits):
    """F2: places by whole numbers of score and column are those by scores, with ties, left-out places and scores beyond 64 bits."""
    rng = np.random.default_rng(digits)
    for size in (1.0, 1e6, 1e14):
        scores = np.round(rng.standard_normal((6, 700)) * size, digits)
        scores[rng.random(scores.shape) < 0.3] = -np.inf
        scores[2, 4:], scores[3, ::2] = -np.inf, 0.0
        row, col = topk.sorted_places(scores, 9, digits)
        want = [np.lexsort((np.arange(700), -s))[: min(9, int(np.isfinite(s).sum()))] for s in scores]
        assert [np.sort(col[row == i]).tolist() for i in range(6)] == [np.sort(w).tolist() for w in want]


def test_searches_are_measured_over_all_rows(spark, monkeypatch):
    """the measures were of the rows with ids divisible by 20."""
    asked = []
    for name in ("topk_exact", "candidates_lsh", "candidates_ivf"):
        search = getattr(topk, name)
        monkeypatch.setattr(topk, name, lambda rows, *a, search=search, **b: asked.append(rows.count()) or search(rows, *a, **b))
    found = experiments.search_measures(embeddings(spark, SMALL), 64, "embeddings").collect()
    assert asked == [500] * 6 and {(r.method, r.k) for r in found} == {(m, k) for m in ("exact", "lsh", "ivf") for k in (20, 50)}
    assert all(r.recall >= 0.9 and (r.method == "exact" or r.share < 0.2) for r in found)


@pytest.mark.parametrize("search", [topk.candidates_lsh, topk.candidates_ivf])
def test_held_pools_are_those_of_the_blocks(spark, search):
    """over all rows the blocks shuffled each column many times, and a place for each cell that a row looks into."""
    table, path = generation_at(embeddings(spark, SMALL).select("id", "vec"), "searched")
    exclude = spark.createDataFrame([(0, 0), (0, 3), (1, 3), (39, 7), (39, 39), (5, 9999)], "row_id long, col_id long")
    for gone in (None, exclude):
        got, want = ({(r.row_id, r.col_id): (r.score, r.exact) for r in search(table, table, 11, 64, exclude=gone, path=p).collect()} for p in (path, None))
        assert got.keys() == want.keys() and len(got) == 500 * topk.pool_of(11)
        assert all(got[x] == pytest.approx(want[x]) for x in got)
    assert search(table.limit(0), table, 3, 64, path=path).count() == 0
    none, empty = generation_at(table.limit(0), "searched")
    assert search(table, none, 3, 64, path=empty).count() == 0


def test_vectors_are_picked_from_a_table_nobody_holds(spark, monkeypatch):
    """beyond the broadcast limit a vector was shuffled for each cell, in each of the half-steps."""
    obs = spark.createDataFrame([(r, c, float(1 + (r + c) % 3)) for r in range(50) for c in range(r % 7 + 1)] + [(7, 9999, 1.0), (60, 1 << 40, 1.0)], "row_id long, col_id long, y double")
    stored = generation_at(halfstep.records(obs), "records")[0]
    h, path = generation_at(factors.init_vectors(spark.range(7).union(spark.range(1 << 40, (1 << 40) + 1)), 4), "frozen")
    near, start = generation_at(factors.init_vectors(spark.range(0, 60, 2), 4, seed=1), "near")
    plan = {"records": (stored, None), "path": path, "start": start}
    packed = {"records": (stored, None)} | {k: halfstep.stored_for(x, FactorConfig(rank=4), "picked", "packed") for k, x in (("path", h), ("start", near))}
    want = {(kind, warm): {r.id: (r.vec, r.err) for r in halfstep.refit_side(obs, h, None, FactorConfig(rank=4, unobserved=0.0, solver=kind, cg_iters=2), "held", start=near if warm else None, plan=plan).collect()} for kind, warm in (("lu", False), ("cg", True), ("cg_free", True))}
    monkeypatch.setattr(halfstep, "gather", lambda *a, **b: pytest.fail("vectors are gathered by a join"))
    for (kind, warm), rows in want.items():
        solved = halfstep.refit_side(obs, h, None, FactorConfig(rank=4, unobserved=0.0, solver=kind, cg_iters=2), "picked", start=near if warm else None, plan=packed)
        assert "Exchange" not in solved._jdf.queryExecution().toString()
        got = {r.id: (r.vec, r.err) for r in solved.collect()}
        assert got.keys() == rows.keys() == {*range(50), 60}
        assert all(np.allclose(got[i][0], rows[i][0]) and got[i][1] == pytest.approx(rows[i][1], abs=1e-9) for i in got)
    counts = np.array([3, 1, 9, 2, 2, 1])
    assert [(a.start, a.stop, b.start, b.stop) for a, b in halfstep.portions(counts, 4)] == [(0, 2, 0, 4), (2, 3, 4, 13), (3, 5, 13, 17), (5, 6, 17, 18)]


@pytest.mark.parametrize("way", ["picked", "shuffle"])
def test_solvers_beyond_the_limit_keep_no_tables(spark, monkeypatch, way):
    """the tables of all dimensions stayed, and so did the files of each half-step's shuffle."""
    monkeypatch.setattr(halfstep, "gather_of", lambda columns, cfg: way if cfg.rank > 64 else "held")
    monkeypatch.setattr(experiments, "SLICE_BYTES", 1 << 20)
    folder, taken, refit = Path(shared_folder(spark).removeprefix("file://")), [], halfstep.refit_side
    before = set(folder.iterdir()) if folder.exists() else set()
    monkeypatch.setattr(halfstep, "refit_side", lambda *a, **b: taken.append(a[4]) or refit(*a, **b))
    found = {(r.solver, r.warm, r.dim): r.n_rows for r in experiments.wl_solvers(spark, SMALL).collect()}
    assert len(found) == 28 and set(found.values()) == {sources.purchases(spark, SMALL).select("row_id").distinct().count()}
    assert set(taken) == {"held", way} and (way == "picked" or taken.count("shuffle") > 8)
    assert set(folder.iterdir()) == before


def test_documents_matrix_matches_the_flat_one(spark):
    """The documents' matrix by a held dictionary has the cells of the joined one, in fewer shuffles; tables made for a result go."""
    cells = sources.word_observations(spark, SMALL, 5).toDF("row_id", "key")
    table = factors.dictionary(cells, "key").withColumnRenamed("id", "col_id")
    want = {tuple(r) for r in cells.join(table, "key").select("row_id", "col_id").collect()}
    assert {tuple(r) for r in experiments.matrix(spark, SMALL, "documents").select("row_id", "col_id").collect()} == want
    words = sources.document_words(spark, SMALL)
    experiments.DICTIONARY_BYTES, before = 0, experiments.DICTIONARY_BYTES
    try:
        assert {tuple(r) for r in experiments.flat(experiments.word_lists(spark, words, 5)).select("row_id", "col_id").collect()} == want
    finally:
        experiments.DICTIONARY_BYTES = before
    folder = Path(shared_folder(spark).removeprefix("file://"))
    there = set(folder.iterdir())
    assert experiments.wl_recall_pages(spark, SMALL).count() == 4
    assert set(folder.iterdir()) <= there


def test_models_of_parts_solve_equal_rows_once(spark):
    """Models of two parts of the observations over classes of equal rows are those of all rows, with recall and losses of all sources."""
    obs = sources.link_observations(spark, SMALL).where("page_id < 40")
    cells = obs.select(F.col("page_id").alias("row_id"), (F.pmod(F.xxhash64("path"), F.lit(1 << 20))).alias("col_id"), (F.lit(1.0) + F.pmod(F.length("path"), F.lit(2))).alias("y"))
    cells = cells.unionByName(cells.where("row_id < 25").withColumn("row_id", F.col("row_id") + 50))
    few = cells.where("row_id % 2 = 0 and col_id % 3 > 0")
    at = F.lit(1 << halfstep.POINT_BITS)
    both = cells.unionByName(few.withColumns({c: F.col(c) + at for c in ("row_id", "col_id")}))
    points, part = [(0.1, 0.01), (0.5, 0.1), (0.2, 0.05)], [0, 1, 1]
    given, hidden = both.where("row_id % 10 < 5 and col_id % 4 > 0"), both.where("row_id % 10 < 5 and col_id % 4 = 0")
    classes = train.row_classes(both)[0]
    assert classes.count() < both.select("row_id").distinct().count()
    got = []
    for limit in (FactorConfig.broadcast_limit, 0):
        models = train.fit_points(both, points, FactorConfig(rank=3, epochs=2, broadcast_limit=limit), keep_epochs=True, part=part)
        vectors = {r.id: r.vec for r in models.row_factors.collect()} | {-1 - r.id: r.vec for r in models.col_factors.collect()}
        got.append((vectors, {(r.epoch, r.point, r.k): (r.recall_truth, r.n_sources) for r in models.recall_by_epoch(given, hidden, (1, 5)).collect()}))
    assert got[0][0].keys() == got[1][0].keys() and max(abs(a - b) for k, v in got[0][0].items() for a, b in zip(v, got[1][0][k], strict=True)) < 1e-8
    assert len(got[0][1]) == 12 and all(v == pytest.approx(got[1][1][k]) for k, v in got[0][1].items())
    truth = hidden.where(F.col("row_id") < at).select("row_id").distinct().count()
    assert got[0][1][(1, 0, 5)][1] == truth


def test_start_at_a_precision_is_the_stored_start(spark):
    some = spark.range(50)
    for mode in ("float64", "float32", "mixed"):
        got = factors.init_vectors(some, 5, precision=mode)
        want = factors.store_table(factors.init_vectors(some, 5), 5, mode)
        assert got.dtypes == want.dtypes and {r.id: r.vec for r in got.collect()} == {r.id: r.vec for r in want.collect()}


def test_precision_leaves_no_tables_of_epochs(spark):
    folder = Path(shared_folder(spark).removeprefix("file://"))
    there = set(folder.iterdir())
    assert experiments.wl_precision(spark, SMALL).count() == 384
    left = {p.name.rsplit("-", 1)[0] for p in set(folder.iterdir()) - there}
    assert "split" in left and not any("points" in x or "judged" in x for x in left)


def test_gather_ablation_in_slices_is_the_whole_one(spark, monkeypatch):
    """Slices of the rows give the rows, errors and bytes of the whole half-step, for every gather."""
    whole = {r.gather: r for r in experiments.wl_gather_ablation(spark, SMALL).collect()}
    monkeypatch.setattr(experiments, "SLICE_BYTES", 100_000)
    parts = {r.gather: r for r in experiments.wl_gather_ablation(spark, SMALL).collect()}
    assert len({(r.n_rows, r.squared_error) for r in [*whole.values(), *parts.values()]}) == 1
    for how, r in whole.items():
        assert (parts[how].modelled_bytes, parts[how].shuffled_bytes) == (r.modelled_bytes, r.shuffled_bytes), how


def test_broadcast_goes_in_parts_and_routes_stream(spark, monkeypatch):
    """A table is broadcast in bounded parts without a relation in the driver, and a routed block isn't a group in memory."""
    obs = experiments.matrix(spark, SMALL, "purchases")
    cfg = FactorConfig(rank=4, blocks=3, unobserved=0.0)
    h = generation_at(factors.init_vectors(obs.select("col_id").distinct().where("col_id % 7 > 0"), 4, id_col="col_id"), "frozen")[0]
    monkeypatch.setattr(halfstep, "SENT_BYTES", 1000)
    assert len(halfstep.sent_parts(h, cfg)) > 1
    found = {how: halfstep.refit_side(obs, h, None, cfg, how) for how in ("shuffle", "broadcast", "routed")}
    want = {r.id: r.vec for r in found["shuffle"].collect()}
    for how, node in (("broadcast", "broadcasthashjoin"), ("routed", "cogroup")):
        got = {r.id: r.vec for r in found[how].collect()}
        assert got.keys() == want.keys() and all(v == pytest.approx(want[k]) for k, v in got.items())
        assert node not in found[how]._jdf.queryExecution().toString().lower()


def test_scaling_counts_lists_and_leaves_no_tables(spark):
    """Counts of rows with lists are those of their cells, and the trainings' tables go with the result."""
    from linkfactor.plans import planner

    lists = experiments.matrix_lists(spark, SMALL, "purchases")
    assert planner.observe(lists, 4, FactorConfig(rank=2, hot_columns=5)) == planner.observe(experiments.flat(lists), 4, FactorConfig(rank=2, hot_columns=5))
    folder = Path(shared_folder(spark).removeprefix("file://"))
    there = set(folder.iterdir())
    found = experiments.wl_scaling(spark, SMALL).collect()
    assert [(r.matrix, r.share, r.partitions) for r in found] == [(m, x, n) for m in ("purchases", "documents") for x, n in ((0.25, 8), (0.5, 8), (1.0, 2), (1.0, 8))]
    assert found[3].cells == experiments.flat(lists).count() and set(folder.iterdir()) <= there
