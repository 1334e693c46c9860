"""The experiments: recall against popularity, and how measures move with the settings."""

from __future__ import annotations

import time
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace
from functools import reduce
from math import ceil

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import sources
from ..config import FactorConfig
from ..operators import evaluate, factors, graph, halfstep, segments, topk, train
from ..operators.gram import gram
from ..operators.split import is_test, strong_split
from ..plans import planner
from ..runtime import drop_path, generation, generation_at, passing_tables
from . import strategies
from . import twins as S
from .model import embeddings, rounded
from .serving import REGS, WEIGHTS

#: Rank, epochs and weights of each matrix's run.
SETTINGS = {"pages": (8, 8, 1e-2, 1e-2), "documents": (16, 8, 1e-2, 1e-1), "events": (8, 8, 1e-2, 1e-2), "purchases": (16, 8, 1e-2, 1e-2)}


#: Bytes of a dictionary that workers may hold.
DICTIONARY_BYTES = 256 << 20


def word_lists(s, words: DataFrame, least: int) -> DataFrame:
    """Documents with their words' ids (row_id, col_ids) from stored row_id, words, after one pass of the least-count filter on both sides. Ids are in the order of the words that are left."""
    stays = F.size("words") >= least
    counts = words.select(F.explode("words").alias("key"), stays.alias("stays")).groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.max("stays").alias("stays"))
    table, path = generation_at(factors.dictionary(counts.where((F.col("n") >= least) & F.col("stays")), "key"), "words")
    kept = words.where(stays)
    if (table.agg(F.sum(F.octet_length("key") + 16)).first()[0] or 0) <= DICTIONARY_BYTES:
        return factors.word_ids(kept, path)
    return kept.select("row_id", F.explode("words").alias("key")).join(table, "key").groupBy("row_id").agg(F.collect_list("id").alias("col_ids"))


def matrix_lists(s, d, which: str, least: int | None = None, words: DataFrame | None = None) -> DataFrame:
    """The matrix as one row a source (row_id, col_ids), stored. least is the least count of links or words on both sides (1 for pages and 5 for documents by default). words: the documents' words, where they are stored already."""
    least = least or {"pages": 1, "documents": 5}.get(which, 1)
    if which == "purchases":
        return generation(sources.purchase_lists(s, d), "matrix")
    if which == "documents":
        return generation(word_lists(s, generation(sources.document_words(s, d), "document-words") if words is None else words, least), "matrix")
    if which == "events":
        obs = sources.events_as_observations(s, d)
    else:
        cells = graph.min_degree(sources.link_observations(s, d), "page_id", "path", least).toDF("row_id", "key")
        obs = cells.join(factors.dictionary(cells, "key").withColumnRenamed("id", "col_id"), "key")
    return generation(obs.groupBy("row_id").agg(F.sort_array(F.collect_list("col_id")).alias("col_ids")), "matrix")


def flat(lists: DataFrame) -> DataFrame:
    return lists.select("row_id", F.explode("col_ids").alias("col_id"), F.lit(1.0).alias("y"))


def matrix(s, d, which: str, least: int | None = None) -> DataFrame:
    """Observations with integer ids, a view of matrix_lists."""
    return flat(matrix_lists(s, d, which, least))


def split_parts(obs: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Cells of training sources, and given and hidden cells of test sources."""
    split = generation(strong_split(obs, "row_id", "col_id"), "split")
    return tuple(split.where(F.col("role") == r).drop("role") for r in ("train", "given", "hidden"))


def split_lists(lists: DataFrame) -> tuple[DataFrame, DataFrame, DataFrame]:
    """Rows of training sources, and given and hidden cells of test sources; only the latter are dealt and stored."""
    split = generation(strong_split(flat(lists.where(is_test("row_id"))), "row_id", "col_id"), "split")
    return lists.where(~is_test("row_id")), *(split.where(F.col("role") == r).drop("role") for r in ("given", "hidden"))


def recall_of(lists: DataFrame, cfg: FactorConfig, ks=(20, 50), with_baseline: bool = True) -> DataFrame:
    """method, k, recall_truth, n_sources by the strong-generalization protocol."""
    known, given, hidden = split_lists(lists)
    model = train.fit(known, cfg, track_loss=False)
    ranked = model.topk(model.fold_in(given), max(ks), exclude=given)
    out = evaluate.recall(generation(ranked, "ranked"), hidden, ks).select(F.lit("factors").alias("method"), "k", "recall_truth", "n_sources")
    if with_baseline:
        popular = evaluate.popularity_topk(flat(known), given, max(ks), exclude=given)
        out = out.unionByName(evaluate.recall(popular, hidden, ks).select(F.lit("popularity").alias("method"), "k", "recall_truth", "n_sources"))
    return out


def settled(s, make) -> DataFrame:
    """The few rows of the frame that make returns, without the tables that were written for them."""
    with passing_tables(s):
        frame = make()
        rows, schema = frame.collect(), frame.schema
    return s.createDataFrame(rows, schema)


def stacked(parts: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def recall_against_popularity(s, d, which: str, rank: int | None = None, epochs: int | None = None) -> DataFrame:
    r, e, reg, weight = SETTINGS[which]
    cfg = FactorConfig(rank=rank or r, epochs=epochs or e, reg=reg, unobserved=weight)
    return settled(s, lambda: rounded(recall_of(matrix_lists(s, d, which), cfg)))


def wl_recall_pages(s, d):
    return recall_against_popularity(s, d, "pages")


def wl_recall_docs(s, d):
    return recall_against_popularity(s, d, "documents")


def wl_recall_events(s, d):
    return recall_against_popularity(s, d, "events")


def wl_recall_purchases(s, d):
    """Negative control: these pairs are random, so nothing can beat chance."""
    return recall_against_popularity(s, d, "purchases")


def wl_popularity_check(s, d):
    """By how much the factors beat popularity on three matrices at 20."""
    names = ("pages", "documents", "events")

    def run(which: str) -> DataFrame:
        r = recall_against_popularity(s, d, which).where("k = 20").groupBy().pivot("method", ["factors", "popularity"]).agg(F.first("recall_truth"))
        return r.select(F.lit(which).alias("matrix"), "factors", "popularity", (F.col("factors") - F.col("popularity")).alias("gain"))

    with ThreadPoolExecutor(len(names)) as pool:
        return rounded(stacked(list(pool.map(run, names))))


def wl_density(s, d):
    """Recall by the least count of links (or words) on both sides, on pages and documents, with the cells and sources that are left."""
    cases = [("pages", n) for n in (1, 2, 5)] + [("documents", n) for n in (5, 10, 20)]

    def run(case: tuple[str, int], words: DataFrame | None = None) -> DataFrame:
        which, least = case

        def make() -> DataFrame:
            lists = matrix_lists(s, d, which, least, words)
            r, e, reg, weight = SETTINGS[which]
            found = recall_of(lists, FactorConfig(rank=r, epochs=e, reg=reg, unobserved=weight), with_baseline=False)
            cells = lists.agg(F.coalesce(F.sum(F.size("col_ids")), F.lit(0)).cast("bigint").alias("cells"), F.count(F.lit(1)).alias("sources"))
            return found.crossJoin(cells).select(F.lit(which).alias("matrix"), F.lit(least).alias("least"), "cells", "sources", "k", "recall_truth", "n_sources")

        return settled(s, make)

    with ThreadPoolExecutor(3) as pool:
        out = list(pool.map(run, cases[:3]))
    # The documents' matrices fill the cores and the disk, so they go one after the other, from words that are stored once.
    with passing_tables(s):
        words = generation(sources.document_words(s, d), "document-words")
        out += [run(case, words) for case in cases[3:]]
    return rounded(stacked(out))


def wl_domain_affinity(s, d):
    """Of a page's ten nearest pages in factor space, the share of the same language and host, beside the base rates."""
    model = train.fit(matrix(s, d, "pages"), FactorConfig(rank=8, epochs=6, reg=1e-2, unobserved=1e-2), track_loss=False)
    rows = generation(model.row_factors, "rows")
    near = generation(topk.topk_exact(rows, rows, 11, 8).where("row_id != col_id"), "near")
    pages, out = sources.read_table(s, d, "pages"), None
    for label, attr in (("lang", graph.page_language(F.col("html"))), ("host", graph.host_of(F.col("url")))):
        one = evaluate.same_attribute_share(near, pages.select(F.col("page_id").alias("id"), attr.alias("attr")), 10).withColumn("attribute", F.lit(label))
        out = one if out is None else out.unionByName(one)
    return rounded(out)


PRECISIONS = ("float64", "float32", "mixed", "bf16_all")


def wl_precision(s, d):
    """Recall at 20 on pages by precision, regularization and epoch, beside the stored and the shuffled bytes of a vector.

    All regularizations of a precision are trained together. Where 16-bit solves become singular, vectors hold no numbers and recall falls to nothing.
    """
    known, given, hidden = split_parts(matrix(s, d, "pages"))
    points = [(reg, 1e-3) for reg in REGS]
    named = s.createDataFrame([(i, reg) for i, (reg, _) in enumerate(points)], "point int, reg double")
    moved = {r["mode"]: r for r in precision_bytes(s, d).collect()}

    def run(mode: str) -> DataFrame:
        size = [F.lit(float(moved[mode][c])).alias(c) for c in ("stored_bytes", "shuffled_bytes")]
        models = train.fit_points(known, points, FactorConfig(rank=8, epochs=16, precision=mode), keep_epochs=True)
        found = models.recall_by_epoch(given, hidden, (20,)).join(F.broadcast(named), "point")
        return found.select(F.lit(mode).alias("mode"), "reg", "epoch", "recall_truth", *size)

    # Small matrices leave cores idle, so two trainings run side by side (four fill the driver's memory); a training's tables of all epochs go with it.
    with ThreadPoolExecutor(2) as pool:
        return rounded(stacked(list(pool.map(lambda mode: settled(s, lambda: run(mode)), PRECISIONS))), but=("reg",))


def precision_bytes(s, d):
    """mode, bytes of a vector of 128 numbers as stored, and as shuffled to its observations in a half-step (measured by the shuffle's own counter, keys and labels included).

    All vectors of a mode have the same bytes, which is checked, so each is shuffled to one of its observations and the counter's mean holds for all of them.
    """
    columns = generation(sources.purchases(s, d).select("col_id").distinct(), "columns")
    rows = []
    for mode in PRECISIONS:
        table = factors.init_vectors(columns, 128, id_col="col_id", precision=mode)
        size = F.length("vec") if factors.is_packed(table) else F.size("vec") * 8
        n, stored, least, most = table.agg(F.count(F.lit(1)), F.avg(size), F.min(size), F.max(size)).first()
        if least != most:
            raise ValueError(f"vectors of {least} to {most} bytes in mode {mode}")
        sent = table.select(F.col("id").alias("row_id"), F.col("id").alias("col_id"), F.lit(1.0).alias("y"), "vec").repartition("row_id")
        rows.append((mode, float(stored), shuffled_bytes(sent) / n))
    return s.createDataFrame(rows, "mode string, stored_bytes double, shuffled_bytes double")


def shuffled_bytes(frame: DataFrame) -> float:
    """Bytes that the last exchange of a plan writes, before compression, by its own measure; all files of the plan's shuffles go."""
    frame._jdf.queryExecution().toRdd().count()
    return exchanged_bytes(frame)[0]


def measured_row(frame: DataFrame):
    """The one row of an aggregate over a solver's rows, and the bytes that the last exchange before the solver writes; all files of the plan's shuffles go."""
    row = frame._jdf.queryExecution().executedPlan().executeCollect()[0]
    return row, exchanged_bytes(frame, "MapInArrowExec")[0]


def exchanged_bytes(frame: DataFrame, below: str | None = None) -> list[float]:
    """Bytes written by each exchange of a plan that was run, the last one first, or of those below the last node of a kind; the files of all go."""
    found, cleaner = [], frame.sparkSession._jsc.sc().cleaner().get()

    def walk(node, inside: bool) -> None:
        name = node.getClass().getSimpleName()
        inside = inside or name == below
        if name == "ShuffleExchangeExec":
            if inside:
                found.append(float(node.metrics().apply("dataSize").value()))
            cleaner.doCleanupShuffle(node.shuffleDependency().shuffleId(), True)
            walk(node.child(), inside)
            return
        children = [node.executedPlan()] if name == "AdaptiveSparkPlanExec" else [node.plan()] if name.endswith("QueryStageExec") else [node.children().apply(i) for i in range(node.children().size())]
        for child in children:
            walk(child, inside)

    walk(frame._jdf.queryExecution().executedPlan(), below is None)
    return found


def in_slices(frame: DataFrame, slices: int, key: str) -> list[DataFrame]:
    """The rows in so many parts by a hash of their key."""
    return [frame] if slices == 1 else [frame.where(F.pmod(F.xxhash64(key), F.lit(slices)) == k) for k in range(slices)]


def wl_solvers(s, d):
    """Seconds of a half-step on purchases by solver and dimension; conjugate gradients also from the solution of nearby weights.

    Workers hold the frozen table or pick from it; vectors of a table beyond that are shuffled over slices of the rows, whose files go before the next one. A dimension's tables go with it.
    """
    dims, rows = (16, 32, 64, 128), []
    with passing_tables(s):
        p, stored = generation_at(sources.purchases(s, d).repartition("row_id"), "obs")
        columns = generation(p.select("col_id").distinct(), "columns")
        whole, n_columns, cells = generation(halfstep.records(p), "records"), columns.count(), p.count()
        if halfstep.gather_of(n_columns, FactorConfig(rank=max(dims))) != "shuffle":
            drop_path(s, stored)
        for dim in dims:
            with passing_tables(s):
                cfg = FactorConfig(rank=dim, cg_iters=16, solve_batch_bytes=8 << 20)
                how, h = halfstep.gather_of(n_columns, cfg), factors.init_vectors(columns, dim, id_col="col_id")
                if how == "picked":
                    path = halfstep.stored_for(h, cfg, how, "frozen")
                else:
                    h, path = generation_at(h, "frozen")
                g, plan = gram(h, dim), {"records": (whole, None), "path": path}
                slices = max(1, ceil(cells * dim * 8 / max(SLICE_BYTES, n_columns * dim * 8))) if how == "shuffle" else 1
                first = [halfstep.refit_side(x, h, g, replace(cfg, reg=1.1e-2), how, plan=plan).select("id", "vec") for x in in_slices(p, slices, "row_id")]
                if how == "shuffle":
                    near = stacked([generation(x, "near") for x in first])
                else:
                    near, plan = first[0], plan | {"start": halfstep.stored_for(first[0], cfg, how, "near")}
                for kind, begin in (("lu", None), ("qr", None), ("cholesky", None), ("cg", None), ("cg", near), ("cg_free", None), ("cg_free", near)):
                    began, n = time.perf_counter(), 0
                    for x, at in zip(in_slices(p, slices, "row_id"), [None] * slices if begin is None else in_slices(begin, slices, "id"), strict=True):
                        solved = halfstep.refit_side(x, h, g, replace(cfg, solver=kind), how, start=at, plan=plan)
                        n += generation(solved.agg(F.count(F.lit(1)), F.sum("err")).toDF("n", "err"), "solved").first()["n"]
                    rows.append((kind, begin is not None, dim, int(n), time.perf_counter() - began))
    return s.createDataFrame(rows, "solver string, warm boolean, dim int, n_rows long, seconds double")


def grid_of(s, d, which: str, rank: int, epochs: int, regs=REGS, weights=WEIGHTS) -> DataFrame:
    """matrix, reg, unobserved, k, recall_truth and the best pair for each k, all pairs being trained together."""
    known, given, hidden = split_parts(matrix(s, d, which))
    results = generation(train.grid(known, given, hidden, regs, weights, FactorConfig(rank=rank, epochs=epochs)), "grid")
    chosen = train.best(results).select("k", F.col("reg").alias("best_reg"), F.col("unobserved").alias("best_unobserved"))
    return results.join(chosen, "k").select(F.lit(which).alias("matrix"), "reg", "unobserved", "k", "recall_truth", "best_reg", "best_unobserved")


def wl_grid(s, d):
    """The 42 pairs of weights by recall on pages, rank 8 and 8 epochs."""
    return rounded(grid_of(s, d, "pages", 8, 8), but=("reg", "unobserved", "best_reg", "best_unobserved"))


def wl_accuracy(s, d):
    """The accuracy table: for each of the six link graphs the best weights of the 42 by recall at 20, and recall at 20 and 50 with them after 16 epochs.

    All graphs and weights are trained in one job a half-step, each graph being a part of the observations. A graph too sparse to hide a link has no recall.
    """
    links = generation(graph.extract_links(sources.read_table(s, d, "pages")), "links")
    table = generation(factors.dictionary(links, "href").withColumnRenamed("id", "col_id"), "targets")
    points, named = [(r, w) for r in REGS for w in WEIGHTS], []
    parts: dict[str, list[DataFrame]] = {"train": [], "given": [], "hidden": []}
    for i, ((label, least), edges) in enumerate(graph.variants(links).items()):
        obs = edges.join(table, F.col("href") == F.col("key")).select(F.col("page_id").alias("row_id"), "col_id", F.lit(1.0).alias("y"))
        split = strong_split(obs, "row_id", "col_id")
        at = F.lit(i << halfstep.POINT_BITS)
        split = generation(split.withColumns({"row_id": F.col("row_id") + at, "col_id": F.col("col_id") + at}), "split")
        for role, cells in parts.items():
            cells.append(split.where(F.col("role") == role).drop("role"))
        named += [(i * len(points) + j, label, least, r, w) for j, (r, w) in enumerate(points)]
    known, given, hidden = (stacked(cells) for cells in parts.values())
    part = [i for i in range(len(named) // len(points)) for _ in points]
    models = train.fit_points(known, points * (len(named) // len(points)), FactorConfig(rank=8, epochs=16), part=part)
    names = s.createDataFrame(named, "point int, variant string, least int, reg double, unobserved double")
    found = generation(models.recall(given, hidden).join(F.broadcast(names), "point"), "accuracy")
    first = found.where("k = 20").groupBy("variant", "least").agg(F.max_by("point", F.struct("recall_truth", "reg", "unobserved")).alias("point"))
    best = found.join(first, ["variant", "least", "point"]).select("variant", "least", "reg", "unobserved", "k", "recall_truth", "n_sources")
    every = names.select("variant", "least").distinct().crossJoin(s.createDataFrame([(20,), (50,)], "k int"))
    return rounded(every.join(best, ["variant", "least", "k"], "left").withColumn("n_sources", F.coalesce("n_sources", F.lit(0).cast("bigint"))), but=("reg", "unobserved"))


def wl_scaling(s, d):
    """Seconds of whole epochs and of the whole training, by matrix, share of the rows and partitions, and the worker count at which the model's speedup ends."""
    rows = []
    for which in ("purchases", "documents"):
        with passing_tables(s):
            every = matrix_lists(s, d, which)
            for share in (0.25, 0.5, 1.0):
                lists = every if share == 1 else generation(factors.sample_ids(every, share, "row_id"), "part")
                stats = planner.observe(lists)
                for parts in (2, 8) if share == 1 else (8,):
                    cfg = FactorConfig(rank=16, epochs=2, blocks=parts)
                    with passing_tables(s):
                        began = time.perf_counter()
                        model = train.fit(lists, cfg, track_loss=False)
                        total, epoch = time.perf_counter() - began, min(h["seconds"] for h in model.history)
                    rows.append((which, share, parts, stats.cells, cfg.epochs, epoch, total, 2 * stats.cells / epoch, planner.scaling_knee(stats, cfg)))
    return s.createDataFrame(rows, "matrix string, share double, partitions int, cells long, epochs int, epoch_seconds double, training_seconds double, cells_per_second double, knee int")


#: Modelled bytes of a gather from which the ablation goes through the rows in slices.
SLICE_BYTES = 1 << 30


def wl_gather_ablation(s, d):
    """Seconds, modelled bytes of vectors, and the bytes that the last exchange before the solver moves (for a broadcast only the observations, for routes only the vectors).

    A gather that moves more than SLICE_BYTES is run over slices of the rows, whole blocks of rows for routes; a slice's shuffle files go before the next one begins, and all figures are sums over all rows.
    """
    p = generation(sources.purchases(s, d), "obs")
    cfg = FactorConfig(rank=16, blocks=8, hot_columns=200, reg=0.1)
    stats = planner.observe(p, 8, cfg)
    moved = planner.traffic(stats, cfg)
    h = generation(factors.init_vectors(p.select("col_id").distinct(), 16, id_col="col_id"), "frozen")
    g, rows = gram(h, 16), []
    hot = generation(halfstep.hot_columns(p, cfg), "hot-columns")
    for how in ("broadcast", "shuffle", "routed", "hot_cold", "partial_stats"):
        # A broadcast shuffles the observations alone.
        slices = 1 if how == "broadcast" else min(ceil(moved[how] / SLICE_BYTES), cfg.blocks if how == "routed" else stats.rows) or 1
        at = F.pmod(F.pmod("row_id", F.lit(cfg.blocks)) if how == "routed" else F.xxhash64("row_id"), F.lit(slices))
        n, check, seconds, measured = 0, 0.0, 0.0, 0.0
        for k in range(slices):
            some = p if slices == 1 else p.where(at == k)
            began = time.perf_counter()
            found, exchanged = measured_row(halfstep.refit_side(some, h, g, cfg, how, plan={"hot": hot}).agg(F.count(F.lit(1)), F.coalesce(F.sum("err"), F.lit(0.0))))
            seconds += time.perf_counter() - began
            if how == "routed":
                exchanged = shuffled_bytes(halfstep.routing(some, cfg.blocks).join(h.hint("merge"), F.col("col_id") == F.col("id")).select("row_block", "vec").repartition("row_block"))
            n, check, measured = n + found.getLong(0), check + found.getDouble(1), measured + exchanged
        rows.append((how, n, round(check, 4), seconds, float(moved[how]), measured))
    return s.createDataFrame(rows, "gather string, n_rows long, squared_error double, seconds double, modelled_bytes double, shuffled_bytes double")


def wl_batching(s, d):
    """Padding waste of the documents' word rows by strategy."""
    words = sources.word_observations(s, d, 5).select(F.col("doc_id").alias("row_id"), F.col("word").alias("col_id"))
    return segments.waste(words)


def search_measures(table: DataFrame, rank: int, what: str) -> DataFrame:
    """vectors, method, k, recall against the exact search, share of all pairs that are scored exactly, and seconds; all rows are searched against all."""
    table, path = generation_at(factors.as_lists(table, rank).select("id", "vec"), "searched")
    path = path if topk.is_held(table, rank) else None
    n, out, s = table.count() ** 2, [], table.sparkSession
    for k in (20, 50):
        with passing_tables(s):
            began = time.perf_counter()
            exact = generation(topk.topk_exact(table, table, k, rank, path=path), "exact")
            out.append((what, "exact", k, 1.0, 1.0, time.perf_counter() - began))
            for method, search in (("lsh", topk.candidates_lsh), ("ivf", topk.candidates_ivf)):
                with passing_tables(s):
                    began = time.perf_counter()
                    pool = generation(search(table, table, k, rank, path=path), "pool")
                    found = generation(topk.rerank(pool, table, table, k, rank), "found")
                    seconds = time.perf_counter() - began
                    recall = generation(evaluate.overlap(found, exact, (k,)), "recall").first()["recall"]
                    out.append((what, method, k, float(recall), pool.count() / n, seconds))
    return s.createDataFrame(out, "vectors string, method string, k int, recall double, share double, seconds double")


def wl_topk(s, d):
    """Approximate searches against the exact one, over embeddings and over learnt factors of the documents' words."""

    def make() -> DataFrame:
        r, e, reg, weight = SETTINGS["documents"]
        model = train.fit(matrix_lists(s, d, "documents"), FactorConfig(rank=r, epochs=4, reg=reg, unobserved=weight), track_loss=False)
        return search_measures(embeddings(s, d), 64, "embeddings").unionByName(search_measures(model.row_factors, r, "factors"))

    return settled(s, make)


def wl_gram(s, d):
    """Trace and total of the embeddings' Gram matrix."""
    g = gram(embeddings(s, d), 64)
    return rounded(s.createDataFrame([(64, float(g.trace()), float(g.sum()))], "dim int, trace double, total double"), 4)


SQL = {
    "wl_gram": "WITH x AS (SELECT unnest(range(0, 64)) AS i), v AS (SELECT vec_id, embedding[i + 1]::double AS v FROM embeddings, x), q AS (SELECT vec_id, sum(v * v) AS sq, sum(v) AS t FROM v GROUP BY vec_id) SELECT 64 AS dim, round(sum(sq), 4) + 0.0 AS trace, round(sum(t * t), 4) + 0.0 AS total FROM q",
    "wl_batching": strategies.waste_sql(f"{S.T}, ko AS (SELECT doc_id FROM t GROUP BY 1 HAVING count(*) >= 5), ki AS (SELECT word FROM t GROUP BY 1 HAVING count(*) >= 5), n AS (SELECT doc_id AS row_id, count(*) AS n FROM t WHERE doc_id IN (SELECT doc_id FROM ko) AND word IN (SELECT word FROM ki) GROUP BY 1)"),
}
QUERIES = {k: v for k, v in globals().items() if k.startswith("wl_")} | {"precision_bytes": precision_bytes}
