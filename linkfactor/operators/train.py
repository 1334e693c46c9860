"""Training to a number of epochs, and the trained model."""

from __future__ import annotations

import json
import time
from dataclasses import asdict, dataclass
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import FactorConfig
from ..functions import dot
from ..plans.planner import ObsStats, choose_gather, fits_broadcast, observe
from ..runtime import drop_path, executors, generation, generation_at, scratch, write_passing
from ..schema import OBSERVATIONS, reject_bad_numbers, require
from .evaluate import recall_by_point
from .factors import as_lists, init_vectors, is_packed, store_table
from .gram import gram, grams_by
from .halfstep import POINT_BITS, Points, blocks_for, heavy_rows, held_records, hot_columns, list_records, refit_held, refit_side, routing, turned_records
from .topk import topk_exact, topk_held, topk_ivf, topk_lsh, topk_points, topk_sort


def transposed(obs: DataFrame) -> DataFrame:
    return obs.select(F.col("col_id").alias("row_id"), F.col("row_id").alias("col_id"), "y")


def scores(pairs: DataFrame, rows: DataFrame, columns: DataFrame, rank: int | None = None) -> DataFrame:
    """pairs with the column score; pairs without a vector on either side go. rank is needed for packed tables."""
    rows, columns = (as_lists(x, rank) if is_packed(x) else x for x in (rows, columns))
    w, h = rows.select(F.col("id").alias("row_id"), F.col("vec").alias("w")), columns.select(F.col("id").alias("col_id"), F.col("vec").alias("h"))
    return pairs.join(w, "row_id").join(h, "col_id").select(*pairs.columns, dot("w", "h").alias("score"))


def loss_terms(obs: DataFrame, rows: DataFrame, columns: DataFrame, cfg: FactorConfig) -> dict[str, float]:
    """The implicit objective; the sum over all cells is the inner product of the two Gram matrices."""
    error = scores(obs, rows, columns, cfg.rank).agg(F.sum((F.col("y") - F.col("score")) * (F.col("y") - F.col("score")))).first()[0] or 0.0
    return loss_parts(float(error), gram(rows, cfg.rank), gram(columns, cfg.rank), cfg)


def loss_parts(error: float, a: np.ndarray, b: np.ndarray, cfg: FactorConfig) -> dict[str, float]:
    terms = {"observed": error, "all_cells": cfg.unobserved * float((a * b).sum()), "reg": cfg.reg * float(np.trace(a) + np.trace(b))}
    return terms | {"total": sum(terms.values())}


@dataclass
class FactorModel:
    row_factors: DataFrame
    col_factors: DataFrame
    cfg: FactorConfig
    history: list[dict[str, float]]

    def num_parameters(self) -> int:
        return (self.row_factors.count() + self.col_factors.count()) * self.cfg.rank

    def predict(self, pairs: DataFrame) -> DataFrame:
        return scores(pairs, self.row_factors, self.col_factors, self.cfg.rank)

    def loss(self, obs: DataFrame) -> dict[str, float]:
        return loss_terms(obs, self.row_factors, self.col_factors, self.cfg)

    def fold_in(self, given: DataFrame) -> DataFrame:
        """Vectors of rows that training never saw: the same half-step with the columns frozen, and their own Gram."""
        table, path = generation_at(self.col_factors, "frozen")
        held = table.count() * self.cfg.rank * 8 <= self.cfg.broadcast_limit
        return refit_side(given, table, gram(table, self.cfg.rank), self.cfg, "held" if held else "shuffle", plan={"path": path}).select("id", "vec")

    def topk(self, rows: DataFrame, k: int, exclude: DataFrame | None = None, method: str = "exact", **more) -> DataFrame:
        if method == "exact" and not more and self.col_factors.count() * self.cfg.rank * 8 <= self.cfg.broadcast_limit:
            return topk_held(generation(rows, "asked"), generation_at(self.col_factors, "searched")[1], k, self.cfg.rank, self.cfg.precision, exclude)
        search = {"exact": topk_exact, "lsh": topk_lsh, "ivf": topk_ivf}.get(method)
        if search is None:
            return topk_sort(as_lists(rows, self.cfg.rank), as_lists(self.col_factors, self.cfg.rank), k, exclude=exclude)
        return search(rows, self.col_factors, k, self.cfg.rank, exclude=exclude, **more)

    def save(self, path: str) -> None:
        self.row_factors.write.mode("overwrite").parquet(f"{path}/rows")
        self.col_factors.write.mode("overwrite").parquet(f"{path}/columns")
        spark = self.row_factors.sparkSession
        spark.createDataFrame([(json.dumps(asdict(self.cfg)), json.dumps(self.history))], "cfg string, history string").write.mode("overwrite").parquet(f"{path}/settings")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> FactorModel:
        row = spark.read.parquet(f"{path}/settings").first()
        return cls(spark.read.parquet(f"{path}/rows"), spark.read.parquet(f"{path}/columns"), FactorConfig(**json.loads(row["cfg"])), json.loads(row["history"]))


class _Generations:
    """The stored tables of one side: a new one replaces the last, which is deleted once the new one is there."""

    def __init__(self, spark: SparkSession, label: str) -> None:
        self.spark, self.label, self.path = spark, label, None

    def commit(self, frame: DataFrame) -> DataFrame:
        path = scratch(self.spark, self.label)
        write_passing(frame, path)
        if self.path:
            drop_path(self.spark, self.path)
        self.path = path
        return self.spark.read.schema(frame.schema).parquet(path)


def _by_side(obs: DataFrame) -> dict[str, DataFrame]:
    """Both layouts of the observations, each dealt by its own side and written once. Labels of repeated cells are summed."""
    checked = reject_bad_numbers(require(obs, OBSERVATIONS))
    rows = generation(checked.groupBy("row_id", "col_id").agg(F.sum("y").alias("y")).repartition("row_id"), "observations")
    return {"row": rows, "col": generation(transposed(rows).repartition("row_id"), "observations-by-column")}


@dataclass
class SidePlan:
    """How one side is refitted, the same in all epochs: the gather, heavy rows, and routes or hot columns stored once."""

    how: str
    heavy: DataFrame | None
    shared: dict

    def drop(self, spark: SparkSession) -> None:
        """Delete the records of both kinds, which nobody reads after training."""
        for stored in self.shared.get("records", ()):
            for path in {f.rsplit("/", 1)[0] for f in stored.inputFiles()} if stored is not None else ():
                drop_path(spark, path)


def plan_side(obs: DataFrame, cfg: FactorConfig) -> SidePlan:
    spark = obs.sparkSession
    workers = executors(spark)
    at_least = int(spark.conf.get("spark.sql.shuffle.partitions"))
    stats = observe(obs)
    blocks = blocks_for(stats.cells, min(stats.cells, stats.columns * at_least), cfg, at_least)
    held = cfg.gather == "held" or cfg.gather == "auto" and stats.columns * cfg.rank * 8 <= cfg.broadcast_limit
    if cfg.gather == "auto" and not held and not fits_broadcast(stats, cfg):
        # What the routed and the hot-and-cold gather move depends on the data, so it is counted.
        stats = observe(obs, blocks, cfg)
    how = "held" if held else choose_gather(stats, cfg, workers) if cfg.gather == "auto" else cfg.gather
    heavy = generation(heavy_rows(obs, cfg.heavy_row), "heavy-rows") if stats.longest > cfg.heavy_row else None
    shared = {}
    if how == "held":
        whole, pieces = held_records(obs, heavy)
        stored = generation(whole, "records")
        shared = {"records": (stored.coalesce(cfg.blocks) if cfg.blocks else stored, None if pieces is None else generation(pieces, "pieces"))}
    if how == "routed":
        light = obs if heavy is None else obs.join(heavy, F.col("row_id") == F.col("heavy_id"), "left_anti")
        shared = {"blocks": blocks, "routes": generation(routing(light, blocks), "routes")}
    if how == "hot_cold":
        shared = {"hot": generation(hot_columns(obs, cfg), "hot-columns")}
    return SidePlan(how, heavy, shared)


def _held_sides(obs: DataFrame, cfg: FactorConfig) -> dict[str, SidePlan] | None:
    """Plans of both sides where workers may hold either side's table: records of the rows, and of the columns made from them; None where a table is too large.

    obs: row_id, col_id and y, or rows with lists (row_id, col_ids), each row once, all labels being 1.
    """
    lists = "col_ids" in obs.columns
    if cfg.gather not in ("auto", "held"):
        return None
    fits = lambda n: cfg.gather == "held" or n * cfg.rank * 8 <= cfg.broadcast_limit
    if not fits(obs.count() if lists else max(obs.agg(F.approx_count_distinct("row_id", 0.01), F.approx_count_distinct("col_id", 0.01)).first())):
        return None
    spark, size = obs.sparkSession, F.size("col_ids")
    if lists:
        long = obs.where(size > cfg.heavy_row).select("row_id", F.explode(F.sequence(F.lit(0), size - 1, F.lit(cfg.heavy_row))).alias("at"), "col_ids").select("row_id", F.slice("col_ids", F.col("at") + 1, F.lit(cfg.heavy_row)).alias("col_ids"))
        some = bool(obs.where(size > cfg.heavy_row).limit(1).count())
        whole, pieces = list_records(obs.where(size <= cfg.heavy_row)), list_records(long) if some else None
    else:
        checked = reject_bad_numbers(require(obs, OBSERVATIONS))
        heavy = generation(heavy_rows(checked, cfg.heavy_row), "heavy-rows")
        whole, pieces = held_records(checked, heavy if heavy.limit(1).count() else None)
    row = tuple(None if x is None else generation(x, "records") for x in (whole, pieces))
    whole, pieces, parts = turned_records(row[0] if row[1] is None else row[0].unionByName(row[1]), cfg.heavy_row)
    col = tuple(None if x is None else generation(x, "records-by-column") for x in (whole, pieces))
    drop_path(spark, parts)
    if not fits(col[0].count()):
        return None
    dealt = lambda x: x if x is None or not cfg.blocks else x.coalesce(cfg.blocks)
    return {k: SidePlan("held", None, {"records": tuple(map(dealt, x))}) for k, x in (("row", row), ("col", col))}


def _ids_of(plan: SidePlan) -> DataFrame:
    whole, pieces = plan.shared["records"]
    return whole.select("row_id") if pieces is None else whole.select("row_id").unionByName(pieces.select("row_id").distinct())


def fit(obs: DataFrame, cfg: FactorConfig, track_loss: bool = True, start: DataFrame | None = None) -> FactorModel:
    """Alternate half-steps. ``start`` are column vectors to begin with (random ones otherwise). obs: cells, or rows with lists (row_id, col_ids) of columns whose labels are 1.

    Both layouts of the observations, routes and hot columns are written once and reused by
    all epochs; each half-step reads the frozen side's last generation, and conjugate
    gradients begin with the own side's. The loss of an epoch comes from the errors that the
    last half-step returns, without another pass over the observations.
    """
    plans = _held_sides(obs, cfg)
    if plans:
        sides, first_ids = {"row": None, "col": None}, _ids_of(plans["col"])
    else:
        sides = _by_side(obs if "y" in obs.columns else obs.select("row_id", F.explode("col_ids").alias("col_id"), F.lit(1.0).alias("y")))
        plans, first_ids = {k: plan_side(x, cfg) for k, x in sides.items()}, sides["col"].select("row_id").distinct()
    stores = {k: _Generations(obs.sparkSession, f"{k}-factors") for k in sides}
    first = init_vectors(first_ids, cfg.rank, cfg.seed, id_col="row_id") if start is None else start.select("id", "vec")
    columns, rows, history = stores["col"].commit(store_table(first, cfg.rank, cfg.precision)), None, []
    column_gram = gram(columns, cfg.rank)

    def step(side: str, frozen: DataFrame, frozen_gram: np.ndarray, own: DataFrame | None) -> DataFrame:
        p, other = plans[side], stores["col" if side == "row" else "row"]
        shared = p.shared | {"path": other.path, "start": stores[side].path}
        return stores[side].commit(refit_side(sides[side], frozen.select("id", "vec"), frozen_gram, cfg, p.how, p.heavy, None if own is None else own.select("id", "vec"), plan=shared))

    for epoch in range(1, cfg.epochs + 1):
        began = time.perf_counter()
        rows = step("row", columns, column_gram, rows)
        row_gram = gram(rows, cfg.rank)
        columns = step("col", rows, row_gram, columns)
        column_gram = gram(columns, cfg.rank)
        seconds = time.perf_counter() - began
        if track_loss or cfg.tol is not None:
            error = columns.agg(F.sum("err")).first()[0] or 0.0
            history.append({"epoch": epoch, "seconds": seconds, **loss_parts(float(error), row_gram, column_gram, cfg)})
            if cfg.tol is not None and len(history) > 1 and history[-2]["total"] - history[-1]["total"] < cfg.tol * abs(history[-2]["total"]):
                break
        else:
            history.append({"epoch": epoch, "seconds": seconds})
    for plan in plans.values():
        plan.drop(obs.sparkSession)
    return FactorModel(rows.select("id", "vec"), columns.select("id", "vec"), cfg, history)


@dataclass
class PointModels:
    """Models of several pairs of weights on the same observations, trained in one job a half-step.

    Ids carry the number of their model (point) above POINT_BITS. part has the part of the
    observations that each model is trained on. epochs holds the column tables of all epochs
    where they were kept.
    """

    points: list[tuple[float, float]]
    part: list[int]
    row_factors: DataFrame
    col_factors: DataFrame
    cfg: FactorConfig
    epochs: list[DataFrame]
    grams: list[np.ndarray]

    def bases(self, grams: np.ndarray) -> np.ndarray:
        return point_bases(self.points, grams, self.cfg.rank)

    def recall(self, given: DataFrame, hidden: DataFrame, ks=(20, 50)) -> DataFrame:
        """point, k, recall_truth, n_sources by the last columns."""
        return self._recall(self.col_factors.select("id", "vec"), self.bases(self.grams[-1]), given, hidden, self.part, ks)

    def recall_by_epoch(self, given: DataFrame, hidden: DataFrame, ks=(20, 50)) -> DataFrame:
        """epoch (from 1), point, k, recall_truth, n_sources of all epochs, which are judged together like so many more points."""
        n = len(self.points)
        shifted = [c.select((F.col("id") + F.lit(e * n << POINT_BITS)).alias("id"), "vec") for e, c in enumerate(self.epochs)]
        bases = np.concatenate([self.bases(g) for g in self.grams])
        found = self._recall(reduce(DataFrame.unionByName, shifted), bases, given, hidden, self.part * len(shifted), ks)
        return found.withColumns({"epoch": F.floor(F.col("point") / F.lit(n)).cast("int") + 1, "point": F.col("point") % F.lit(n)})

    def _recall(self, columns: DataFrame, bases: np.ndarray, given: DataFrame, hidden: DataFrame, part: list[int], ks) -> DataFrame:
        """Sources with the same given and the same hidden links have the same recall, so one of them is judged and counts as often as there are such sources."""
        cfg, models = self.cfg, Points(models_of(part))
        table, path = generation_at(columns, "judged")
        some = generation(alike(given, hidden), "judged-sources")
        asked = some.select("row_id", F.explode("cells").alias("cell")).select("row_id", F.col("cell.col_id").alias("col_id"), F.col("cell.y").alias("y"))
        wanted = some.select("row_id", F.explode("truth").alias("col_id"))
        asked, wanted, times = (at_models(x, part) for x in (asked, wanted, some.select("row_id", "times")))
        if table.count() * cfg.rank * 8 <= cfg.broadcast_limit:
            lists = some.select("row_id", F.col("cells.col_id").alias("col_ids"), F.col("cells.y").alias("ys"))
            folded = refit_held(list_records(lists), path, bases, cfg, points=models)
        else:
            folded = refit_side(asked, table, None, cfg, "shuffle", base=bases)
        ranked = topk_points(folded.select("id", "vec"), table, max(ks), cfg.rank, exclude=asked)
        return recall_by_point(ranked, wanted, ks, times=times)


def alike(given: DataFrame, hidden: DataFrame) -> DataFrame:
    """row_id (the smallest), cells (col_id, y), truth (col_ids) and times of the sources with equal given and hidden links in the same part; those without hidden links go."""
    cells = given.groupBy("row_id", "col_id").agg(F.sum("y").alias("y")).groupBy("row_id").agg(F.sort_array(F.collect_list(F.struct("col_id", "y"))).alias("cells"))
    truth = hidden.groupBy("row_id").agg(F.sort_array(F.collect_set("col_id")).alias("truth"))
    each = truth.join(cells, "row_id", "left").withColumn("part", F.shiftright("row_id", POINT_BITS))
    return each.groupBy("part", "cells", "truth").agg(F.min("row_id").alias("row_id"), F.count(F.lit(1)).alias("times")).select("row_id", "cells", "truth", "times")


def models_of(part: list[int]) -> tuple[tuple[int, ...], ...]:
    """The models of each part."""
    return tuple(tuple(i for i, p in enumerate(part) if p == k) for k in range(max(part) + 1))


def at_models(cells: DataFrame, part: list[int]) -> DataFrame:
    """A copy of the cells (row_id and others) for each model of their part, whose number is above POINT_BITS in the models' ids instead of the part's."""
    of, low = F.array(*[F.array(*[F.lit(i) for i in x]) for x in models_of(part)]), F.lit((1 << POINT_BITS) - 1)
    copies = cells.withColumn("point", F.explode(F.get(of, F.shiftright("row_id", POINT_BITS).cast("int"))))
    shift = F.shiftleft(F.col("point").cast("bigint"), POINT_BITS)
    return copies.withColumns({c: F.col(c).bitwiseAND(low) + shift for c in ("row_id", "col_id") if c in cells.columns}).drop("point")


def point_grams(fac: DataFrame, rank: int, n: int, points: Points | None = None) -> np.ndarray:
    """The Gram matrix of each point's vectors, with points of their multiples by the scales."""
    point = F.shiftright("id", POINT_BITS).cast("int")
    scaled = None if points is None or points.scale is None else lambda x, names: points.scaled(x, names, (points.scale,))
    return np.stack(grams_by(fac.select("id", point.alias("group"), "vec"), rank, n, scaled))


def point_bases(points: list[tuple[float, float]], grams: np.ndarray, rank: int) -> np.ndarray:
    return np.stack([reg * np.eye(rank) + weight * g for (reg, weight), g in zip(points, grams, strict=True)])


def row_classes(obs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Rows with equal cells in the same part as one: (row_id, the smallest; cells of col_id, y; times), and the members (id, of)."""
    summed = obs.groupBy("row_id", "col_id").agg(F.sum("y").alias("y")).groupBy("row_id").agg(F.sort_array(F.collect_list(F.struct("col_id", "y"))).alias("cells"))
    rows = generation(summed.withColumn("part", F.shiftright("row_id", POINT_BITS)), "rows-of-points")
    classes = generation(rows.groupBy("part", "cells").agg(F.min("row_id").alias("row_id"), F.count(F.lit(1)).alias("times")), "classes")
    found = rows.select("part", "cells", F.col("row_id").alias("id")).join(classes.select("part", "cells", F.col("row_id").alias("of")), ["part", "cells"])
    return classes.select("row_id", "cells", "times"), found.select("id", "of")


def _held_points(obs: DataFrame, part: list[int], cfg: FactorConfig) -> tuple[dict[str, tuple[DataFrame, Points]], DataFrame, DataFrame] | None:
    """Records of both sides with their models, the columns' ids and the members of the rows' classes, where workers may hold the tables of all models; else None.

    A column's records hold classes instead of rows: labels and vectors are multiplied by the root of a class's size, which makes the same systems.
    """
    classes, members = row_classes(obs)
    many = models_of(part)
    fits = lambda ids: sum(r["n"] * len(many[r["part"]]) for r in ids.groupBy(F.shiftright("row_id", POINT_BITS).alias("part")).agg(F.count(F.lit(1)).alias("n")).collect()) * cfg.rank * 8 <= cfg.broadcast_limit
    if not fits(classes):
        return None
    root = F.sqrt(F.col("times").cast("double"))
    turned_cells = classes.select("row_id", root.alias("root"), F.explode("cells").alias("cell"))
    columns = turned_cells.groupBy(F.col("cell.col_id").alias("row_id")).agg(F.sort_array(F.collect_list(F.struct(F.col("row_id").alias("id"), (F.col("cell.y") * F.col("root")).alias("y")))).alias("cells"))
    columns = generation(columns.select("row_id", F.col("cells.id").alias("col_ids"), F.col("cells.y").alias("ys")), "columns-of-points")
    if not fits(columns):
        return None
    scale = generation_at(classes.select(F.col("row_id").alias("id"), F.array(root).alias("vec")), "scales")[1]
    rows = list_records(classes.select("row_id", F.col("cells.col_id").alias("col_ids"), F.col("cells.y").alias("ys")))
    sides = {"row": (generation(rows, "records"), Points(many)), "col": (generation(list_records(columns), "records"), Points(many, scale))}
    return sides, columns.select("row_id"), members


def fit_points(obs: DataFrame, points: list[tuple[float, float]], cfg: FactorConfig, keep_epochs: bool = False, part: list[int] | None = None) -> PointModels:
    """A model for each pair of weights (reg, unobserved), every half-step being one job for all.

    Where workers may hold the vectors of all models, the observations are stored once as
    records, and rows with equal cells, which have equal vectors, are solved once. Beyond that
    the observations are laid out once for each model and vectors are shuffled.

    Ids must be from 0 and below 2 ** POINT_BITS. part: which part of the observations each model is trained on, where the ids carry the number of their part above POINT_BITS.
    """
    n, top = len(points), 1 if part is None else max(part) + 1
    part = [0] * n if part is None else part
    obs = reject_bad_numbers(require(obs, OBSERVATIONS))
    if obs.where(~F.col("row_id").between(0, (top << POINT_BITS) - 1) | ~F.col("col_id").between(0, (top << POINT_BITS) - 1)).limit(1).count():
        raise ValueError("ids out of range for several models at once")
    held = _held_points(obs, part, cfg)
    sides = held[0] if held else _by_side(at_models(obs, part))
    stores = {k: _Generations(obs.sparkSession, f"{k}-points") for k in sides}
    ids = at_models(held[1], part) if held else sides["col"].select("row_id")
    ids = ids.select(F.col("row_id").alias("at_point"), F.col("row_id").bitwiseAND(F.lit((1 << POINT_BITS) - 1)).alias("plain")).distinct()
    first = ids.join(init_vectors(ids.select("plain").distinct(), cfg.rank, cfg.seed, id_col="plain"), F.col("plain") == F.col("id")).select(F.col("at_point").alias("id"), "vec")
    columns, path = generation_at(store_table(first, cfg.rank, cfg.precision), "first-points")
    column_grams, rows, kept, grams = point_grams(columns, cfg.rank, n), None, [], []

    def step(side: str, frozen: DataFrame, path: str, frozen_grams: np.ndarray) -> DataFrame:
        base = point_bases(points, frozen_grams, cfg.rank)
        if held:
            return refit_held(sides[side][0], path, base, cfg, points=sides[side][1])
        return refit_side(sides[side], frozen.select("id", "vec"), None, cfg, "shuffle", base=base)

    for _ in range(cfg.epochs):
        rows = stores["row"].commit(step("row", columns, path, column_grams))
        done = step("col", rows, stores["row"].path, point_grams(rows, cfg.rank, n, sides["col"][1] if held else None))
        if keep_epochs:
            columns, path = generation_at(done, "col-points")
        else:
            columns, path = stores["col"].commit(done), stores["col"].path
        column_grams = point_grams(columns, cfg.rank, n)
        kept, grams = ([*kept, columns], [*grams, column_grams]) if keep_epochs else ([], [column_grams])
    if held:
        alike_rows = at_models(held[2].select(F.col("of").alias("row_id"), F.col("id").bitwiseAND(F.lit((1 << POINT_BITS) - 1)).alias("plain")), part)
        shift = F.shiftleft(F.shiftright("row_id", POINT_BITS), POINT_BITS)
        rows = rows.join(alike_rows, F.col("id") == F.col("row_id")).select((F.col("plain") + shift).alias("id"), "vec", "err")
    return PointModels(points, part, rows, columns, cfg, kept, grams)


def with_empty_rows(model: FactorModel, ids: DataFrame) -> DataFrame:
    """Row vectors of all ids: those without observations solve to zero."""
    zero = F.array_repeat(F.lit(0.0), model.cfg.rank)
    return ids.select("id").join(as_lists(model.row_factors, model.cfg.rank), "id", "left").select("id", F.coalesce("vec", zero).alias("vec"))


def grid(train: DataFrame, given: DataFrame, hidden: DataFrame, regs, weights, cfg: FactorConfig, ks=(20, 50)) -> DataFrame:
    """reg, unobserved, k, recall_truth of a model for each pair of weights; all models are trained together."""
    points = [(float(r), float(w)) for r in regs for w in weights]
    models = fit_points(train, points, cfg)
    named = train.sparkSession.createDataFrame([(i, r, w) for i, (r, w) in enumerate(points)], "point int, reg double, unobserved double")
    return models.recall(given, hidden, ks).join(F.broadcast(named), "point").select("reg", "unobserved", "k", "recall_truth")


def best(results: DataFrame, metric: str = "recall_truth") -> DataFrame:
    """The pair of weights with the best metric for each k; ties go to the larger reg."""
    return results.groupBy("k").agg(F.max_by(F.struct("reg", "unobserved"), F.struct(metric, "reg", "unobserved")).alias("at"), F.max(metric).alias(metric)).select("k", "at.reg", "at.unobserved", metric)


__all__ = ["FactorModel", "ObsStats", "PointModels", "best", "fit", "fit_points", "grid", "loss_terms", "scores", "transposed", "with_empty_rows"]
