"""The worked example, invariants and equivalences of the factorization."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from linkfactor import sources
from linkfactor.config import FactorConfig
from linkfactor.operators import factors, halfstep, segments, smallrank, solvers, train
from linkfactor.operators.gram import gram
from linkfactor.plans import planner
from linkfactor.schema import reject_bad_numbers, require
from linkfactor.workloads.model import columns_of, vectors, wide

SMALL = "/root/testdata/sf0.001"
MID = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def example(spark):
    h = spark.createDataFrame([(0, 1.0, 0.0), (1, 0.0, 1.0), (2, 1.0, 1.0)], "id long, f0 double, f1 double")
    obs = spark.createDataFrame([(0, 0, 1.0), (0, 1, 1.0), (1, 2, 1.0)], "row_id long, col_id long, y double")
    return obs, h


def as_dict(frame):
    return {r[0]: tuple(r)[1:] for r in frame.collect()}


def test_worked_example(spark, example):
    obs, h = example
    ids = spark.createDataFrame([(0,), (1,), (2,)], "id long")
    w = as_dict(smallrank.refit_all_rows(ids, obs, h, 0.5, 0.1))
    assert w[0] == pytest.approx((0.555556, 0.555556), abs=1e-6)
    assert w[1] == pytest.approx((0.357143, 0.357143), abs=1e-6)
    assert w[2] == (0.0, 0.0)
    rows = smallrank.refit(obs, h, 0.5, 0.1)
    loss = smallrank.loss_implicit(obs, rows, h, 0.5, 0.1).first()
    assert loss.observed == pytest.approx(0.476695, abs=1e-6)
    assert loss.all_cells / 0.1 == pytest.approx(2.617158, abs=1e-6)
    assert loss.reg == pytest.approx(2.436193, abs=1e-6)
    assert loss.total == pytest.approx(3.174604, abs=1e-5)
    assert smallrank.loss_implicit(obs, rows, h, 0.5, 0.1, bruteforce=True).first().total == pytest.approx(loss.total)
    assert solvers.bf16_round(np.array([0.555556, 0.357143])).tolist() == [0.5546875, 0.357421875]
    packed = segments.pack(obs, 2)
    assert packed.count() == 2 and segments.waste(obs, (2,)).where("strategy = 'segments'").first().waste == 0.25


@pytest.mark.parametrize("how", ["broadcast", "shuffle", "routed", "hot_cold", "masked_sum", "partial_stats"])
@pytest.mark.parametrize("blocks", [1, 3])
def test_all_gathers_agree(spark, how, blocks):
    obs = sources.purchases(spark, SMALL)
    h = vectors(columns_of(obs, 3)).cache()
    cfg = FactorConfig(rank=3, reg=0.1, unobserved=0.01, blocks=blocks, hot_columns=20)
    got = as_dict(wide(halfstep.refit_side(obs, h, gram(h, 3), cfg, how), 3))
    want = as_dict(smallrank.refit(obs, columns_of(obs, 3), 0.1, 0.01, 3))
    assert got.keys() == want.keys()
    assert max(abs(a - b) for k in got for a, b in zip(got[k], want[k], strict=True)) < 1e-9


def test_heavy_rows_and_segments_agree(spark):
    obs = sources.purchases(spark, SMALL)
    h = vectors(columns_of(obs)).cache()
    cfg = FactorConfig(rank=2, reg=0.1, unobserved=0.01)
    want = as_dict(smallrank.refit(obs, columns_of(obs), 0.1, 0.01))
    got = as_dict(wide(halfstep.refit_side(obs, h, gram(h, 2), cfg, "shuffle", halfstep.heavy_rows(obs, 30)), 2))
    assert all(got[k] == pytest.approx(want[k], abs=1e-9) for k in want)
    for width in (1, 4, 8, 32):
        packed = segments.pack(obs, width)
        assert packed.where(f"size(col_ids) != {width} or n_valid > {width} or n_valid < 1").count() == 0
        assert obs.exceptAll(segments.unpack(packed)).count() == 0
        system = as_dict(segments.segment_system(packed, columns_of(obs)).select("row_id", "a00", "b1"))
        plain = as_dict(smallrank.normal_system(obs, columns_of(obs)).select("row_id", "a00", "b1"))
        assert all(system[k] == pytest.approx(plain[k], abs=1e-9) for k in plain)


@pytest.mark.parametrize("dim", [1, 3, 32, 96])
def test_solvers_agree(dim):
    rng = np.random.default_rng(dim)
    x = rng.standard_normal((50, 20, dim))
    a, b = np.einsum("nki,nkj->nij", x, x) + 0.5 * np.eye(dim), rng.standard_normal((50, dim))
    base = solvers.solve_lu(a, b)
    assert np.abs(solvers.solve_qr(a, b) - base).max() < 1e-8
    assert np.abs(solvers.solve_cholesky(a, b) - base).max() < 1e-8
    assert np.abs(solvers.solve_cg(a, b, 6 * dim + 10, 1e-12) - base).max() < 1e-6
    warm = solvers.solve_cg(a, b, 1, 1e-12, start=base)
    assert solvers.residual(a, b, warm).max() < 1e-8
    assert np.allclose(solvers.unpack(solvers.pack(a), dim), a)
    y = rng.standard_normal((50, 20))
    owner = np.repeat(np.arange(50), 20)
    free = solvers.solve_cg_free(x.reshape(-1, dim), owner, y.reshape(-1), 0.5 * np.eye(dim), 50, 6 * dim + 10, 1e-12)
    assert np.abs(free - solvers.solve_lu(a, np.einsum("nk,nkd->nd", y, x))).max() < 1e-6


def test_bf16_is_round_to_even():
    x = np.random.default_rng(2).standard_normal(20000) * 10.0 ** np.random.default_rng(3).integers(-20, 20, 20000)
    c = x * (2.0**45 + 1)
    by_product, by_bits = c - (c - x), solvers.bf16_round(x.astype(np.float32))
    exact = x.astype(np.float32).astype(float) == x
    assert (np.abs(by_product - by_bits)[exact] == 0).all() and (np.abs(by_bits - x) <= np.abs(x) * 2.0**-8 * 1.0001).all()
    assert (solvers.bf16_unpack(solvers.bf16_pack(x)) == by_bits).all()


def test_loss_never_rises_and_half_step_is_stationary(spark):
    obs = sources.events_as_observations(spark, SMALL)
    model = train.fit(obs, FactorConfig(rank=4, epochs=4, reg=0.05, unobserved=0.01))
    losses = [h["total"] for h in model.history]
    assert all(b <= a + 1e-9 for a, b in zip(losses, losses[1:], strict=False))
    assert model.num_parameters() == 4 * (obs.select("row_id").distinct().count() + obs.select("col_id").distinct().count())
    # The columns were refitted last: moving any of them can only raise the loss.
    cfg = model.cfg
    base = model.loss(obs)["total"]
    for shift in (0.01, -0.01):
        moved = model.col_factors.withColumn("vec", F.transform("vec", lambda x, i: F.when((F.col("id") % 7 == 0) & (i == 1), x + shift).otherwise(x)))
        assert train.loss_terms(obs, model.row_factors, moved, cfg)["total"] > base


def test_fold_in_equals_a_half_step_and_rotation_keeps_predictions(spark):
    obs = sources.events_as_observations(spark, SMALL).cache()
    model = train.fit(obs, FactorConfig(rank=3, epochs=2, reg=0.1, unobserved=0.01), track_loss=False)
    folded = as_dict(wide(model.fold_in(obs.where("row_id < 5")), 3))
    full = as_dict(wide(halfstep.refit_side(obs, model.col_factors, gram(model.col_factors, 3), model.cfg, "shuffle"), 3))
    assert folded and all(folded[k] == pytest.approx(full[k], abs=1e-9) for k in folded)
    c, s = 0.6, 0.8
    turn = F.array(F.get("vec", 0) * c - F.get("vec", 1) * s, F.get("vec", 0) * s + F.get("vec", 1) * c, F.get("vec", 2))
    turned = model.col_factors.select("id", turn.alias("vec")).cache()
    again = halfstep.refit_side(obs, turned, gram(turned, 3), model.cfg, "shuffle")
    a = {(r.row_id, r.col_id): r.score for r in train.scores(obs, again, turned).collect()}
    b = {(r.row_id, r.col_id): r.score for r in train.scores(obs, halfstep.refit_side(obs, model.col_factors, gram(model.col_factors, 3), model.cfg, "shuffle"), model.col_factors).collect()}
    assert max(abs(a[k] - b[k]) for k in a) < 1e-8


def test_precisions(spark):
    obs = sources.events_as_observations(spark, SMALL)
    ends = {p: train.fit(obs, FactorConfig(rank=4, epochs=3, reg=0.1, unobserved=0.01, precision=p)).history[-1]["total"] for p in ("float64", "float32", "mixed")}
    assert ends["float32"] == pytest.approx(ends["float64"], rel=1e-3)
    assert ends["mixed"] == pytest.approx(ends["float64"], rel=0.03)
    for precision, size in (("mixed", 8), ("bf16_all", 8), ("float32", 16)):
        table = train.fit(obs, FactorConfig(rank=4, epochs=1, precision=precision, reg=0.1), track_loss=False).row_factors
        assert dict(table.dtypes)["vec"] == "binary" and {len(r.vec) for r in table.collect()} == {size}
        plain = factors.as_lists(table, 4)
        assert as_dict(wide(factors.as_lists(factors.store_table(plain, 4, precision), 4), 4)) == as_dict(wide(plain, 4))
        assert np.allclose(gram(table, 4), gram(plain, 4))


@pytest.mark.parametrize(("how", "solver"), [("broadcast", "lu"), ("shuffle", "cg_free"), ("routed", "cg_free"), ("hot_cold", "cg"), ("partial_stats", "lu")])
def test_packed_vectors_by_all_gathers_and_widths(spark, how, solver):
    obs = sources.purchases(spark, SMALL).where("row_id < 60")
    h = vectors(columns_of(obs, 3)).cache()
    outs = []
    for precision, width in (("mixed", 1), ("mixed", 32)):
        cfg = FactorConfig(rank=3, reg=0.1, unobserved=0.01, blocks=3, hot_columns=20, precision=precision, solver=solver, cg_iters=40, cg_tol=1e-7, segment_width=width)
        done = halfstep.refit_side(obs, h, gram(h, 3), cfg, how).cache()
        outs.append(as_dict(wide(factors.as_lists(done, 3), 3)))
        pairs = train.scores(obs, done, factors.store_table(h, 3, "mixed"), 3)
        error = pairs.agg(F.sum((F.col("y") - F.col("score")) ** 2)).first()[0]
        assert done.agg(F.sum("err")).first()[0] == pytest.approx(error, rel=1e-4)
    want = as_dict(smallrank.refit(obs, columns_of(obs, 3), 0.1, 0.01, 3))
    for got in outs:
        assert got.keys() == want.keys()
        assert max(abs(a - b) for k in got for a, b in zip(got[k], want[k], strict=True)) < 0.05


def sequential(cells, rank, epochs, reg, weight, start):
    """The factorization on one machine, row by row in loops."""
    rows, cols = sorted({r for r, _, _ in cells}), sorted({c for _, c, _ in cells})
    h = {c: np.array(start[c]) for c in cols}
    w, losses = {}, []
    for _ in range(epochs):
        for side in (0, 1):
            frozen, own, names = (h, w, rows) if side == 0 else (w, h, cols)
            total = sum(np.outer(v, v) for v in frozen.values())
            for name in names:
                a, b = weight * total + reg * np.eye(rank), np.zeros(rank)
                for r, c, y in cells:
                    if (r, c)[side] == name:
                        v = frozen[(c, r)[side]]
                        a, b = a + np.outer(v, v), b + y * v
                own[name] = np.linalg.solve(a, b)
        loss = sum((y - w[r] @ h[c]) ** 2 for r, c, y in cells) + weight * sum((x @ z) ** 2 for x in w.values() for z in h.values())
        losses.append(loss + reg * sum(x @ x for x in [*w.values(), *h.values()]))
    return w, h, losses


@pytest.mark.parametrize("solver", ["lu", "cg"])
def test_training_is_the_sequential_one(spark, solver):
    obs = sources.events_as_observations(spark, SMALL).where("row_id < 25").cache()
    cells = [tuple(r) for r in obs.collect()]
    cols = sorted({c for _, c, _ in cells})
    rng = np.random.default_rng(6)
    start = {c: rng.standard_normal(3).tolist() for c in cols}
    frame = spark.createDataFrame([(c, start[c]) for c in cols], "id long, vec array<double>")
    w, h, losses = sequential(cells, 3, 3, 0.1, 0.05, start)
    model = train.fit(obs, FactorConfig(rank=3, epochs=3, reg=0.1, unobserved=0.05, solver=solver, cg_iters=50, cg_tol=1e-12, segment_width=4), start=frame)
    for mine, theirs in ((model.row_factors, w), (model.col_factors, h)):
        got = as_dict(wide(mine, 3))
        assert got.keys() == theirs.keys() and max(np.abs(np.array(got[k]) - theirs[k]).max() for k in got) < 1e-7
    assert [x["total"] for x in model.history] == pytest.approx(losses, rel=1e-8)
    assert model.loss(obs)["total"] == pytest.approx(losses[-1], rel=1e-8)


def test_warm_start_saves_steps(spark):
    obs = sources.purchases(spark, SMALL).where("row_id < 40")
    h = vectors(columns_of(obs, 3)).cache()
    cfg = FactorConfig(rank=3, reg=0.1, unobserved=0.01, solver="cg", cg_iters=1, cg_tol=1e-12)
    exact = smallrank.refit(obs, columns_of(obs, 3), 0.1, 0.01, 3)
    want = as_dict(exact)
    for solver in ("cg", "cg_free"):
        one = FactorConfig(**{**cfg.__dict__, "solver": solver})
        cold = as_dict(wide(halfstep.refit_side(obs, h, gram(h, 3), one, "shuffle"), 3))
        warm = as_dict(wide(halfstep.refit_side(obs, h, gram(h, 3), one, "shuffle", start=vectors(exact)), 3))
        off = lambda got: max(abs(a - b) for k in want for a, b in zip(got[k], want[k], strict=True))
        assert warm.keys() == want.keys() and off(warm) < 1e-9 < off(cold)


def test_models_of_several_weights_in_one_job(spark):
    obs = sources.events_as_observations(spark, SMALL)
    points = [(0.1, 0.01), (0.5, 0.001), (0.02, 0.1)]
    cfg = FactorConfig(rank=3, epochs=2)
    together = train.fit_points(obs, points, cfg, keep_epochs=True)
    got = as_dict(wide(together.col_factors, 3))
    for i, (reg, weight) in enumerate(points):
        alone = as_dict(wide(train.fit(obs, FactorConfig(rank=3, epochs=2, reg=reg, unobserved=weight), track_loss=False).col_factors, 3))
        assert all(got[(i << 40) + k] == pytest.approx(alone[k], abs=1e-9) for k in alone)
    assert len(together.epochs) == 2 and len(got) == 3 * len(alone)
    given, hidden = obs.where("row_id < 9 and col_id % 2 = 0"), obs.where("row_id < 9 and col_id % 2 = 1")
    by_epoch = {(r.epoch, r.point, r.k): r.recall_truth for r in together.recall_by_epoch(given, hidden, (5,)).collect()}
    last = {(2, r.point, r.k): r.recall_truth for r in together.recall(given, hidden, (5,)).collect()}
    assert len(by_epoch) == 6 and all(by_epoch[k] == pytest.approx(v) for k, v in last.items())
    with pytest.raises(ValueError, match="range"):
        train.fit_points(obs.withColumn("row_id", F.lit(-1)), points, cfg)


def test_repeated_cells_are_summed(spark):
    twice = spark.createDataFrame([(1, 1, 1.0), (1, 1, 2.0), (2, 1, 1.0)], "row_id long, col_id long, y double")
    once = spark.createDataFrame([(1, 1, 3.0), (2, 1, 1.0)], twice.schema)
    cfg = FactorConfig(rank=2, epochs=2, reg=0.1, unobserved=0.01)
    assert as_dict(wide(train.fit(twice, cfg).row_factors, 2)) == as_dict(wide(train.fit(once, cfg).row_factors, 2))


def test_odd_observations(spark):
    obs = spark.createDataFrame([(7, 70, 0.0), (7, 90, -2.0), (9, 70, 1.0)], "row_id long, col_id long, y double")
    model = train.fit(obs, FactorConfig(rank=1, epochs=2, reg=0.1, unobserved=0.0))
    assert model.row_factors.count() == 2
    everyone = train.with_empty_rows(model, spark.createDataFrame([(7,), (8,), (9,)], "id long"))
    assert {r.id: r.vec for r in everyone.collect()}[8] == [0.0]
    with pytest.raises(Exception, match="finite label"):
        reject_bad_numbers(spark.createDataFrame([(1, 1, float("nan"))], obs.schema)).collect()
    with pytest.raises(ValueError, match="missing"):
        require(obs.drop("y"), "row_id BIGINT, y DOUBLE")
    with pytest.raises(ValueError):
        FactorConfig(solver="magic")
    singular = np.zeros((1, 2, 2))
    with pytest.raises(np.linalg.LinAlgError):
        solvers.solve_lu(singular, np.ones((1, 2)))


def test_save_and_load(spark, tmp_path):
    obs = sources.events_as_observations(spark, SMALL)
    model = train.fit(obs, FactorConfig(rank=2, epochs=1, reg=0.1))
    model.save(str(tmp_path / "m"))
    again = train.FactorModel.load(spark, str(tmp_path / "m"))
    assert again.cfg == model.cfg and again.history == model.history
    assert as_dict(wide(again.row_factors, 2)) == as_dict(wide(model.row_factors, 2))


def test_against_the_built_in_implicit_factorization(spark):
    """On a regular graph both objectives agree up to scale, so either's solution must be about as good."""
    from pyspark.ml.recommendation import ALS

    n, reg, weight = 24, 0.05, 0.1
    cells = [(i, (i + k) % n, 1.0 + weight) for i in range(n) for k in (0, 1, 3)]
    obs = spark.createDataFrame(cells, "row_id long, col_id long, y double")
    cfg = FactorConfig(rank=4, epochs=15, reg=reg, unobserved=weight)
    mine = train.fit(obs, cfg).history[-1]["total"]
    built = ALS(rank=4, maxIter=15, implicitPrefs=True, alpha=1 / weight, regParam=reg / (weight * 3), userCol="row_id", itemCol="col_id", ratingCol="y", seed=3).fit(obs.withColumn("y", F.lit(1.0)))
    sides = [f.select(F.col("id").cast("long").alias("id"), F.col("features").cast("array<double>").alias("vec")).cache() for f in (built.userFactors, built.itemFactors)]
    theirs = train.loss_terms(obs, *sides, cfg)["total"]
    assert mine <= theirs * 1.05


def test_planner(spark):
    stats = planner.ObsStats(cells=29_904_000_000, rows=365_400_000, columns=365_400_000, longest=10**6)
    cfg = FactorConfig(rank=128, precision="mixed", blocks=1000)
    assert planner.min_executors(stats, cfg, 16 << 30) in range(8, 33)
    assert planner.choose_gather(stats, cfg) != "broadcast"
    assert planner.choose_gather(planner.ObsStats(1000, 10, 10, 100), cfg) == "broadcast"
    moved = planner.traffic(stats, cfg)
    assert moved["shuffle"] < moved["partial_stats"]
    assert moved["shuffle"] * 4 == planner.traffic(stats, FactorConfig(rank=128, blocks=1000))["shuffle"]
    skewed = planner.ObsStats(cells=29_904_000_000, rows=365_400_000, columns=365_400_000, longest=10**6, routed=20_000_000_000, cold=10**9)
    assert planner.choose_gather(skewed, FactorConfig(rank=128, precision="mixed", hot_columns=1_000_000, blocks=1000), 100) == "hot_cold"
    assert planner.cost_report(stats, cfg)["parameters"] == pytest.approx(93.5e9, rel=0.01)


def test_dictionary_and_shards(spark):
    keys = spark.createDataFrame([("b",), ("a",), ("c",), ("a",), (None,)], "k string")
    assert {r.key: r.id for r in factors.dictionary(keys, "k").collect()} == {"a": 0, "b": 1, "c": 2}
    assert factors.dictionary(keys.limit(0), "k").count() == 0
    table = smallrank.init_factors(spark.range(100))
    assert as_dict(factors.masked_add(table, 5)) == as_dict(table)
    assert sum(r.n for r in factors.shard_balance(table, 7).collect()) == 100


@pytest.mark.parametrize(("solver", "precision"), [("lu", "float64"), ("cg", "float64"), ("cg_free", "float64"), ("lu", "float32")])
def test_held_tables_agree_and_shuffle_nothing(spark, solver, precision):
    """frozen tables went through the driver in every half-step."""
    obs = sources.purchases(spark, SMALL).where("row_id < 60").unionByName(spark.createDataFrame([(7, 10**15, 1.0), (99, -5, 1.0)], "row_id long, col_id long, y double"))
    h = vectors(columns_of(sources.purchases(spark, SMALL), 3)).cache()
    cfg = FactorConfig(rank=3, reg=0.1, unobserved=0.01, solver=solver, precision=precision, cg_iters=40, cg_tol=1e-12, solve_batch_bytes=500)
    heavy = halfstep.heavy_rows(obs, 42) if solver == "lu" else None
    start = vectors(smallrank.refit(obs, columns_of(obs, 3), 0.2, 0.01, 3)) if solver != "lu" else None
    stored = halfstep.generation_at(halfstep.records(obs), "records")[0]
    g = gram(h, 3)
    got = as_dict(wide(factors.as_lists(halfstep.refit_side(obs, h, g, cfg, "held", heavy, start), 3), 3))
    own = as_dict(wide(halfstep.refit_side(obs, h, g, FactorConfig(rank=3, reg=0.1, unobserved=0.01), "held", plan={"records": (stored, None)}), 3))
    narrow = smallrank.refit(obs.join(h, F.col("id") == F.col("col_id"), "left_semi"), wide(h, 3), 0.1, 0.01, 3)
    want = as_dict(narrow)
    for found, off in ((got, 1e-9 if precision == "float64" else 1e-5), (own, 1e-9)):
        assert found.keys() == want.keys() and max(abs(a - b) for k in found for a, b in zip(found[k], want[k], strict=True)) < off
    plan = halfstep.refit_side(obs, h, g, cfg, "held", plan={"records": (stored, None)})._jdf.queryExecution().toString()
    assert "Exchange" not in plan and "Join" not in plan


def test_generations_leave_no_shuffle(spark, tmp_path):
    """shuffle files of every half-step stayed until the session's end."""
    from linkfactor.runtime import _CLEANUP, generation

    local = [d for d in spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().localDirsString()]
    import glob

    files = lambda: {f for d in local for f in glob.glob(f"{d}/*/shuffle_*")}
    before = files()
    out = generation(spark.range(1000).withColumn("k", F.col("id") % 7).groupBy("k").count(), "sums")
    assert out.count() == 7 and spark.conf.get(_CLEANUP, None) in (None, "false")
    kept = files() - before
    assert len([f for f in kept if f.endswith(".data")]) <= 1  # the count's own
