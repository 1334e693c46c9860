"""Gather strategies, commits, segments, precision and solvers."""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .. import sources
from ..config import FactorConfig
from ..functions import bf16, bf16_parts
from ..operators import factors, halfstep, segments, smallrank
from ..operators.arrays import ids, to_matrix
from ..operators.gram import gram
from ..operators.train import fit
from ..plans import planner
from ..runtime import generation
from . import twins as S
from .model import as_side, columns_of, embeddings, rounded, vectors, wide
from .twins import REG, UNOBSERVED

SMALL = FactorConfig(rank=2, reg=REG, unobserved=UNOBSERVED, blocks=4, hot_columns=50)


def _gathered(s, d, how: str) -> DataFrame:
    p = sources.purchases(s, d)
    got = halfstep.gather(p, vectors(columns_of(p)), SMALL, how)
    return rounded(got.select("row_id", "col_id", F.aggregate("vec", F.lit(0.0), lambda a, x: a + x).alias("vec_sum")))


def gather_broadcast(s, d):
    return _gathered(s, d, "broadcast")


def gather_shuffle(s, d):
    return _gathered(s, d, "shuffle")


def gather_hot_cold(s, d):
    return _gathered(s, d, "hot_cold")


def gather_masked_sum(s, d):
    return _gathered(s, d, "masked_sum")


def gather_routed(s, d):
    """Vectors sent once to each block of rows, then met by the block's observations."""
    p = sources.purchases(s, d)
    sent = halfstep.routing(p, 4).join(vectors(columns_of(p)), F.col("col_id") == F.col("id")).select("row_block", F.col("col_id").alias("need"), "vec")
    met = p.withColumn("my_block", halfstep.row_block(4)).join(sent, (F.col("my_block") == F.col("row_block")) & (F.col("col_id") == F.col("need")))
    return rounded(met.select("row_id", "col_id", F.aggregate("vec", F.lit(0.0), lambda a, x: a + x).alias("vec_sum")))


def _refitted(s, d, how: str, **change) -> DataFrame:
    from dataclasses import replace

    p = sources.purchases(s, d)
    h = generation(vectors(columns_of(p)), "frozen")
    cfg = replace(SMALL, **change)
    heavy = halfstep.heavy_rows(p, cfg.heavy_row) if "heavy_row" in change else None
    return as_side(wide(halfstep.refit_side(p, h, gram(h, 2), cfg, how, heavy), 2), "row_id", "w")


def refit_broadcast(s, d):
    return _refitted(s, d, "broadcast")


def refit_routed(s, d):
    return _refitted(s, d, "routed")


def refit_hot_cold(s, d):
    return _refitted(s, d, "hot_cold")


def refit_heavy_rows(s, d):
    """Rows of more than 40 cells are summed in parts."""
    return _refitted(s, d, "shuffle", heavy_row=40)


def partial_stats(s, d):
    return _refitted(s, d, "partial_stats")


def routing_sizes(s, d):
    p = sources.purchases(s, d).withColumn("row_block", halfstep.row_block(4))
    return p.groupBy("row_block").agg(F.countDistinct("col_id").alias("distinct_cols"), F.count(F.lit(1)).alias("obs"))


def scatter_masked_add(s, d):
    return rounded(factors.masked_add(columns_of(sources.purchases(s, d)), 4))


def scatter_commit(s, d):
    done = factors.commit(columns_of(sources.purchases(s, d)), 4)
    return done.groupBy(factors.shard_of(F.col("id"), 4).alias("shard")).agg(F.count(F.lit(1)).alias("n"), F.sum("id").alias("checksum"))


def shard_balance(s, d):
    return factors.shard_balance(sources.purchases(s, d).select("col_id").distinct(), 8, "col_id")


def _counts(s, d, label: str) -> DataFrame:
    if label == "purchases":
        obs = sources.purchases(s, d)
    else:
        obs = sources.word_observations(s, d, 5).select(F.col("doc_id").alias("row_id"), F.col("word").alias("col_id"))
    return obs.agg(F.count(F.lit(1)).alias("cells"), F.countDistinct("row_id").alias("n_rows"), F.countDistinct("col_id").alias("n_cols")).withColumn("matrix", F.lit(label))


def cost_gather_vs_stats(s, d):
    """Elements and bytes (16-bit vectors, 32-bit statistics) of both ways at d = 128."""
    both = _counts(s, d, "purchases").unionByName(_counts(s, d, "documents"))
    move, stats = F.col("cells") * 128, F.col("n_rows") * (128 * 131 // 2)
    return both.select("matrix", move.alias("gather_elements"), (move * 2).alias("gather_bytes"), stats.alias("partial_elements"), (stats * 4).alias("partial_bytes"), F.when(move * 2 <= stats * 4, "gather").otherwise("partial").alias("cheaper"))


def cost_flops_traffic(s, d):
    both = _counts(s, d, "purchases").unionByName(_counts(s, d, "documents"))
    return both.select("matrix", (F.col("cells") * 2 * 128 * 128).alias("flops_statistics"), ((F.col("n_rows") + F.col("n_cols")) * 128**3).alias("flops_solve"), (F.col("cells") * 128 * 8).alias("collective_elements_8"), (F.col("cells") * 128).alias("elements_per_worker"))


def segments_pack(s, d):
    packed = segments.pack(sources.purchases(s, d), 16)
    return packed.select("row_id", "seg_no", "n_valid", F.get("col_ids", 0).alias("first_id"))


def segments_roundtrip(s, d):
    p = sources.purchases(s, d)
    back = segments.unpack(segments.pack(p, 8))
    return p.exceptAll(back).agg(F.count(F.lit(1)).alias("missing")).crossJoin(back.exceptAll(p).agg(F.count(F.lit(1)).alias("extra")))


def padding_waste(s, d):
    return segments.waste(sources.purchases(s, d))


def refit_from_segments(s, d):
    p = sources.purchases(s, d)
    h = columns_of(p)
    system = segments.segment_system(segments.pack(p, 8), h)
    solved = smallrank.add_ridge(system, smallrank.gram_columns(h), REG, UNOBSERVED)
    return as_side(solved.select(F.col("row_id").alias("id"), *[x.alias(f"f{k}") for k, x in enumerate(smallrank.solve2())]), "row_id", "w")


def _elements(s, d) -> DataFrame:
    return embeddings(s, d).select(F.col("id").alias("vec_id"), F.posexplode("vec").alias("pos", "v"))


def bf16_round(s, d):
    return _elements(s, d).select("vec_id", "pos", (bf16(F.col("v")) + F.lit(0.0)).alias("v16"))


def bf16_error(s, d):
    e = _elements(s, d).where("v != 0").select((F.abs(bf16(F.col("v")) - F.col("v")) / F.abs("v")).alias("e"))
    return rounded(e.agg(F.max("e").alias("max_rel_err"), F.avg("e").alias("mean_rel_err")), 9)


def bf16_split(s, d):
    a, b, rest = bf16_parts(F.col("v"), 2)
    return _elements(s, d).select("vec_id", "pos", (a + 0.0).alias("part0"), (b + 0.0).alias("part1"), (rest + 0.0).alias("residual"))


def refit_mixed(s, d):
    p = sources.purchases(s, d)
    return as_side(smallrank.refit_low_precision(p, columns_of(p), REG, UNOBSERVED, False), "row_id", "w")


def refit_bf16_all(s, d):
    p = sources.purchases(s, d)
    return as_side(smallrank.refit_low_precision(p, columns_of(p), REG, UNOBSERVED, True), "row_id", "w")


def precision_ablation(s, d):
    """mode, reg, epoch, loss for four precisions and two weights, and whether the run collapsed."""
    e = generation(sources.events_as_observations(s, d), "obs")
    rows = []
    for mode in ("float64", "float32", "mixed", "bf16_all"):
        for reg in (5e-2, 1e-4):
            cfg = FactorConfig(rank=8, epochs=4, reg=reg, unobserved=1e-3, precision=mode)
            losses = [(h["epoch"], h["total"]) for h in fit(e, cfg).history]
            least = losses[0][1]
            for epoch, loss in losses:
                rows.append((mode, reg, int(epoch), float(loss), bool(not np.isfinite(loss) or loss > 1.5 * least)))
                least = min(least, loss) if np.isfinite(loss) else least
    return s.createDataFrame(rows, "mode string, reg double, epoch int, loss double, collapsed boolean")


def _solved(s, d, kind: str) -> DataFrame:
    p = sources.purchases(s, d)
    h = generation(vectors(columns_of(p, 3)), "frozen")
    cfg = FactorConfig(rank=3, reg=REG, unobserved=UNOBSERVED, solver=kind, cg_iters=24, cg_tol=1e-13)
    return as_side(wide(halfstep.refit_side(p, h, gram(h, 3), cfg, "shuffle"), 3), "row_id", "x")


def solve_lu(s, d):
    return _solved(s, d, "lu")


def solve_qr(s, d):
    return _solved(s, d, "qr")


def solve_cholesky(s, d):
    return _solved(s, d, "cholesky")


def solve_cg(s, d):
    return _solved(s, d, "cg")


def solve_cg_free(s, d):
    return _solved(s, d, "cg_free")


def solve_expressions(s, d):
    """The same systems by unrolled column expressions."""
    p = sources.purchases(s, d)
    return as_side(smallrank.refit(p, columns_of(p, 3), REG, UNOBSERVED, 3), "row_id", "x")


def solver_residuals(s, d):
    """solver, dim, seconds, largest residual and distance to LU over the systems of the embeddings: 40 vectors by id make one.

    A system of dim coordinates takes the first ones of its vectors; beyond their 64, those of the next vector of the system follow.
    """
    from ..operators.solvers import residual, solve_batch

    kinds = ("lu", "qr", "cholesky", "cg")

    def run(part: pa.Table) -> pa.Table:
        names, vectors, rows = ids(part.column("id")), to_matrix(part.column("vec"), 64), []
        order = np.argsort(names)
        system, vectors = names[order] // 40, vectors[order]
        starts = np.flatnonzero(np.concatenate([[True], system[1:] != system[:-1]]))
        after = np.arange(1, len(system) + 1)
        after[np.append(starts[1:], len(system)) - 1] = starts
        wide_vectors = np.concatenate([vectors, vectors[after]], axis=1)
        for dim in (16, 32, 64, 128):
            x = wide_vectors[:, :dim]
            found = halfstep.dense_systems(system, np.ones(len(x)), x, 40, 8 << 20)
            a, b = found.a + 0.05 * np.eye(dim), found.b
            base = solve_batch(a, b, "lu")
            for kind in kinds:
                began = time.perf_counter()
                out = solve_batch(a, b, kind, 2 * dim, 1e-10)
                rows.append((kind, dim, time.perf_counter() - began, float(residual(a, b, out).max()), float(np.abs(out - base).max())))
        return pa.table(dict(zip(("solver", "dim", "seconds", "max_residual", "max_diff"), map(list, zip(*rows)), strict=True))).cast(pa.schema([("solver", pa.string()), ("dim", pa.int32()), ("seconds", pa.float64()), ("max_residual", pa.float64()), ("max_diff", pa.float64())]))

    parts = embeddings(s, d).groupBy(F.floor(F.col("id") / 8000).alias("block")).applyInArrow(run, "solver string, dim int, seconds double, max_residual double, max_diff double")
    return parts.groupBy("solver", "dim").agg(F.sum("seconds").alias("seconds"), F.max("max_residual").alias("max_residual"), F.max("max_diff").alias("max_diff"))


def planner_choice(s, d):
    """What the planner takes for each matrix under three broadcast limits."""
    rows = []
    p = sources.purchases(s, d)
    for label, obs in (("by_row", p), ("by_column", smallrank.transpose(p))):
        stats = planner.observe(obs, blocks=4)
        for limit in (256 << 20, 1 << 10):
            cfg = FactorConfig(rank=64, broadcast_limit=limit, blocks=4)
            rows.append((label, limit, planner.choose_gather(stats, cfg), planner.scaling_knee(stats, cfg), planner.min_executors(stats, cfg)))
    return s.createDataFrame(rows, "side string, broadcast_limit long, gather string, knee int, min_executors int")


_H = f"WITH {S.P}, {S.factors('h', 'p', 'col_id')}"
_GATHERED = f"{_H} SELECT row_id, col_id, round(f0 + f1, 6) + 0.0 AS vec_sum FROM p JOIN h ON col_id = id"
_REFIT = f"{_H}, {S.refit('w', 'p', 'h')} SELECT id AS row_id, round(f0, 6) + 0.0 AS w0, round(f1, 6) + 0.0 AS w1 FROM w"
_COUNTS = (
    f"WITH {S.P}, {S.T}, ko AS (SELECT doc_id FROM t GROUP BY 1 HAVING count(*) >= 5), ki AS (SELECT word FROM t GROUP BY 1 HAVING count(*) >= 5), "
    "q AS (SELECT * FROM t WHERE doc_id IN (SELECT doc_id FROM ko) AND word IN (SELECT word FROM ki)), "
    "n AS (SELECT 'purchases' AS matrix, count(*) AS cells, count(DISTINCT row_id) AS n_rows, count(DISTINCT col_id) AS n_cols FROM p UNION ALL SELECT 'documents', count(*), count(DISTINCT doc_id), count(DISTINCT word) FROM q)"
)
_NUMBERED = "o AS (SELECT row_id, col_id, row_number() OVER (PARTITION BY row_id ORDER BY col_id) AS place FROM p)"
_V = "v AS (SELECT vec_id, i::integer AS pos, embedding[i + 1]::double AS v FROM embeddings, (SELECT unnest(range(0, 64)) AS i))"
_B = S.bf16
_LOW_H = f"{_H}, h16 AS (SELECT id, {_B('f0')} AS f0, {_B('f1')} AS f1 FROM h)"
_A = [f"a{i}{j}" for i, j in S.pairs(3)]
_CRAMER = (
    f"WITH {S.P}, {S.factors('h', 'p', 'col_id', 3)}, {S.gram('g', 'h', 3)}, {S.system('s', 'p', 'h', 3)}, {S.ridge('r', 's', 'g', rank=3)}, "
    "m AS (SELECT *, a11 * a22 - a12 * a12 AS c00, a02 * a12 - a01 * a22 AS c01, a01 * a12 - a02 * a11 AS c02, a00 * a22 - a02 * a02 AS c11, a01 * a02 - a00 * a12 AS c12, a00 * a11 - a01 * a01 AS c22 FROM r), "
    "t AS (SELECT *, a00 * c00 + a01 * c01 + a02 * c02 AS det FROM m) "
    "SELECT row_id, round((c00 * b0 + c01 * b1 + c02 * b2) / det, 6) + 0.0 AS x0, round((c01 * b0 + c11 * b1 + c12 * b2) / det, 6) + 0.0 AS x1, round((c02 * b0 + c12 * b1 + c22 * b2) / det, 6) + 0.0 AS x2 FROM t"
)


def waste_sql(lengths: str) -> str:
    """lengths: CTEs, the last of which, n, holds row_id and n."""
    parts = [f"SELECT 'segments' AS strategy, {w} AS width, sum(ceil(n / {w}.0::double))::bigint AS segments, sum(ceil(n / {w}.0::double) * {w})::bigint AS slots, sum(n)::bigint AS nnz FROM n" for w in (4, 8, 16, 32)]
    parts.append("SELECT 'pad_to_max', max(n)::integer, count(*), count(*) * max(n), sum(n)::bigint FROM n")
    parts.append("SELECT 'pad_per_batch', 64, sum(c)::bigint, sum(c * m)::bigint, sum(t)::bigint FROM (SELECT count(*) AS c, max(n) AS m, sum(n) AS t FROM n GROUP BY floor(row_id / 64.0::double))")
    return f"WITH {lengths}, x AS ({' UNION ALL '.join(parts)}) SELECT *, round(1.0::double - nnz::double / slots, 6) AS waste FROM x"


def _bf16_all_sql() -> str:
    names = ["a00", "a01", "a11", "b0", "b1"]
    return (
        f"{_LOW_H}, {S.gram('g0', 'h16')}, {S.system('s0', 'p', 'h16')}, s AS (SELECT row_id, {', '.join(f'{_B(c)} AS {c}' for c in names)} FROM s0), g AS (SELECT {', '.join(f'{_B(c)} AS {c}' for c in ('g00', 'g01', 'g11'))} FROM g0), "
        f"{S.ridge('r0', 's', 'g')}, r AS (SELECT row_id, {', '.join(f'{_B(c)} AS {c}' for c in names)} FROM r0), "
        f"m AS (SELECT row_id, {_B('a00 * a11')} AS p1, {_B('a01 * a01')} AS p2, {_B('a11 * b0')} AS q1, {_B('a01 * b1')} AS q2, {_B('a00 * b1')} AS u1, {_B('a01 * b0')} AS u2 FROM r), "
        f"z AS (SELECT row_id, {_B('p1 - p2')} AS det, {_B('q1 - q2')} AS x, {_B('u1 - u2')} AS y FROM m), k AS (SELECT row_id, CASE WHEN det <> 0 THEN x / det END AS x, CASE WHEN det <> 0 THEN y / det END AS y FROM z) "
        f"SELECT row_id, round({_B('x')}, 6) + 0.0 AS w0, round({_B('y')}, 6) + 0.0 AS w1 FROM k"
    )


SQL = {
    **{f"gather_{k}": _GATHERED for k in ("broadcast", "shuffle", "routed", "hot_cold", "masked_sum")},
    **{k: _REFIT for k in ("refit_broadcast", "refit_routed", "refit_hot_cold", "refit_heavy_rows", "partial_stats", "refit_from_segments")},
    "routing_sizes": f"WITH {S.P} SELECT (row_id % 4)::integer AS row_block, count(DISTINCT col_id) AS distinct_cols, count(*) AS obs FROM p GROUP BY 1",
    "scatter_masked_add": f"{_H} SELECT id, {S.rounded(['f0', 'f1'])} FROM h",
    "scatter_commit": f"{_H} SELECT (id % 4)::integer AS shard, count(*) AS n, sum(id)::bigint AS checksum FROM h GROUP BY 1",
    "shard_balance": f"{_H} SELECT (id % 8)::integer AS shard, count(*) AS n FROM h GROUP BY 1",
    "cost_gather_vs_stats": f"{_COUNTS} SELECT matrix, cells * 128 AS gather_elements, cells * 256 AS gather_bytes, n_rows * 8384 AS partial_elements, n_rows * 33536 AS partial_bytes, CASE WHEN cells * 256 <= n_rows * 33536 THEN 'gather' ELSE 'partial' END AS cheaper FROM n",
    "cost_flops_traffic": f"{_COUNTS} SELECT matrix, cells * 32768 AS flops_statistics, (n_rows + n_cols) * 2097152 AS flops_solve, cells * 1024 AS collective_elements_8, cells * 128 AS elements_per_worker FROM n",
    "segments_pack": f"WITH {S.P}, {_NUMBERED} SELECT row_id, floor((place - 1) / 16.0::double)::integer AS seg_no, count(*)::integer AS n_valid, min(col_id) AS first_id FROM o GROUP BY 1, 2",
    "segments_roundtrip": "SELECT 0::bigint AS missing, 0::bigint AS extra",
    "padding_waste": waste_sql(f"{S.P}, n AS (SELECT row_id, count(*) AS n FROM p GROUP BY row_id)"),
    "bf16_round": f"WITH {_V} SELECT vec_id, pos, {_B('v')} + 0.0 AS v16 FROM v",
    "bf16_error": f"WITH {_V}, e AS (SELECT abs({_B('v')} - v) / abs(v) AS e FROM v WHERE v <> 0) SELECT round(max(e), 9) + 0.0 AS max_rel_err, round(avg(e), 9) + 0.0 AS mean_rel_err FROM e",
    "bf16_split": f"WITH {_V}, a AS (SELECT vec_id, pos, v, {_B('v')} AS p0 FROM v), b AS (SELECT *, v - p0 AS r FROM a) SELECT vec_id, pos, p0 + 0.0 AS part0, {_B('r')} + 0.0 AS part1, r - {_B('r')} + 0.0 AS residual FROM b",
    "refit_mixed": f"{_LOW_H}, {S.refit('w', 'p', 'h16')} SELECT id AS row_id, round({_B('f0')}, 6) + 0.0 AS w0, round({_B('f1')}, 6) + 0.0 AS w1 FROM w",
    "refit_bf16_all": _bf16_all_sql(),
    **{k: _CRAMER for k in ("solve_lu", "solve_qr", "solve_cholesky", "solve_cg", "solve_cg_free", "solve_expressions")},
}
QUERIES = {k: globals()[k] for k in [*SQL, "precision_ablation", "solver_residuals", "planner_choice"]}
