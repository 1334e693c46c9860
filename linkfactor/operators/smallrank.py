"""The model at rank 2 to 8 in column expressions alone (wide layout: id, f0, f1, ...).

These are the same half-steps, losses and Gram sums as the array path, without Python, so
that any SQL engine can check them. ``id_col`` names differ by side: a factor table is (id,
f0 ...), observations are (row_id, col_id, y).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import bf16, start_value


def cols(rank: int, prefix: str = "f") -> list[str]:
    return [f"{prefix}{k}" for k in range(rank)]


def init_factors(ids: DataFrame, rank: int = 2, id_col: str = "id") -> DataFrame:
    """Deterministic start: a hash of id and coordinate."""
    return ids.select(F.col(id_col).alias("id"), *[start_value(F.col(id_col), k).alias(f"f{k}") for k in range(rank)])


def transpose(obs: DataFrame) -> DataFrame:
    """The observations of the other pass: columns become rows."""
    return obs.select(F.col("col_id").alias("row_id"), F.col("row_id").alias("col_id"), "y")


def gram_columns(fac: DataFrame, rank: int = 2) -> DataFrame:
    """One row g00, g01, ... of the upper triangle; partial sums are combined per partition first."""
    return fac.agg(*[F.coalesce(F.sum(F.col(f"f{i}") * F.col(f"f{j}")), F.lit(0.0)).alias(f"g{i}{j}") for i in range(rank) for j in range(i, rank)])


def normal_system(obs: DataFrame, fac: DataFrame, rank: int = 2) -> DataFrame:
    """row_id, a00, a01, ..., b0, ..., n from the gathered vectors; the label enters the right side only."""
    gathered = obs.join(fac, F.col("col_id") == F.col("id"))
    sums = [F.sum(F.col(f"f{i}") * F.col(f"f{j}")).alias(f"a{i}{j}") for i in range(rank) for j in range(i, rank)]
    return gathered.groupBy("row_id").agg(*sums, *[F.sum(F.col("y") * F.col(f"f{i}")).alias(f"b{i}") for i in range(rank)], F.count(F.lit(1)).alias("n"))


def add_ridge(system: DataFrame, gram: DataFrame, reg: float, unobserved: float, rank: int = 2) -> DataFrame:
    """Add unobserved * Gram + reg * identity; the Gram is one row, broadcast."""
    if unobserved:
        system = system.crossJoin(F.broadcast(gram))
    fixed = {f"a{i}{j}": F.col(f"a{i}{j}") + (F.lit(unobserved) * F.col(f"g{i}{j}") if unobserved else F.lit(0.0)) + F.lit(reg if i == j else 0.0) for i in range(rank) for j in range(i, rank)}
    return system.withColumns(fixed).drop(*[f"g{i}{j}" for i in range(rank) for j in range(i, rank)])


def solve2() -> list[Column]:
    """Closed form of the 2 x 2 system."""
    det = F.col("a00") * F.col("a11") - F.col("a01") * F.col("a01")
    return [(F.col("a11") * F.col("b0") - F.col("a01") * F.col("b1")) / det, (F.col("a00") * F.col("b1") - F.col("a01") * F.col("b0")) / det]


def solve_by_elimination(rank: int) -> list[Column]:
    """Unrolled Cholesky of small symmetric systems, as column expressions."""
    a = {(i, j): F.col(f"a{i}{j}") for i in range(rank) for j in range(i, rank)}
    low: dict[tuple[int, int], Column] = {}
    for i in range(rank):
        for j in range(i + 1):
            rest = a[j, i]
            for k in range(j):
                rest = rest - low[i, k] * low[j, k]
            low[i, j] = F.sqrt(rest) if i == j else rest / low[j, j]
    half: list[Column] = []
    for i in range(rank):
        rest = F.col(f"b{i}")
        for k in range(i):
            rest = rest - low[i, k] * half[k]
        half.append(rest / low[i, i])
    out: list[Column] = [F.lit(0.0)] * rank
    for i in reversed(range(rank)):
        rest = half[i]
        for k in range(i + 1, rank):
            rest = rest - low[k, i] * out[k]
        out[i] = rest / low[i, i]
    return out


def refit(obs: DataFrame, fac: DataFrame, reg: float, unobserved: float, rank: int = 2) -> DataFrame:
    """One half-step: (id, f0, ...) of the row side; rows without observations are absent (their vector is zero)."""
    system = add_ridge(normal_system(obs, fac, rank), gram_columns(fac, rank), reg, unobserved, rank)
    solved = solve2() if rank == 2 else solve_by_elimination(rank)
    return system.select(F.col("row_id").alias("id"), *[x.alias(f"f{k}") for k, x in enumerate(solved)])


def refit_all_rows(ids: DataFrame, obs: DataFrame, fac: DataFrame, reg: float, unobserved: float, rank: int = 2) -> DataFrame:
    """Like refit, with a zero vector for ids that no observation names."""
    solved = refit(obs, fac, reg, unobserved, rank).withColumnRenamed("id", "solved_id")
    return ids.select("id").join(solved, F.col("id") == F.col("solved_id"), "left").select("id", *[F.coalesce(f"f{k}", F.lit(0.0)).alias(f"f{k}") for k in range(rank)])


def refit_low_precision(obs: DataFrame, fac: DataFrame, reg: float, unobserved: float, everything: bool) -> DataFrame:
    """Rank 2 with 16-bit tables; the solve is in full precision, or with ``everything`` each stored number of it is rounded too."""
    table = fac.select("id", bf16(F.col("f0")).alias("f0"), bf16(F.col("f1")).alias("f1"))
    if not everything:
        solved = refit(obs, table, reg, unobserved)
        return solved.select("id", bf16(F.col("f0")).alias("f0"), bf16(F.col("f1")).alias("f1"))
    names = ["a00", "a01", "a11", "b0", "b1"]
    rough = normal_system(obs, table).withColumns({c: bf16(F.col(c)) for c in names})
    gram = gram_columns(table).select(*[bf16(F.col(c)).alias(c) for c in ("g00", "g01", "g11")])
    rough = add_ridge(rough, gram, reg, unobserved).withColumns({c: bf16(F.col(c)) for c in names})
    det = bf16(bf16(F.col("a00") * F.col("a11")) - bf16(F.col("a01") * F.col("a01")))
    x = bf16(bf16(F.col("a11") * F.col("b0")) - bf16(F.col("a01") * F.col("b1")))
    y = bf16(bf16(F.col("a00") * F.col("b1")) - bf16(F.col("a01") * F.col("b0")))
    return rough.select(F.col("row_id").alias("id"), bf16(F.try_divide(x, det)).alias("f0"), bf16(F.try_divide(y, det)).alias("f1"))


def predict(pairs: DataFrame, rows: DataFrame, columns: DataFrame, rank: int = 2) -> DataFrame:
    """pairs (row_id, col_id, ...) with the column score."""
    w = rows.select(F.col("id").alias("w_id"), *[F.col(f"f{k}").alias(f"w{k}") for k in range(rank)])
    h = columns.select(F.col("id").alias("h_id"), *[F.col(f"f{k}").alias(f"h{k}") for k in range(rank)])
    score = sum((F.col(f"w{k}") * F.col(f"h{k}") for k in range(1, rank)), F.col("w0") * F.col("h0"))
    joined = pairs.join(w, F.col("row_id") == F.col("w_id")).join(h, F.col("col_id") == F.col("h_id"))
    return joined.select(*pairs.columns, score.alias("score"))


def observed_error(obs: DataFrame, rows: DataFrame, columns: DataFrame, rank: int = 2) -> DataFrame:
    scored = predict(obs, rows, columns, rank)
    return scored.agg(F.coalesce(F.sum((F.col("y") - F.col("score")) * (F.col("y") - F.col("score"))), F.lit(0.0)).alias("observed"))


def _norms(fac: DataFrame, name: str, rank: int) -> DataFrame:
    return fac.agg(F.coalesce(F.sum(sum((F.col(f"f{k}") * F.col(f"f{k}") for k in range(1, rank)), F.col("f0") * F.col("f0"))), F.lit(0.0)).alias(name))


def loss_explicit(obs: DataFrame, rows: DataFrame, columns: DataFrame, reg: float, rank: int = 2) -> DataFrame:
    """observed, reg_row, reg_col, total of the explicit objective; one row."""
    one = observed_error(obs, rows, columns, rank).crossJoin(_norms(rows, "norm_row", rank)).crossJoin(_norms(columns, "norm_col", rank))
    one = one.select("observed", (F.lit(reg) * F.col("norm_row")).alias("reg_row"), (F.lit(reg) * F.col("norm_col")).alias("reg_col"))
    return one.withColumn("total", F.col("observed") + F.col("reg_row") + F.col("reg_col"))


def all_cells(rows: DataFrame, columns: DataFrame, rank: int = 2) -> DataFrame:
    """Sum of squared predictions over all cells, as the inner product of the two Gram matrices."""
    g = gram_columns(rows, rank).select(*[F.col(f"g{i}{j}").alias(f"w{i}{j}") for i in range(rank) for j in range(i, rank)])
    both = g.crossJoin(gram_columns(columns, rank))
    terms = [F.lit(1.0 if i == j else 2.0) * F.col(f"w{i}{j}") * F.col(f"g{i}{j}") for i in range(rank) for j in range(i, rank)]
    return both.select(sum(terms[1:], terms[0]).alias("cells"))


def all_cells_bruteforce(rows: DataFrame, columns: DataFrame, rank: int = 2) -> DataFrame:
    """The same over the cross product; for small tables and tests only."""
    w = rows.select(*[F.col(f"f{k}").alias(f"w{k}") for k in range(rank)])
    h = columns.select(*[F.col(f"f{k}").alias(f"h{k}") for k in range(rank)])
    score = sum((F.col(f"w{k}") * F.col(f"h{k}") for k in range(1, rank)), F.col("w0") * F.col("h0"))
    return w.crossJoin(h).agg(F.coalesce(F.sum(score * score), F.lit(0.0)).alias("cells"))


def loss_implicit(obs: DataFrame, rows: DataFrame, columns: DataFrame, reg: float, unobserved: float, rank: int = 2, bruteforce: bool = False) -> DataFrame:
    """observed, all_cells, reg, total of the implicit objective; one row."""
    cells = (all_cells_bruteforce if bruteforce else all_cells)(rows, columns, rank)
    one = loss_explicit(obs, rows, columns, reg, rank).crossJoin(cells)
    one = one.select("observed", (F.lit(unobserved) * F.col("cells")).alias("all_cells"), (F.col("reg_row") + F.col("reg_col")).alias("reg"))
    return one.withColumn("total", F.col("observed") + F.col("all_cells") + F.col("reg"))


def epochs(obs: DataFrame, columns: DataFrame, reg: float, unobserved: float, n: int, rank: int = 2, cut=None) -> list[tuple[DataFrame, DataFrame]]:
    """(row factors, column factors) after each of n epochs; ``cut`` materializes each half-step."""
    cut = cut or (lambda frame: frame)
    back, out = transpose(obs), []
    for _ in range(n):
        rows = cut(refit(obs, columns, reg, unobserved, rank))
        columns = cut(refit(back, rows, reg, unobserved, rank))
        out.append((rows, columns))
    return out
