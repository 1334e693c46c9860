"""Settings of the factorization."""

from __future__ import annotations

from dataclasses import dataclass

SOLVERS = ("auto", "lu", "qr", "cholesky", "cg", "cg_free")
GATHERS = ("auto", "broadcast", "shuffle", "routed", "hot_cold", "masked_sum", "partial_stats", "held")
PRECISIONS = ("float64", "float32", "mixed", "bf16_all")


@dataclass(frozen=True)
class FactorConfig:
    """reg is the weight of the squared norms, unobserved that of the squared predictions over all cells."""

    rank: int = 128
    epochs: int = 16
    reg: float = 1e-2
    unobserved: float = 1e-5
    solver: str = "auto"
    cg_iters: int | None = None
    cg_tol: float = 1e-6
    gather: str = "auto"
    precision: str = "float64"
    segment_width: int = 16
    blocks: int | None = None
    seed: int = 42
    tol: float | None = None
    broadcast_limit: int = 256 << 20
    solve_batch_bytes: int = 64 << 20
    block_bytes: int = 256 << 20
    heavy_row: int = 1 << 16
    hot_columns: int = 100_000

    def __post_init__(self) -> None:
        for value, allowed in ((self.solver, SOLVERS), (self.gather, GATHERS), (self.precision, PRECISIONS)):
            if value not in allowed:
                raise ValueError(f"{value!r} is not one of {allowed}")
        if self.rank < 1 or self.segment_width < 1 or self.reg < 0 or self.unobserved < 0:
            raise ValueError("rank and width must be positive, weights not negative")

    @property
    def bytes_per_number(self) -> int:
        """Bytes of a number as vectors are stored, shuffled and broadcast."""
        return {"float64": 8, "float32": 4, "mixed": 2, "bf16_all": 2}[self.precision]

    def chosen_solver(self) -> str:
        """On CPUs a direct solve is as fast as conjugate gradients of equal accuracy; at high rank the matrix-free form saves the normal matrices."""
        return self.solver if self.solver != "auto" else "lu"

    def iterations(self) -> int:
        return self.cg_iters or min(2 * self.rank, max(32, self.rank))
