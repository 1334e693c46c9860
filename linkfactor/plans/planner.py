"""Cost model of a half-step: work, traffic and memory by strategy, from a few counts."""

from __future__ import annotations

from dataclasses import dataclass
from math import ceil

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..config import FactorConfig


@dataclass(frozen=True)
class ObsStats:
    cells: int
    rows: int
    columns: int
    longest: int
    routed: int | None = None
    cold: int | None = None

    @property
    def mean_row(self) -> float:
        return self.cells / max(1, self.rows)


def observe(obs: DataFrame, blocks: int | None = None, cfg: FactorConfig | None = None) -> ObsStats:
    """Counts of an observation table (cells, or rows with lists col_ids); with blocks also the vectors that a routed gather would send, with cfg the cells of columns that aren't hot."""
    sizes = obs.select(F.size("col_ids").alias("n")) if "col_ids" in obs.columns else obs.groupBy("row_id").agg(F.count(F.lit(1)).alias("n"))
    lengths = sizes.agg(F.sum("n"), F.count(F.lit(1)), F.max("n")).first()
    if "col_ids" in obs.columns:
        obs = obs.select("row_id", F.explode("col_ids").alias("col_id"))
    columns = obs.agg(F.approx_count_distinct("col_id", 0.01)).first()[0]
    routed = cold = None
    if blocks:
        from ..operators.halfstep import routing

        routed = routing(obs, blocks).count()
    if cfg is not None:
        from ..operators.halfstep import hot_columns

        cold = obs.join(F.broadcast(hot_columns(obs, cfg)), F.col("col_id") == F.col("hot_id"), "left_anti").count()
    return ObsStats(int(lengths[0] or 0), int(lengths[1] or 0), int(columns or 0), int(lengths[2] or 0), routed, cold)


def traffic(stats: ObsStats, cfg: FactorConfig, executors: int = 1) -> dict[str, float]:
    """Bytes moved in a half-step by way of gathering; vectors move as they are stored, partial statistics as doubles."""
    d, size, shards = cfg.rank, cfg.bytes_per_number, cfg.blocks or 200
    partials = stats.rows * min(max(stats.mean_row, 1.0), shards)
    hot = min(cfg.hot_columns, max(1, cfg.broadcast_limit // (d * size)), stats.columns)
    cold = stats.cold if stats.cold is not None else stats.cells
    return {
        "broadcast": float(stats.columns * d * size * executors),
        "shuffle": float(stats.cells * d * size),
        "routed": float((stats.routed if stats.routed is not None else min(stats.cells, stats.columns * shards)) * d * size),
        "hot_cold": float((hot * executors + cold) * d * size),
        "partial_stats": float(partials * (d * (d + 3) / 2 + 1) * 8),
    }


def fits_broadcast(stats: ObsStats, cfg: FactorConfig) -> bool:
    return stats.columns * cfg.rank * cfg.bytes_per_number <= cfg.broadcast_limit


def choose_gather(stats: ObsStats, cfg: FactorConfig, executors: int = 1) -> str:
    """Broadcast while the frozen table is within the limit, else the way with the least traffic among those that scale."""
    if fits_broadcast(stats, cfg):
        return "broadcast"
    moved = traffic(stats, cfg, executors)
    moved.pop("broadcast")
    return min(moved, key=lambda k: (moved[k], k))


def cost_report(stats: ObsStats, cfg: FactorConfig, workers: int = 1) -> dict[str, float]:
    """Work of an epoch and what the published formulas say of its traffic, in vector elements and bytes."""
    d = cfg.rank
    return {
        "flops_statistics": float(2 * stats.cells * d * d),
        "flops_solve": float((stats.rows + stats.columns) * d**3),
        "flops_gram": float((stats.rows + stats.columns) * d * d),
        "flops_per_worker": (2 * stats.cells * d * d + (stats.rows + stats.columns) * d**3) / workers,
        "collective_elements": float(stats.cells * d * workers),
        "collective_elements_per_worker": float(stats.cells * d),
        "partial_elements": float(d * d * stats.rows),
        "parameters": float((stats.rows + stats.columns) * d),
        **{f"bytes_{k}": v for k, v in traffic(stats, cfg, workers).items()},
    }


def min_executors(stats: ObsStats, cfg: FactorConfig, memory: int = 16 << 30) -> int:
    """Executors whose memory holds both tables."""
    return max(1, ceil((stats.rows + stats.columns) * cfg.rank * cfg.bytes_per_number / memory))


def scaling_knee(stats: ObsStats, cfg: FactorConfig, flops: float = 5e9, network: float = 1e9, most: int = 4096) -> int:
    """Workers (powers of two) at which fetching vectors takes as long as the work that is divided; beyond it more workers no longer help in proportion."""
    workers, moved = 1, stats.cells * cfg.rank * cfg.bytes_per_number / network
    while workers < most and cost_report(stats, cfg, workers)["flops_per_worker"] / flops > moved:
        workers *= 2
    return workers
