"""Choosing strategies from counts, before a plan is built."""

from .planner import ObsStats, choose_gather, cost_report, min_executors, observe, scaling_knee

__all__ = ["ObsStats", "choose_gather", "cost_report", "min_executors", "observe", "scaling_knee"]
