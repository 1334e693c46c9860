"""Structured Streaming over event files."""

from .events import batch_twin, event_stream, run_available

__all__ = ["batch_twin", "event_stream", "run_available"]
