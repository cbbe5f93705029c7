"""Structured Streaming surface."""

from .online import batch_chain, chain_dp, dedup_events, events_stream, join_static, purchases_after_views, run_available, windowed_dp

__all__ = ["batch_chain", "chain_dp", "dedup_events", "events_stream", "join_static", "purchases_after_views", "run_available", "windowed_dp"]
