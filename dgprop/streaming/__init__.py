"""Structured Streaming: incremental propagation and event-time operators."""
