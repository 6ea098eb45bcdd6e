"""Adapters from tables and files to graph events, and sinks."""
