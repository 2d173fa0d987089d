"""Structured Streaming: interval makers, ingest, windows."""
