"""Structured Streaming: ingest, encode and keep a running top-k; windows over events."""
