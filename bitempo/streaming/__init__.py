"""Structured Streaming: ingest, late data, windows, bursts, reachability, note withdrawal."""
