"""Streaming ingest of events and standing cubes."""
