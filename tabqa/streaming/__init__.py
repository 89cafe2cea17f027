"""Structured Streaming: windows over events, joins, state, ingestion of pages, and a stream of queries."""
