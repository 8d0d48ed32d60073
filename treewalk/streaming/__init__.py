"""Structured Streaming: windows, deduplication, joins and first visits over growing logs."""
