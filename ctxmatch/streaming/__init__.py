"""Structured Streaming forms: windows, deduplication, joins, state, and scoring of newly announced columns."""
