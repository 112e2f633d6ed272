"""Structured Streaming: event-time windows, deduplication, joins, state, scoring."""
