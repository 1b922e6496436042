"""Streams: lookups and filters against built functions, windows, deduplication, state, joins, rebuilds."""
