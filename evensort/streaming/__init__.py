"""Streams: windowed counts, late data, joins, and sorting over time."""
