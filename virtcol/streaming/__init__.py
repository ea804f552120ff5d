"""Streams: replay, windows, late data, joins, windowed estimates, standing filters."""
