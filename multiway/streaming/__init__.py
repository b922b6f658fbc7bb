"""Streams of events: windows, joins, and sketches that grow with the data."""
