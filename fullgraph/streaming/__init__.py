"""Streams over events: windows, sessions, state, joins, incremental aggregation."""
