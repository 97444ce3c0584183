"""Edges that arrive as streams: windows, joins, state, and ranks kept fresh."""
