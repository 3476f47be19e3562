"""Operators of the search: tuple sets, counting, frequencies, the grid and its placement, baselines and measures."""
