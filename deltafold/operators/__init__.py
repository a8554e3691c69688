"""Operators on keyed states, joins with time, and iterative methods."""
