"""Operators that a user of splitters needs: ranks, windows, joins, quantiles, sets, sorted output."""
