"""Operators on top of the functions: filters, joins, references, identifiers, graphs, and the baselines."""
