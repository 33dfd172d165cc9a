"""Exact parent-set search on Spark: scores, lattice search, lookup and networks."""
