"""Distributed operators: partitions, indexes, reachability, joins, baselines."""
