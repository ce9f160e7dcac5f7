"""Queries: text, graph, statistics, costs, plans."""
