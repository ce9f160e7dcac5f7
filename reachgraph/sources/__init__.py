"""Readers and writers: tables as triples, edge rules, N-Triples, index folders."""
