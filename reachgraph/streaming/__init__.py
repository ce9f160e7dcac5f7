"""Streams of events as triples and edges."""
