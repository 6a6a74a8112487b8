"""Streams of events and of graph insertions."""
