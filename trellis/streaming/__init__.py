"""Streams of events, of queries and of triples."""
