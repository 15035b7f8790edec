"""Streams of queries."""
