"""Readers, checks and the stored index."""
