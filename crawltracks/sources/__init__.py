"""Readers, connectors and the stand-in inputs built on the given tables."""
