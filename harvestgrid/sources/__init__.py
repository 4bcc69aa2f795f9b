"""Readers, sinks and adapters of the given tables."""
