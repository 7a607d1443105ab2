"""Fixtures, parsers, readers and sinks."""
