"""Frames over the given tables, generators, sinks."""
