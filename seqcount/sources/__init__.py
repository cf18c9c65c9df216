"""Reads from tables and sequence files; sinks."""
