"""Graphs from tables, files and generators; sinks."""
