"""Readers of tables, graph builders and sinks."""
