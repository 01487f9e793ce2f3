"""Readers of tables, record renderers and sinks."""
