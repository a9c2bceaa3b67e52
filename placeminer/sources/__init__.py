"""Logs from tables and files, and their sinks."""
