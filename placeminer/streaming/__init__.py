"""Incremental logs and online conformance."""
