"""Streaming of the wide-table engine."""
