"""Operators of the wide-table engine."""
