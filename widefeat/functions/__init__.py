"""Functions of the wide-table engine."""
