"""Sources of the wide-table engine."""
