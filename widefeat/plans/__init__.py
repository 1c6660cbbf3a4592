"""Plans of the wide-table engine."""
