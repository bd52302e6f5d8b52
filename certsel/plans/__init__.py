"""Plans of the selection engine."""
