"""Plans of the local-community engine."""
