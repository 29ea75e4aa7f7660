"""Functions of the local-community engine."""
