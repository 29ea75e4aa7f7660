"""Operators of the local-community engine."""
