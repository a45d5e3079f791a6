"""Expressions over texts, names and vectors."""
